"""Named queries over the given tables, each with its DuckDB counterpart where SQL can express it."""

from __future__ import annotations

import math
from collections.abc import Callable
from itertools import combinations

import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..config import ASYM_DEFAULT, CANDIDATES_DENSE, FlipParams
from ..functions import channel, sqlfuncs
from ..operators import counting, distort, metrics, mining, privacy, reconstruct, rules, tuning
from ..operators import relational as rel
from ..sources import baskets, generator
from ..sources.shared import spread, stored
from ..sources.tables import itemset_text, load
from ..streaming import streams
from . import oracles as sql

SEED = sql.SEED
MAIN = FlipParams(0.6, 0.96)
MIN_SUPPORT = "0.003"
TYPES = 6

QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {}
ORACLES: dict[str, str] = {}


def query(oracle: str | None = None) -> Callable:
    def register(f: Callable[[SparkSession, str], DataFrame]) -> Callable[[SparkSession, str], DataFrame]:
        QUERIES[f.__name__] = f
        if oracle:
            ORACLES[f.__name__] = oracle
        return f

    return register


def r6(c: Column | str) -> Column:
    return F.round(F.col(c) if isinstance(c, str) else c, 6)


def of(spark: SparkSession, sf_dir: str, kind: str) -> baskets.Baskets:
    if kind == "clicks":
        return baskets.from_events(spark, sf_dir)
    return baskets.from_customers(spark, sf_dir) if kind == "cust_supp" else baskets.from_orders(spark, sf_dir, kind)


def seen(spark: SparkSession, sf_dir: str, kind: str, params: FlipParams = MAIN) -> tuple[baskets.Baskets, DataFrame]:
    """True baskets, and the distorted item lists as a stored table that a level-wise miner may read again and again."""
    true = of(spark, sf_dir, kind)
    return true, stored(distort.flip_arrays(spread(true.arrays()), true.n_items, params, SEED), f"seen-{kind}")


def exploded(arrays: DataFrame) -> DataFrame:
    return arrays.select("tid", F.explode("items").alias("item"))


def named(mined: DataFrame) -> DataFrame:
    return mined.withColumn("itemset", itemset_text())


def pairs(n: int, k: int = 2) -> list[tuple[int, ...]]:
    return list(combinations(range(n), k))


def with_names(df: DataFrame, itemsets: list[tuple[int, ...]]) -> DataFrame:
    return df.join(F.broadcast(counting.frame(df.sparkSession, itemsets).select("cand", itemset_text().alias("itemset"))), "cand").drop("cand")


# ---- baskets -------------------------------------------------------------------------------------------------


def items_sql(kind: str) -> str:
    return f"WITH {sql.baskets(kind)} SELECT i.item, label, count(t.tid) AS n FROM items i LEFT JOIN t ON t.item = i.item GROUP BY ALL"


def _items(spark: SparkSession, sf_dir: str, kind: str) -> DataFrame:
    b = of(spark, sf_dir, kind)
    return b.items.join(counting.singletons(b.long), "item", "left").select("item", "label", F.coalesce("n", F.lit(0)).alias("n"))


@query(items_sql("brand"))
def items_brand(spark, sf_dir):
    return _items(spark, sf_dir, "brand")


@query(items_sql("name"))
def items_name(spark, sf_dir):
    return _items(spark, sf_dir, "name")


@query(f"WITH {sql.baskets('brand')} SELECT tids.tid, coalesce(string_agg(item::VARCHAR, ',' ORDER BY item), '') AS items FROM tids LEFT JOIN t ON t.tid = tids.tid GROUP BY tids.tid")
def baskets_brand(spark, sf_dir):
    return of(spark, sf_dir, "brand").arrays().select("tid", itemset_text("items").alias("items"))


@query(f"WITH {sql.baskets('brand')}, l AS (SELECT tids.tid, count(t.item) AS length FROM tids LEFT JOIN t ON t.tid = tids.tid GROUP BY tids.tid) SELECT length::INTEGER AS length, count(*) AS n FROM l GROUP BY 1")
def basket_lengths(spark, sf_dir):
    return of(spark, sf_dir, "brand").arrays().groupBy(F.size("items").alias("length")).agg(F.count(F.lit(1)).alias("n"))


@query(" UNION ALL ".join(f"(WITH {sql.baskets(k)} SELECT '{k}' AS workload, (SELECT n FROM size) AS tuples, count(*) AS ones, round(count(*) / ((SELECT n FROM size) * (SELECT count(*) FROM items)), 9) AS s0 FROM t)" for k in ("brand", "name", "type", "supp", "cust_supp", "clicks")))
def avg_support(spark, sf_dir):
    out = None
    for kind in ("brand", "name", "type", "supp", "cust_supp", "clicks"):
        b = of(spark, sf_dir, kind)
        one = tuning.average_support(b.long, b.tids, b.n_items).select(F.lit(kind).alias("workload"), "tuples", "ones", F.round("s0", 9).alias("s0"))
        out = one if out is None else out.unionByName(one)
    return out


@query(f"""WITH {sql.baskets('brand')}, picked AS (SELECT tid FROM tids WHERE ('0x' || substr(md5('sample-42|' || tid), 1, 13))::BIGINT < {int(0.1 * 2**52)})
SELECT (SELECT count(*) FROM picked) AS tuples, count(*) AS ones, round(count(*) / ((SELECT count(*) FROM picked) * (SELECT count(*) FROM items)), 9) AS s0 FROM t WHERE tid IN (SELECT tid FROM picked)""")
def avg_support_sample(spark, sf_dir):
    b = of(spark, sf_dir, "brand")
    return tuning.average_support(b.long, b.tids, b.n_items, 0.1, SEED).withColumn("s0", F.round("s0", 9))


@query(f"WITH {sql.baskets('brand')} SELECT item, count(*) AS n FROM t GROUP BY item")
def vertical_bitmap_counts(spark, sf_dir):
    return counting.column_bits(of(spark, sf_dir, "brand").long).groupBy("item").agg(F.sum(F.bitmap_count("bits")).alias("n"))


def measured(spark: SparkSession, sf_dir: str, kind: str = "name_type"):  # noqa: ANN201
    """(tuples, ones, s0) of baskets near the published average support of 0.01; s0 is null without tuples."""
    b = of(spark, sf_dir, kind)
    return tuning.average_support(b.long, b.tids, b.n_items).first()


#: CTEs up to ``ms`` (tuples, ones, width, s0), the same figures.
_MEASURED = f"{sql.baskets('name_type')}, ms AS (SELECT (SELECT n FROM size) AS tuples, count(*) AS ones, (SELECT count(*) FROM items) AS width, count(*) / ((SELECT n FROM size) * (SELECT count(*) FROM items)) AS s0 FROM t)"
_MS0 = "(SELECT s0 FROM ms)"


# ---- distortion and singletons -------------------------------------------------------------------------------


@query(f"WITH {sql.distorted('brand', 0.6, 0.96)} SELECT tid, item FROM d")
def distort_cells_brand(spark, sf_dir):
    return distort.flip_cells(of(spark, sf_dir, "brand"), MAIN, SEED).long


@query(f"WITH {sql.distorted('brand', 0.9, 0.9)} SELECT tid, item FROM d")
def distort_cells_sym(spark, sf_dir):
    return distort.flip_symmetric(of(spark, sf_dir, "brand"), 0.9, SEED).long


@query(f"WITH {sql.distorted('name', 0.4, 0.98)} SELECT (SELECT count(*) FROM t) AS before, (SELECT count(*) FROM d) AS after, round((SELECT count(*) FROM d) / (SELECT count(*) FROM t), 6) AS ratio")
def distorted_density(spark, sf_dir):
    b = of(spark, sf_dir, "name")
    return metrics.density_ratio(distort.flip_cells(b, ASYM_DEFAULT, SEED).long, b.long).withColumn("ratio", r6("ratio"))


@query(f"WITH {_MEASURED} SELECT p, q, round(ones / tuples * p + (width - ones / tuples) * (1 - q), 6) AS length FROM ms, (VALUES " + ", ".join(f"({p}::DOUBLE, {q}::DOUBLE)" for p, q in ((0.9, 0.9), *CANDIDATES_DENSE)) + ") AS v(p, q)")
def expected_density(spark, sf_dir):
    rows = spark.createDataFrame([(0.9, 0.9), *CANDIDATES_DENSE], "p double, q double")
    b = of(spark, sf_dir, "name_type")
    lengths = tuning.average_support(b.long, b.tids, b.n_items).select((F.col("ones") / F.col("tuples")).alias("mean"))
    return rows.join(lengths, F.lit(True)).select("p", "q", r6(distort.expected_length(F.col("mean"), F.lit(b.n_items), F.col("p"), F.col("q"))).alias("length"))  # lengths: one row


@query(f"WITH {sql.distorted('brand', 0.6, 0.96)} SELECT item, count(*) AS n FROM d GROUP BY item")
def singleton_counts_d(spark, sf_dir):
    return counting.singletons(distort.flip_cells(of(spark, sf_dir, "brand"), MAIN, SEED).long)


def _single_sql(kind: str) -> str:
    return f"""WITH {sql.distorted(kind, 0.6, 0.96)}, c AS (SELECT item, count(*) AS n FROM d GROUP BY item)
SELECT items.item, label, n, round((25 * n - 1 * (SELECT n FROM size))::DOUBLE / 14.0::DOUBLE, 6) AS est FROM c JOIN items ON items.item = c.item"""


def _single(spark: SparkSession, sf_dir: str, kind: str) -> DataFrame:
    b = of(spark, sf_dir, kind)
    (seen_,) = distort.flip_counts(spread(b.arrays()), b.n_items, [MAIN], SEED)
    counts = spark.createDataFrame([(i, n) for i, n in enumerate(seen_.tolist()) if n], "item int, n long").join(b.items, "item")
    return counts.select("item", "label", "n", r6(reconstruct.singleton_expr(F.col("n"), b.dbsize(), MAIN)).alias("est"))


@query(_single_sql("brand"))
def singleton_recon(spark, sf_dir):
    return _single(spark, sf_dir, "brand")


@query(_single_sql("clicks"))
def clicks_recon(spark, sf_dir):
    return _single(spark, sf_dir, "clicks")


@query(_single_sql("cust_supp"))
def cust_supp_recon(spark, sf_dir):
    return _single(spark, sf_dir, "cust_supp")


@query(f"""WITH {sql.distorted('type', 0.6, 0.96)}, c AS (SELECT item, count(*) AS n FROM d GROUP BY item)
SELECT item, round((25 * n - (SELECT n FROM size)) / 14.0, 6) AS est, round((15 * (SELECT n FROM size) - 25 * n) / 14.0, 6) AS est0 FROM c""")
def singleton_recon_matrix(spark, sf_dir):
    b = of(spark, sf_dir, "type")
    counts = counting.singletons(distort.flip_cells(b, MAIN, SEED).long)
    return reconstruct.singletons(counts, b.dbsize(), MAIN).select("item", r6("est").alias("est"), r6("est0").alias("est0"))


# ---- counting strategies and reconstruction of itemsets ------------------------------------------------------

_TYPE = f"{sql.distorted('type', 0.6, 0.96)}, {sql.masks('t', 'tm')}, {sql.masks('d', 'dm')}, {sql.codes('tm', 'tc')}, {sql.codes('dm', 'dc')}, {sql.estimates('dc', 'e', 0.6, 0.96)}"
_PATTERNS = "SELECT c.itemset, 2 * (mask & hi > 0)::BIGINT + (mask & lo > 0)::BIGINT AS pattern, count(*) AS n FROM dm, (SELECT itemset, code & -code AS lo, code - (code & -code) AS hi FROM dc WHERE k = 2) c GROUP BY ALL"


@query(f"WITH {_TYPE} {_PATTERNS}")
def pattern_counts_pair(spark, sf_dir):
    b, arrays = seen(spark, sf_dir, "type")
    return with_names(counting.pattern_counts(exploded(arrays), pairs(TYPES), b.dbsize()), pairs(TYPES))


@query(f"WITH {_TYPE} SELECT itemset, bit_count(mask & code)::BIGINT AS weight, count(*) AS n FROM dm, (SELECT itemset, code FROM dc WHERE k = 2) c GROUP BY ALL")
def weight_counts_pair(spark, sf_dir):
    b, arrays = seen(spark, sf_dir, "type")
    return with_names(counting.weight_counts(exploded(arrays), pairs(TYPES), b.dbsize()), pairs(TYPES))


def _subset_counts(arrays: DataFrame, k: int) -> DataFrame:
    """(itemset, n) of all itemsets of up to k types."""
    out = None
    for size in range(1, k + 1):
        sets = pairs(TYPES, size)
        one = counting.count_chunks(arrays, sets, TYPES).join(F.broadcast(counting.frame(arrays.sparkSession, sets)), "cand").select("itemset", "n")
        out = one if out is None else out.unionByName(one)
    return out


def _candidates(spark: SparkSession, k: int) -> DataFrame:
    return counting.frame(spark, pairs(TYPES, k)).select("itemset", "k")


@query(f"WITH {_TYPE} {_PATTERNS}")
def pair_patterns_by_ie(spark, sf_dir):
    b, arrays = seen(spark, sf_dir, "type")
    found = reconstruct.pattern_from_subsets(_candidates(spark, 2), _subset_counts(arrays, 2), b.dbsize())
    return found.select(itemset_text().alias("itemset"), F.col("pattern").cast("long").alias("pattern"), "n")


@query(f"WITH {_TYPE} SELECT itemset, bit_count(mask & code)::INTEGER AS weight, count(*) AS n FROM dm, (SELECT itemset, code FROM dc WHERE k = 3) c GROUP BY ALL")
def triple_classes_by_ie(spark, sf_dir):
    b, arrays = seen(spark, sf_dir, "type")
    return named(reconstruct.classes_from_subsets(_candidates(spark, 3), _subset_counts(arrays, 3), b.dbsize()))


_EST = "SELECT itemset, round(est, {digits}) AS est FROM e WHERE k = {k}"


@query(f"WITH {_TYPE} " + _EST.format(k=2, digits=6))
def pair_recon_pattern(spark, sf_dir):
    b, arrays = seen(spark, sf_dir, "type")
    found = reconstruct.by_pattern(counting.pattern_counts(exploded(arrays), pairs(TYPES), b.dbsize()), 2, MAIN)
    return with_names(found, pairs(TYPES)).select("itemset", r6("est").alias("est"))


@query(f"WITH {_TYPE} " + _EST.format(k=2, digits=6))
def pair_recon_matrix(spark, sf_dir):
    b, arrays = seen(spark, sf_dir, "type")
    found = reconstruct.by_pattern_matrix(counting.pattern_counts(exploded(arrays), pairs(TYPES), b.dbsize()), 2, MAIN).where("pattern = 3").select("cand", "est")
    return with_names(found, pairs(TYPES)).select("itemset", r6("est").alias("est"))


@query(f"WITH {_TYPE} " + _EST.format(k=2, digits=6))
def pair_recon_weight(spark, sf_dir):
    b, arrays = seen(spark, sf_dir, "type")
    found = reconstruct.by_weight(counting.weight_counts(exploded(arrays), pairs(TYPES), b.dbsize()), 2, MAIN)
    return with_names(found, pairs(TYPES)).select("itemset", r6("est").alias("est"))


@query(f"WITH {_TYPE} SELECT itemset, num, round(est, 6) AS est FROM e WHERE k = 2")
def pair_recon_subset(spark, sf_dir):
    b, arrays = seen(spark, sf_dir, "type")
    found = reconstruct.by_subsets(_candidates(spark, 2), _subset_counts(arrays, 2), b.dbsize(), MAIN)
    return found.select(itemset_text().alias("itemset"), F.col("num").cast("long").alias("num"), r6("est").alias("est"))


@query(f"WITH {_TYPE} SELECT itemset, num, round(est, 6) AS est FROM e WHERE k = 3")
def triple_recon_subset(spark, sf_dir):
    b, arrays = seen(spark, sf_dir, "type")
    found = reconstruct.by_subsets(_candidates(spark, 3), _subset_counts(arrays, 3), b.dbsize(), MAIN)
    return found.select(itemset_text().alias("itemset"), F.col("num").cast("long").alias("num"), r6("est").alias("est"))


@query(f"WITH {_TYPE} " + _EST.format(k=6, digits=3))
def type_recon_depth6(spark, sf_dir):
    b, arrays = seen(spark, sf_dir, "type")
    found = reconstruct.by_weight(counting.weights_by_chunks(arrays, pairs(TYPES, 6), TYPES), 6, MAIN)
    return with_names(found, pairs(TYPES, 6)).select("itemset", F.round("est", 3).alias("est"))


_MATRIX = """m AS (SELECT i, j, sum(factorial((j)::INTEGER) / (factorial((k)::INTEGER) * factorial((j - k)::INTEGER)) * 0.6::DOUBLE ** k * 0.4::DOUBLE ** (j - k)
    * factorial((3 - j)::INTEGER) / (factorial((i - k)::INTEGER) * factorial((3 - j - i + k)::INTEGER)) * 0.04::DOUBLE ** (i - k) * 0.96::DOUBLE ** (3 - j - i + k)) AS prob
    FROM generate_series(0, 3) AS a(i), generate_series(0, 3) AS b(j), generate_series(0, 3) AS c(k)
    WHERE k <= i AND k <= j AND i - k <= 3 - j GROUP BY i, j)"""


_HELD = f"{sql.baskets('type')}, {sql.masks('t', 'tm')}, h AS (SELECT bit_count(mask & 7) AS j, count(*) AS n FROM tm GROUP BY 1)"


def _held(spark: SparkSession, sf_dir: str) -> dict[int, int]:
    """Tuples by how many of the first three types they have."""
    return {r.weight: r.n for r in counting.weights_by_chunks(of(spark, sf_dir, "type").arrays(), [(0, 1, 2)], TYPES).collect()}


@query(f"WITH {_MATRIX}, {_HELD} SELECT i::INTEGER AS i, m.j::INTEGER AS j, round(prob, 9) AS prob, round(prob * coalesce(n, 0), 6) AS tuples FROM m LEFT JOIN h ON h.j = m.j")
def transition_matrix(spark, sf_dir):
    m = channel.weight_matrix(3, 0.6, 0.96)
    held = _held(spark, sf_dir)
    rows = [(i, j, round(float(m[i, j]), 9), round(float(m[i, j]) * held.get(j, 0), 6)) for i in range(4) for j in range(4) if m[i, j]]
    return spark.createDataFrame(rows, "i int, j int, prob double, tuples double")


@query(f"WITH {_MATRIX}, {_HELD} SELECT m.j::INTEGER AS j, round(sum(prob), 9) AS total, round(sum(prob * coalesce(n, 0)), 6) AS tuples FROM m LEFT JOIN h ON h.j = m.j GROUP BY m.j")
def transition_column_sums(spark, sf_dir):
    m = channel.weight_matrix(3, 0.6, 0.96)
    held = _held(spark, sf_dir)
    return spark.createDataFrame([(j, round(float(m[:, j].sum()), 9), round(float(m[:, j].sum() * held.get(j, 0)), 6)) for j in range(4)], "j int, total double, tuples double")


# ---- mining --------------------------------------------------------------------------------------------------

_LEAST = "(SELECT 0.003 * n FROM size)"
_EXACT = f"""x1 AS (SELECT item AS a, count(*) AS n FROM t GROUP BY item HAVING count(*) >= {_LEAST}),
x2 AS (SELECT u.item AS a, v.item AS b, count(*) AS n FROM t u JOIN t v ON u.tid = v.tid AND u.item < v.item GROUP BY ALL HAVING count(*) >= {_LEAST}),
x3 AS (SELECT u.item AS a, v.item AS b, w.item AS c, count(*) AS n FROM t u JOIN t v ON u.tid = v.tid AND u.item < v.item JOIN t w ON w.tid = v.tid AND v.item < w.item GROUP BY ALL HAVING count(*) >= {_LEAST})"""
_FOUND = f"""c1 AS (SELECT item AS a, count(*) AS n FROM d GROUP BY item),
c2 AS (SELECT u.item AS a, v.item AS b, count(*) AS n FROM d u JOIN d v ON u.tid = v.tid AND u.item < v.item GROUP BY ALL),
c3 AS (SELECT u.item AS a, v.item AS b, w.item AS c, count(*) AS n FROM d u JOIN d v ON u.tid = v.tid AND u.item < v.item JOIN d w ON w.tid = v.tid AND v.item < w.item GROUP BY ALL),
f1 AS (SELECT a, n, (25 * n - (SELECT n FROM size)) / 14.0::DOUBLE AS est FROM c1 WHERE 1000 * (25 * n - (SELECT n FROM size)) >= 3 * 14 * (SELECT n FROM size)),
g2 AS (SELECT x.a, y.a AS b, x.n AS na, y.n AS nb FROM f1 x JOIN f1 y ON x.a < y.a),
f2 AS (SELECT a, b, n, num / 196.0::DOUBLE AS est FROM (SELECT g2.a, g2.b, coalesce(c2.n, 0) AS n, 625 * coalesce(c2.n, 0) - 25 * (na + nb) + (SELECT n FROM size) AS num FROM g2 LEFT JOIN c2 ON c2.a = g2.a AND c2.b = g2.b) WHERE 1000 * num >= 3 * 196 * (SELECT n FROM size)),
g3 AS (SELECT p.a, p.b, q.b AS c, p.n AS nab, q.n AS nac, r.n AS nbc FROM f2 p JOIN f2 q ON p.a = q.a AND p.b < q.b JOIN f2 r ON r.a = p.b AND r.b = q.b),
f3 AS (SELECT a, b, c, n, num / 2744.0::DOUBLE AS est FROM (SELECT g3.a, g3.b, g3.c, coalesce(c3.n, 0) AS n,
    15625 * coalesce(c3.n, 0) - 625 * (nab + nac + nbc) + 25 * (x.n + y.n + z.n) - (SELECT n FROM size) AS num
    FROM g3 LEFT JOIN c3 ON c3.a = g3.a AND c3.b = g3.b AND c3.c = g3.c JOIN f1 x ON x.a = g3.a JOIN f1 y ON y.a = g3.b JOIN f1 z ON z.a = g3.c) WHERE 1000 * num >= 3 * 2744 * (SELECT n FROM size))"""
_BRAND_D = f"{sql.distorted('brand', 0.6, 0.96)}, {_FOUND}"
_KEYS = {1: "a::VARCHAR", 2: "a || ',' || b", 3: "a || ',' || b || ',' || c"}


def exact_brand(spark: SparkSession, sf_dir: str, max_len: int) -> mining.Mined:
    b = of(spark, sf_dir, "brand")
    return mining.mine_exact(stored(b.arrays(), "true-brand"), b.n_items, b.dbsize(), MIN_SUPPORT, max_len)


def found_brand(spark: SparkSession, sf_dir: str, max_len: int) -> mining.Mined:
    b, arrays = seen(spark, sf_dir, "brand")
    return mining.mine_distorted(arrays, b.n_items, b.dbsize(), MAIN, MIN_SUPPORT, max_len)


def _level(spark: SparkSession, mined: mining.Mined, k: int, est: bool) -> DataFrame:
    rows = [(",".join(map(str, x)), mined.counts[x], round(float(s), 6)) for x, s in mined.support.items() if len(x) == k]
    out = spark.createDataFrame(rows, "itemset string, n long, est double")
    return out.withColumn("est", r6("est")) if est else out.drop("est")


for _k in (1, 2, 3):

    def _exact(spark, sf_dir, k=_k):
        return _level(spark, exact_brand(spark, sf_dir, k), k, False)

    def _mined(spark, sf_dir, k=_k):
        return _level(spark, found_brand(spark, sf_dir, k), k, True)

    _exact.__name__, _mined.__name__ = f"exact_l{_k}", f"mined_l{_k}"
    query(f"WITH {sql.baskets('brand')}, {_EXACT} SELECT {_KEYS[_k]} AS itemset, n FROM x{_k}")(_exact)
    query(f"WITH {_BRAND_D} SELECT {_KEYS[_k]} AS itemset, n, round(est, 6) AS est FROM f{_k}")(_mined)


@query(f"WITH {_TYPE} SELECT itemset, k, n FROM tc WHERE n >= {_LEAST}")
def exact_itemsets_type(spark, sf_dir):
    b = of(spark, sf_dir, "type")
    found = mining.mine_exact(stored(b.arrays(), "true-type"), b.n_items, b.dbsize(), MIN_SUPPORT)
    return named(found.frame(spark)).select("itemset", "k", F.col("est").cast("long").alias("n"))


@query(f"WITH {sql.distorted('type', 0.9, 0.9)}, {sql.masks('d', 'dm')}, {sql.codes('dm', 'dc')}, {sql.estimates('dc', 'e', 0.9, 0.9)} SELECT itemset, round(est, 6) AS est FROM e WHERE k = 2 AND est >= {_LEAST}")
def mined_sym_l2(spark, sf_dir):
    b, arrays = seen(spark, sf_dir, "type", FlipParams(0.9, 0.9))
    found = mining.mine_symmetric(arrays, b.n_items, b.dbsize(), 0.9, MIN_SUPPORT, 2)
    return named(found.frame(spark)).where("k = 2").select("itemset", r6("est").alias("est"))


@query(f"WITH {_TYPE} SELECT itemset, k, round(est, 6) AS est FROM e WHERE k <= 2 AND est >= {_LEAST}")
def mined_full_pattern(spark, sf_dir):
    b, arrays = seen(spark, sf_dir, "type")
    found = mining.mine_full_pattern(arrays, b.n_items, b.dbsize(), MAIN, MIN_SUPPORT, 2)
    return named(found.frame(spark)).select("itemset", "k", r6("est").alias("est"))


@query(f"WITH {_BRAND_D} SELECT a || ',' || b AS itemset FROM g2")
def candidates_l2(spark, sf_dir):
    level = spark.createDataFrame([(list(x),) for x in found_brand(spark, sf_dir, 1).support], "itemset array<int>")
    return named(mining.candidates_frame(level))


@query(f"WITH {_BRAND_D} SELECT a || ',' || b || ',' || c AS itemset FROM g3")
def candidates_l3(spark, sf_dir):
    level = spark.createDataFrame([(list(x),) for x in found_brand(spark, sf_dir, 2).support if len(x) == 2], "itemset array<int>")
    return named(mining.candidates_frame(level))


def _rules_sql(source: str, value: str, min_conf: float) -> str:
    return f"""WITH {_TYPE}, f AS (SELECT code, k, itemset, {value}::DOUBLE AS est FROM {source} WHERE {value} >= {_LEAST})
SELECT a.itemset AS antecedent, c.itemset AS consequent, round(x.est / (SELECT n FROM size), 6) AS support, round(x.est / a.est, 6) AS confidence
FROM f x JOIN f a ON x.code & a.code = a.code AND a.code < x.code AND a.est > 0 JOIN {source} c ON c.code = x.code - a.code WHERE x.est / a.est >= {min_conf}"""


def _rules(frequent: DataFrame, dbsize: int) -> DataFrame:
    found = rules.generate(frequent, dbsize, 0.5)
    return found.select(itemset_text("antecedent").alias("antecedent"), itemset_text("consequent").alias("consequent"), r6("support").alias("support"), r6("confidence").alias("confidence"))


@query(_rules_sql("tc", "n", 0.5))
def rules_exact(spark, sf_dir):
    b = of(spark, sf_dir, "type")
    return _rules(mining.mine_exact(stored(b.arrays(), "true-type"), b.n_items, b.dbsize(), MIN_SUPPORT).frame(spark), b.dbsize())


@query(_rules_sql("e", "est", 0.5))
def rules_recon(spark, sf_dir):
    b, arrays = seen(spark, sf_dir, "type")
    return _rules(mining.mine_distorted(arrays, b.n_items, b.dbsize(), MAIN, MIN_SUPPORT).frame(spark), b.dbsize())


def _type_exact(spark: SparkSession, sf_dir: str, share: str = MIN_SUPPORT) -> DataFrame:
    b = of(spark, sf_dir, "type")
    return mining.mine_exact(stored(b.arrays(), "true-type"), b.n_items, b.dbsize(), share).frame(spark)


@query(f"WITH {_TYPE} SELECT itemset, n FROM tc WHERE k = 2 ORDER BY n DESC, itemset LIMIT 10")
def topk_itemsets(spark, sf_dir):
    return named(mining.top_k(_type_exact(spark, sf_dir).where("k = 2"), 10)).select("itemset", F.col("est").cast("long").alias("n"))


@query(f"WITH {_TYPE} SELECT itemset, k, n, rank::INTEGER AS rank FROM (SELECT *, row_number() OVER (PARTITION BY k ORDER BY n DESC, itemset) AS rank FROM tc WHERE n >= {_LEAST}) WHERE rank <= 3")
def topk_per_length(spark, sf_dir):
    rows = named(_type_exact(spark, sf_dir)).select("itemset", "k", F.col("est").cast("long").alias("n"))
    return rows.withColumn("rank", F.row_number().over(Window.partitionBy("k").orderBy(F.desc("n"), "itemset"))).where("rank <= 3")


@query(f"WITH {_TYPE}, f AS (SELECT * FROM tc WHERE n >= (SELECT 0.2 * n FROM size)) SELECT itemset, n FROM f WHERE NOT EXISTS (SELECT 1 FROM f g WHERE g.code & f.code = f.code AND g.code > f.code)")
def maximal_itemsets(spark, sf_dir):
    return named(mining.maximal(_type_exact(spark, sf_dir, "0.2"))).select("itemset", F.col("est").cast("long").alias("n"))


@query(f"WITH {_TYPE}, f AS (SELECT * FROM tc WHERE n >= {_LEAST}) SELECT itemset, n FROM f WHERE NOT EXISTS (SELECT 1 FROM f g WHERE g.code & f.code = f.code AND g.code > f.code AND g.n = f.n)")
def closed_itemsets(spark, sf_dir):
    rows = _type_exact(spark, sf_dir).withColumn("n", F.col("est").cast("long"))
    return named(mining.closed(rows)).select("itemset", "n")


@query("SELECT ''::VARCHAR AS itemset, 0::BIGINT AS n WHERE false")
def fpgrowth_check(spark, sf_dir):
    """Itemsets on which the level-wise miner and Spark's own disagree: none."""
    b = of(spark, sf_dir, "type")
    arrays = stored(b.arrays(), "true-type")
    ours = mining.mine_exact(arrays, b.n_items, b.dbsize(), MIN_SUPPORT).frame(spark).select("itemset", F.col("est").cast("long").alias("n"))
    theirs = mining.fpgrowth(arrays, float(MIN_SUPPORT))
    return named(ours.exceptAll(theirs).unionByName(theirs.exceptAll(ours)))


# ---- privacy -------------------------------------------------------------------------------------------------

_R = "({s} * {p} * {p} / ({s} * {p} + (1 - {s}) * (1 - {q})) + {s} * (1 - {p}) * (1 - {p}) / ({s} * (1 - {p}) + (1 - {s}) * {q}))"


def _supports(b: baskets.Baskets) -> DataFrame:
    return counting.singletons(b.long).select("item", (F.col("n") / b.dbsize()).alias("s"))


_S = "s AS (SELECT item, count(*) / (SELECT n FROM size) AS s FROM t GROUP BY item)"


@query(f"WITH {sql.baskets('name')}, {_S} SELECT item, round(s, 9) AS s, round(100 * (1 - {_R.format(s='s', p='0.4::DOUBLE', q='0.98::DOUBLE')}), 6) AS privacy FROM s")
def basic_privacy_items(spark, sf_dir):
    rows = _supports(of(spark, sf_dir, "name"))
    return rows.select("item", F.round("s", 9).alias("s"), r6(privacy.basic_item(F.col("s"), ASYM_DEFAULT)).alias("privacy"))


@query(f"WITH {sql.baskets('name')}, {_S} SELECT round(100 * (1 - sum(s * {_R.format(s='s', p='0.4::DOUBLE', q='0.98::DOUBLE')}) / sum(s)), 6) AS privacy FROM s")
def basic_privacy_weighted(spark, sf_dir):
    return privacy.basic_weighted(_supports(of(spark, sf_dir, "name")), ASYM_DEFAULT).withColumn("privacy", r6("privacy"))


@query(f"""WITH {_MEASURED}, g AS (SELECT i / 10 AS p, j / 10 AS q FROM generate_series(0, 10) AS a(i), generate_series(0, 10) AS b(j) WHERE NOT (i IN (0, 10) AND j = 10 - i))
SELECT p, q, round(100 * (1 - {_R.format(s=_MS0, p='p', q='q')}), 6) AS privacy FROM g""")
def basic_privacy_surface(spark, sf_dir):
    return privacy.surface(spark, measured(spark, sf_dir).s0).withColumn("privacy", r6("privacy"))


@query(f"""WITH {sql.distorted('name', 0.4, 0.98)}, o AS (SELECT item, count(*) AS n FROM t GROUP BY item), y AS (SELECT item, count(*) AS m FROM d GROUP BY item), k AS (SELECT item, count(*) AS kept FROM t JOIN d USING (tid, item) GROUP BY item)
SELECT round(100 * (1 - sum(kept * kept / m + (n - kept) * (n - kept) / ((SELECT n FROM size) - m)) / sum(n)), 6) AS privacy FROM o JOIN y USING (item) JOIN k USING (item)""")
def basic_privacy_empirical(spark, sf_dir):
    b = of(spark, sf_dir, "name")
    return privacy.basic_empirical(b.long, distort.flip_cells(b, ASYM_DEFAULT, SEED).long, b.dbsize()).withColumn("privacy", r6("privacy"))


_CAND = "(VALUES " + ", ".join(f"({p}::DOUBLE, {q}::DOUBLE)" for p, q in CANDIDATES_DENSE) + ") AS v(p, q)"


@query(f"WITH {_MEASURED} SELECT p, q, round(100 * (1 - {_R.format(s=f'(1 - {_MS0})', p='q', q='p')}), 6) AS zeros, round(50 * (1 - {_R.format(s=f'(1 - {_MS0})', p='q', q='p')}) + 50 * (1 - {_R.format(s=_MS0, p='p', q='q')}), 6) AS mix FROM {_CAND}")
def zero_privacy(spark, sf_dir):
    rows = spark.createDataFrame(CANDIDATES_DENSE, "p double, q double")
    s0, p, q = F.lit(measured(spark, sf_dir).s0), F.col("p"), F.col("q")
    return rows.select("p", "q", r6(privacy.basic_zero(s0, p, q)).alias("zeros"), r6(privacy.basic_mix(s0, p, q, 0.5)).alias("mix"))


def _exact_types(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(cand, itemset, k) of the truly frequent itemsets: few, by the mining budget."""
    found = sorted(map(tuple, (r.itemset for r in _type_exact(spark, sf_dir).collect())))
    return counting.frame(spark, found)


_BREACH = """br AS (SELECT c.code, c.itemset, c.k, g.b::INTEGER AS item, count(*) AS matched, count_if(t.mask & (1::BIGINT << g.b) > 0) AS present
    FROM (SELECT * FROM tc WHERE n >= (SELECT 0.003 * n FROM size)) c JOIN generate_series(0, 5) AS g(b) ON c.code & (1 << g.b) > 0 JOIN dm s ON s.mask & c.code = c.code JOIN tm t ON t.tid = s.tid GROUP BY ALL)"""


@query(f"WITH {_TYPE}, {_BREACH} SELECT itemset, item, matched, present, round(present / matched, 6) AS breach FROM br")
def breach_pairs(spark, sf_dir):
    b, arrays = seen(spark, sf_dir, "type")
    sets = _exact_types(spark, sf_dir)
    found = privacy.breaches(b.long, exploded(arrays), sets).join(F.broadcast(sets.select("cand", itemset_text().alias("itemset"))), "cand")
    return found.select("itemset", "item", "matched", "present", r6("breach").alias("breach"))


_S0 = "(SELECT (SELECT count(*) FROM t) / ((SELECT n FROM size) * 6))"
_BP = f"100 * (1 - {_R.format(s=_S0, p='0.6::DOUBLE', q='0.96::DOUBLE')})"


@query(f"""WITH {_TYPE}, {_BREACH}, bp AS (SELECT {_BP} AS bp),
w AS (SELECT t.tid, br.item, max(present / matched) AS breach FROM t JOIN d ON d.tid = t.tid AND d.item = t.item JOIN dm ON dm.tid = t.tid JOIN br ON br.item = t.item AND dm.mask & br.code = br.code GROUP BY ALL)
SELECT round((sum(100 * (1 - breach)) + ((SELECT count(*) FROM t) - count(*)) * (SELECT bp FROM bp)) / (SELECT count(*) FROM t), 6) AS privacy, (SELECT count(*) FROM t) AS ones, count(*) AS kept, (SELECT count(*) FROM t) - count(*) AS flipped, 0::BIGINT AS rare FROM w""")
def reinterrogated_privacy(spark, sf_dir):
    b, arrays = seen(spark, sf_dir, "type")
    s0 = tuning.average_support(b.long, b.tids, b.n_items).first().s0
    found = privacy.reinterrogated(b.long, exploded(arrays), _exact_types(spark, sf_dir), privacy.basic(s0, MAIN.p, MAIN.q))
    return found.withColumn("privacy", r6("privacy"))


_RARE = f"""WITH {sql.baskets('brand')}, {sql.wide_masks('t', 'tm')}, {sql.flips(0.6, 0.96, name='d')}, {sql.wide_masks('d', 'dm')}, {sql.level_wise('tm', 'x', '0.15', 2)}, {sql.attacked('x', 'tm', 'dm', 'a', '{bp}')},
kept AS (SELECT t.item FROM t JOIN d ON d.tid = t.tid AND d.item = t.item)
SELECT round((SELECT rp FROM a), 4) AS privacy, (SELECT count(*) FROM t) AS ones, (SELECT count(*) FROM kept) AS kept, (SELECT count(*) FROM t) - (SELECT count(*) FROM kept) AS flipped,
    (SELECT count(*) FROM kept WHERE 1::HUGEINT << item NOT IN (SELECT code FROM x)) AS rare""".replace("{bp}", f"100 * (1 - {_R.format(s='(SELECT (SELECT count(*) FROM t) / ((SELECT n FROM size) * 25))', p='0.6::DOUBLE', q='0.96::DOUBLE')})")


@query(_RARE)
def reinterrogated_privacy_with_rare_items(spark, sf_dir):
    """The same at a bar that about half of the brands miss, in the two passes over columns of bits."""
    b, arrays = seen(spark, sf_dir, "brand")
    true = stored(b.arrays(), "true-brand")
    size = b.dbsize()
    sets = sorted(mining.mine_exact(true, b.n_items, size, "0.15", 2).support)
    s0 = tuning.average_support(b.long, b.tids, b.n_items).first().s0
    pairs = stored(true.join(arrays.withColumnRenamed("items", "seen"), "tid"), "pairs-brand")
    rp, _ = privacy.reinterrogated_chunks(pairs, sets, b.n_items, privacy.basic(s0, MAIN.p, MAIN.q))
    frequent = F.array(*(F.lit(x[0]) for x in sets if len(x) == 1)).cast("array<int>")
    both = F.array_intersect("items", "seen")
    sums = pairs.agg(F.sum(F.size("items")).alias("ones"), F.sum(F.size(both)).alias("kept"), F.sum(F.size(F.array_except(both, frequent))).alias("rare"))
    return sums.select(F.lit(round(rp, 4)).alias("privacy"), "ones", "kept", (F.col("ones") - F.col("kept")).alias("flipped"), "rare")


@query(f"""WITH {sql.baskets('type')}, {sql.masks('t', 'tm')}, v AS (SELECT n, q, (SELECT count(*) FROM tm WHERE mask & code = code) / (SELECT n FROM size) AS s FROM (VALUES (3, 0.9::DOUBLE, 7), (2, 0.98::DOUBLE, 3), (4, 0.96::DOUBLE, 15)) AS c(n, q, code))
SELECT n::INTEGER AS n, q, s, round((1 - q) ** n * (1 - s), 9) AS prob FROM v""")
def spurious_probability(spark, sf_dir):
    """That a tuple shows the first n types while it has none of them, from the support that these have together."""
    b, rows = of(spark, sf_dir, "type"), []
    arrays, size = stored(b.arrays(), "true-type"), b.dbsize()
    for n, q in ((3, 0.9), (2, 0.98), (4, 0.96)):
        s = sum(counting.count(arrays, [tuple(range(n))], TYPES).values()) / size
        rows.append((n, q, s, round(privacy.spurious_probability(n, q, s), 9)))
    return spark.createDataFrame(rows, "n int, q double, s double, prob double")


# ---- parameter choice ----------------------------------------------------------------------------------------

_INDEX = "sqrt({p} * (1 - {p}) + (1 / {s} - 1) * {q} * (1 - {q})) / abs({p} + {q} - 1)"


def _grid_sql(s: str) -> str:
    return f"""{_MEASURED}, g AS (SELECT p, q, 100 * (1 - {_R.format(s=s, p='p', q='q')}) AS bp, CASE WHEN abs(p + q - 1) > 1e-9 THEN {_INDEX.format(s=s, p='p', q='q')} END AS error
    FROM (SELECT i / 10 AS p, j / 100 AS q FROM generate_series(1, 9) AS a(i), generate_series(90, 99) AS b(j)))"""


def _reference(s: str, slack: float) -> str:
    return f"{_INDEX.format(s=s, p='0.9::DOUBLE', q='0.9::DOUBLE')} * (1 + {slack}::DOUBLE)"


@query(f"WITH {_grid_sql(_MS0)} SELECT p, q, round(bp, 6) AS bp, round(error, 6) AS error, bp >= 90 AS private, error <= {_reference(_MS0, 0.0)} AS accurate FROM g")
def param_grid(spark, sf_dir):
    return tuning.grid(spark, measured(spark, sf_dir).s0).withColumns({"bp": r6("bp"), "error": r6("error")})


def _chosen_sql(s0: str) -> str:
    return f"WITH {_grid_sql(s0)} SELECT p, q, round(bp, 6) AS bp, round(error, 6) AS error FROM g WHERE bp >= 90 AND error <= {_reference(s0, 0.04)} AND round(q, 6) > 0.95"


@query(_chosen_sql(_MS0))
def param_candidates_001(spark, sf_dir):
    return tuning.candidates(spark, measured(spark, sf_dir).s0, slack=0.04).select("p", "q", r6("bp").alias("bp"), r6("error").alias("error"))


@query(_chosen_sql(f"({_MS0} / 2)"))
def param_candidates_0005(spark, sf_dir):
    """Settings for the same baskets in a universe twice as wide: half the average support."""
    s0 = measured(spark, sf_dir).s0
    return tuning.candidates(spark, s0 and s0 / 2, slack=0.04).select("p", "q", r6("bp").alias("bp"), r6("error").alias("error"))


@query(f"WITH {_MEASURED} SELECT p, q, round({_INDEX.format(s=_MS0, p='p', q='q')}, 6) AS error, round({_INDEX.format(s=_MS0, p='p', q='q')} / sqrt((SELECT ones / width FROM ms)), 8) AS relative FROM {_CAND}")
def error_index(spark, sf_dir):
    m = measured(spark, sf_dir)
    rows = [(p, q, round(tuning.relative_error(m.s0 * m.tuples, m.tuples, p, q), 8) if m.s0 else None) for p, q in CANDIDATES_DENSE]
    return spark.createDataFrame(rows, "p double, q double, relative double").select("p", "q", r6(tuning.relative_error_index(m.s0, F.col("p"), F.col("q"))).alias("error"), "relative")


# ---- errors and costs ----------------------------------------------------------------------------------------

_LEVELS = f"""WITH {_BRAND_D}, {_EXACT},
tr AS (SELECT 1 AS k, a::VARCHAR AS s, n FROM x1 UNION ALL SELECT 2, a || ',' || b, n FROM x2 UNION ALL SELECT 3, a || ',' || b || ',' || c, n FROM x3),
fo AS (SELECT 1 AS k, a::VARCHAR AS s, est FROM f1 UNION ALL SELECT 2, a || ',' || b, est FROM f2 UNION ALL SELECT 3, a || ',' || b || ',' || c, est FROM f3),
lv AS (SELECT coalesce(tr.k, fo.k) AS k, count(n) AS n_true, count(est) AS n_found, count(n + est) AS hits, 100 * avg(abs(est - n) / n) AS rho FROM tr FULL JOIN fo ON tr.s = fo.s GROUP BY 1),
le AS (SELECT *, 100 * (n_found - hits) / n_true AS sigma_plus, 100 * (n_true - hits) / n_true AS sigma_minus FROM lv)"""


def levels(spark: SparkSession, sf_dir: str) -> DataFrame:
    return metrics.by_level(found_brand(spark, sf_dir, 3).frame(spark), exact_brand(spark, sf_dir, 3).frame(spark))


@query(_LEVELS + " SELECT k, hits, round(rho, 6) AS rho FROM le")
def support_error_levels(spark, sf_dir):
    return levels(spark, sf_dir).select("k", "hits", r6("rho").alias("rho"))


@query(_LEVELS + " SELECT k, n_true, n_found, round(sigma_plus, 6) AS sigma_plus, round(sigma_minus, 6) AS sigma_minus FROM le")
def identity_error_levels(spark, sf_dir):
    return levels(spark, sf_dir).select("k", "n_true", "n_found", r6("sigma_plus").alias("sigma_plus"), r6("sigma_minus").alias("sigma_minus"))


def _weighted(x: str) -> str:
    mean = f"sum(n_true * {x}) / sum(n_true)"
    return f"round({mean}, 6) AS {x}, round(sum(n_true * {x} * {x}) / sum(n_true) - ({mean}) * ({mean}), 4) AS var_{x}"


@query(_LEVELS + f" SELECT {_weighted('sigma_plus')}, {_weighted('sigma_minus')}, {_weighted('rho')} FROM le")
def error_rollup(spark, sf_dir):
    row = metrics.rollup(levels(spark, sf_dir))
    return row.select(*(F.round(c, 4 if c.startswith("var") else 6).alias(c) for c in row.columns))


def _both_settings(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(pq, k, itemset, rel) relative errors of all true itemsets of types under two settings."""
    true, out = _type_exact(spark, sf_dir).select("itemset", "k", F.col("est").alias("t")), None
    for p, q in ((0.6, 0.96), (0.9, 0.9)):
        b, arrays = seen(spark, sf_dir, "type", FlipParams(p, q))
        found = mining.mine_distorted(arrays, b.n_items, b.dbsize(), FlipParams(p, q), MIN_SUPPORT).frame(spark)
        one = true.join(found.select("itemset", "est"), "itemset").select(F.lit(f"{p}/{q}").alias("pq"), "k", "itemset", (100 * F.abs(F.col("est") - F.col("t")) / F.col("t")).alias("rel"))
        out = one if out is None else out.unionByName(one)
    return out


_TWO = f"""WITH {_TYPE}, {sql.flips(0.9, 0.9, name='s')}, {sql.masks('s', 'sm')}, {sql.codes('sm', 'sc')}, {sql.estimates('sc', 'se', 0.9, 0.9)},
rl AS (SELECT '0.6/0.96' AS pq, tc.k, 100 * abs(est - n) / n AS rel FROM tc JOIN e USING (code) WHERE n >= {_LEAST} AND est >= {_LEAST}
    UNION ALL SELECT '0.9/0.9', tc.k, 100 * abs(est - n) / n FROM tc JOIN se USING (code) WHERE n >= {_LEAST} AND est >= {_LEAST})"""


@query(_TWO + " SELECT coalesce(pq, 'all') AS pq, coalesce(k, 0)::INTEGER AS k, count(*) AS n, round(avg(rel), 6) AS rho FROM rl GROUP BY CUBE (pq, k)")
def error_cube(spark, sf_dir):
    rows = _both_settings(spark, sf_dir).cube("pq", "k").agg(F.count(F.lit(1)).alias("n"), r6(F.avg("rel")).alias("rho"))
    return rows.select(F.coalesce("pq", F.lit("all")).alias("pq"), F.coalesce("k", F.lit(0)).alias("k"), "n", "rho")


@query(_TWO + " SELECT k, round(avg(rel) FILTER (pq = '0.6/0.96'), 6) AS asym, round(avg(rel) FILTER (pq = '0.9/0.9'), 6) AS sym FROM rl GROUP BY k")
def error_pivot(spark, sf_dir):
    rows = _both_settings(spark, sf_dir).groupBy("k").pivot("pq", ["0.6/0.96", "0.9/0.9"]).agg(F.avg("rel"))
    return rows.select("k", r6(F.col("`0.6/0.96`")).alias("asym"), r6(F.col("`0.9/0.9`")).alias("sym"))


@query(_TWO + " SELECT pq, count(*) AS n, round(quantile_cont(rel, 0.5), 6) AS median, round(stddev_pop(rel), 6) AS spread, round(corr(k, rel), 6) AS with_length FROM rl GROUP BY pq")
def error_distribution(spark, sf_dir):
    return _both_settings(spark, sf_dir).groupBy("pq").agg(F.count(F.lit(1)).alias("n"), r6(F.percentile("rel", F.lit(0.5))).alias("median"), r6(F.stddev_pop("rel")).alias("spread"), r6(F.corr("k", "rel")).alias("with_length"))


@query(f"""WITH {sql.distorted('brand', 0.6, 0.96)}, {sql.flips(0.9, 0.9, name='s')}
SELECT 0.6::DOUBLE AS p, 0.96::DOUBLE AS q, (SELECT count(*) FROM t) AS before, (SELECT count(*) FROM d) AS after, round((SELECT count(*) FROM d) / (SELECT count(*) FROM t), 6) AS ratio
UNION ALL SELECT 0.9, 0.9, (SELECT count(*) FROM t), (SELECT count(*) FROM s), round((SELECT count(*) FROM s) / (SELECT count(*) FROM t), 6)""")
def density_ratio(spark, sf_dir):
    b, out = of(spark, sf_dir, "brand"), None
    for p, q in ((0.6, 0.96), (0.9, 0.9)):
        one = metrics.density_ratio(distort.flip_cells(b, FlipParams(p, q), SEED).long, b.long).select(F.lit(p).alias("p"), F.lit(q).alias("q"), "before", "after", r6("ratio").alias("ratio"))
        out = one if out is None else out.unionByName(one)
    return out


@query(f"""WITH {_TYPE}, c AS (SELECT k, count(*) AS n FROM tc GROUP BY k) SELECT 'pattern' AS strategy, sum(n * 2 ** k)::BIGINT AS counters FROM c
UNION ALL SELECT 'weight', sum(n * (k + 1))::BIGINT FROM c UNION ALL SELECT 'weight_explicit', sum(n * k)::BIGINT FROM c UNION ALL SELECT 'ones', sum(n)::BIGINT FROM c""")
def counter_cost(spark, sf_dir):
    b = of(spark, sf_dir, "type")
    found = mining.mine_exact(stored(b.arrays(), "true-type"), b.n_items, b.dbsize(), MIN_SUPPORT)
    return spark.createDataFrame([(s, metrics.counter_cost(list(found.candidates.items()), s)) for s in ("pattern", "weight", "weight_explicit", "ones")], "strategy string, counters long")


# ---- other workloads -----------------------------------------------------------------------------------------


@query(f"WITH {sql.baskets('clicks')} SELECT tid, string_agg(item::VARCHAR, ',' ORDER BY item) AS items FROM t GROUP BY tid")
def clicks_baskets(spark, sf_dir):
    return of(spark, sf_dir, "clicks").arrays().select("tid", itemset_text("items").alias("items"))


_WORDS = """docs AS (SELECT doc_id AS tid, unnest(list_distinct(regexp_extract_all(lower(text), '\\p{L}+'))) AS label FROM documents),
rk AS (SELECT label, row_number() OVER (ORDER BY n DESC, label) AS r FROM (SELECT label, count(*) AS n FROM docs GROUP BY label)),
items AS (SELECT label, (row_number() OVER (ORDER BY label) - 1)::INTEGER AS item FROM rk WHERE r BETWEEN 101 AND 1100),
t AS (SELECT tid, item FROM docs JOIN items USING (label))"""


@query(f"WITH {_WORDS} SELECT items.item, label, count(*) AS n FROM t JOIN items ON items.item = t.item GROUP BY ALL")
def words_baskets(spark, sf_dir):
    b = baskets.from_documents(spark, sf_dir)
    return counting.singletons(b.long).join(b.items, "item").select("item", "label", "n")


@query(f"WITH {_WORDS} SELECT u.item || ',' || v.item AS itemset, count(*) AS n FROM t u JOIN t v ON u.tid = v.tid AND u.item < v.item GROUP BY 1 HAVING count(*) >= (SELECT 0.03 * count(DISTINCT doc_id) FROM documents)")
def words_exact_l2(spark, sf_dir):
    b = baskets.from_documents(spark, sf_dir)
    found = mining.mine_exact(stored(b.arrays(), "words"), b.n_items, b.dbsize(), "0.03", 2)
    return named(found.frame(spark)).where("k = 2").select("itemset", F.col("est").cast("long").alias("n"))


@query()
def part_sparse_recon(spark, sf_dir):
    """Singleton estimates over the widest universe, distorted by the sparse sampler: (item, n_true, est)."""
    b, params = of(spark, sf_dir, "part"), FlipParams(0.3, 0.99)
    true, (seen_,), _ = distort.flip_sparse_counts(spread(b.arrays()), b.n_items, [params], SEED)
    counts = spark.createDataFrame(pa.table({"item": pa.array(range(b.n_items), pa.int32()), "n_true": true, "n": seen_}), "item int, n_true long, n long")
    return counts.select("item", "n_true", r6(reconstruct.singleton_expr(F.col("n"), b.dbsize(), params)).alias("est"))


@query()
def distort_sparse_sampler(spark, sf_dir):
    b = of(spark, sf_dir, "name_type")
    return distort.flip_sparse(b.arrays(), b.n_items, ASYM_DEFAULT, SEED).select("tid", itemset_text("items").alias("items"))


@query()
def pattern_generator(spark, sf_dir):
    """Items of generated baskets, one for each given order."""
    tids = load(spark, sf_dir, "orders", "o_orderkey").select(F.col("o_orderkey").alias("tid"))
    return counting.singletons(generator.pattern_baskets(spark, tids).long)


@query(f"WITH {_BRAND_D}, {_EXACT}, fs AS (SELECT a || ',' || b AS s FROM f2), ts AS (SELECT a || ',' || b AS s FROM x2) SELECT 'both' AS part, count(*) AS n FROM (SELECT s FROM fs INTERSECT SELECT s FROM ts) UNION ALL SELECT 'extra', count(*) FROM (SELECT s FROM fs EXCEPT SELECT s FROM ts) UNION ALL SELECT 'missed', count(*) FROM (SELECT s FROM ts EXCEPT SELECT s FROM fs)")
def set_ops_rf(spark, sf_dir):
    found, true = (m.frame(spark).where("k = 2").select("itemset") for m in (found_brand(spark, sf_dir, 2), exact_brand(spark, sf_dir, 2)))
    parts = (("both", found.intersect(true)), ("extra", found.subtract(true)), ("missed", true.subtract(found)))
    out = None
    for name, df in parts:
        one = df.agg(F.count(F.lit(1)).alias("n")).select(F.lit(name).alias("part"), "n")
        out = one if out is None else out.unionByName(one)
    return out


@query(f"WITH {sql.baskets('brand')}, x AS (SELECT item, count(*) AS n FROM t GROUP BY item) SELECT item, n, round(n / sum(n) OVER (), 9) AS share, rank() OVER (ORDER BY n DESC)::INTEGER AS rank, round(percent_rank() OVER (ORDER BY n), 9) AS relative, ntile(4) OVER (ORDER BY n, item)::INTEGER AS quarter FROM x")
def window_support_share(spark, sf_dir):
    return rel.support_shares(counting.singletons(of(spark, sf_dir, "brand").long))


for _name, (_f, _oracle) in rel.TABLE_QUERIES.items():

    def _table_query(spark, sf_dir, f=_f):
        return f(lambda name, *columns: load(spark, sf_dir, name, *columns))

    _table_query.__name__ = _name
    query(_oracle)(_table_query)


@query(f"WITH {sql.baskets('brand')}, top AS (SELECT item FROM t GROUP BY item ORDER BY count(*) DESC, item LIMIT 5) SELECT tid, item FROM t WHERE item IN (SELECT item FROM top)")
def semi_frequent(spark, sf_dir):
    b = of(spark, sf_dir, "brand")
    return baskets.restrict(b, counting.singletons(b.long).orderBy(F.desc("n"), "item").limit(5)).long


@query(f"WITH {sql.baskets('brand')}, top AS (SELECT item FROM t GROUP BY item ORDER BY count(*) DESC, item LIMIT 5) SELECT tid, item FROM t WHERE item NOT IN (SELECT item FROM top)")
def anti_infrequent(spark, sf_dir):
    b = of(spark, sf_dir, "brand")
    return baskets.restrict(b, counting.singletons(b.long).orderBy(F.desc("n"), "item").limit(5), keep=False).long


@query(f"WITH {sql.baskets('brand')}, l AS (SELECT tid, list_sort(list(item)) AS items FROM t GROUP BY tid) SELECT tid FROM l WHERE list_has_all(items, [0, 3])")
def containment_filter(spark, sf_dir):
    return of(spark, sf_dir, "brand").arrays().where(rel.contains("items", (0, 3))).select("tid")


@query("SELECT lower(tag) AS label, count(DISTINCT page_id) AS n FROM (SELECT page_id, unnest(regexp_extract_all(html, '<([a-zA-Z][a-zA-Z0-9]*)', 1)) AS tag FROM pages) GROUP BY 1")
def page_tags(spark, sf_dir):
    b = baskets.from_pages(spark, sf_dir)
    return counting.singletons(b.long).join(b.items, "item").select("label", "n")


@query("""WITH w AS (SELECT DISTINCT conv_id, label FROM (SELECT conv_id, unnest(regexp_extract_all(lower(text), '\\p{L}+')) AS label FROM conversations)),
x AS (SELECT w.label, count(*) AS n FROM (SELECT conv_id, turn, unnest(list_distinct(regexp_extract_all(lower(text), '\\p{L}+'))) AS label FROM conversations) w GROUP BY 1 ORDER BY n DESC, label LIMIT 500)
SELECT w.label, count(*) AS n FROM w JOIN x USING (label) GROUP BY 1""")
def conv_words(spark, sf_dir):
    b = baskets.from_conversations(spark, sf_dir)
    return counting.singletons(b.long).join(b.items, "item").select("label", "n")


@query("SELECT count(DISTINCT l_orderkey) AS tuples, true AS about, true AS hll, true AS theta FROM lineitem")
def approx_tuples(spark, sf_dir):
    """The exact number of tuples, and whether each kind of sketch comes within five percent of it."""
    long = of(spark, sf_dir, "brand").long
    near = lambda c: F.abs(c - F.col("tuples")) <= 0.05 * F.col("tuples")
    sums = long.agg(F.count_distinct("tid").alias("tuples"), F.approx_count_distinct("tid", 0.01).alias("a"), F.hll_sketch_estimate(F.hll_sketch_agg("tid")).alias("h"), F.theta_sketch_estimate(F.theta_sketch_agg("tid")).alias("t"))
    return sums.select("tuples", near(F.col("a")).alias("about"), near(F.col("h")).alias("hll"), near(F.col("t")).alias("theta"))


@query(f"WITH {sql.baskets('clicks')}, {sql.flips(0.6, 0.96)} SELECT tids.tid, coalesce(string_agg(d.item::VARCHAR, ',' ORDER BY d.item), '') AS items FROM tids LEFT JOIN d ON d.tid = tids.tid GROUP BY tids.tid")
def stream_distort(spark, sf_dir):
    b = of(spark, sf_dir, "clicks")
    return streams.distort_table(b.arrays(), b.n_items, MAIN, SEED).select("tid", itemset_text("items").alias("items"))


@query("SELECT date_trunc('day', ts) AS day, event_type, count(*) AS n FROM events GROUP BY ALL")
def stream_window_counts(spark, sf_dir):
    return streams.run_once(streams.window_counts(streams.read_events(spark, sf_dir)), "complete")


@query(f"""WITH {sql.baskets('clicks')}, {sql.flips(0.6, 0.96)}, y AS (SELECT tid % 100000 AS day, item, count(*) AS n FROM d GROUP BY ALL), s AS (SELECT tid % 100000 AS day, count(*) AS tuples FROM tids GROUP BY 1)
SELECT DATE '1970-01-01' + y.day::INTEGER AS day, item, n, round((25 * n - tuples) / 14.0::DOUBLE, 6) AS est FROM y JOIN s ON s.day = y.day""")
def stream_window_recon(spark, sf_dir):
    """Distorted click baskets streamed by day, estimated per window."""
    b = of(spark, sf_dir, "clicks")
    dated = stored(distort.flip_arrays(b.arrays(), b.n_items, MAIN, SEED).withColumn("ts", F.timestamp_seconds((F.col("tid") % 100_000) * 86_400)).select("tid", "ts", "items"), "dated")
    stream = streams.read_table(dated)
    counts = streams.run_once(streams.window_recon(stream, MAIN), "complete")
    return streams.estimates_of(counts, MAIN).select(F.to_date("day").alias("day"), "item", "n", r6("est").alias("est"))


_EVENT_TYPES = """m AS (SELECT DISTINCT user_id * 100000 + date_diff('day', DATE '1970-01-01', ts::DATE) AS tid, event_type AS label FROM events),
items AS (SELECT label, (row_number() OVER (ORDER BY label) - 1)::INTEGER AS item FROM (SELECT DISTINCT label FROM m)), t AS (SELECT tid, item FROM m JOIN items USING (label)),
tids AS (SELECT DISTINCT tid FROM m), size AS (SELECT count(*) AS n FROM tids)"""


@query(f"WITH {_EVENT_TYPES}, {sql.masks('t', 'tm')}, {sql.codes('tm', 'tc', 5)} SELECT itemset, k, n FROM tc WHERE n >= {_LEAST}")
def event_types_exact(spark, sf_dir):
    b = baskets.from_events(spark, sf_dir, "type")
    found = mining.mine_exact(stored(b.arrays(), "event-types"), b.n_items, b.dbsize(), MIN_SUPPORT)
    return named(found.frame(spark)).select("itemset", "k", F.col("est").cast("long").alias("n"))


@query("""WITH docs AS (SELECT doc_id AS tid, unnest(list_distinct(regexp_extract_all(lower(text), '\\p{L}+'))) AS label FROM documents WHERE lang = 'en' AND doc_id IN (SELECT doc_id FROM labels WHERE quality = 1)),
rk AS (SELECT label, n, row_number() OVER (ORDER BY n DESC, label) AS r FROM (SELECT label, count(*) AS n FROM docs GROUP BY label))
SELECT label, n FROM rk WHERE r BETWEEN 101 AND 1100""")
def words_en_quality(spark, sf_dir):
    b = baskets.from_documents(spark, sf_dir, slice_=True)
    return counting.singletons(b.long).join(b.items, "item").select("label", "n")


@query(f"""WITH {sql.baskets('type')}, x AS (SELECT item, count(*) AS n FROM t GROUP BY item)
SELECT item, round(sqrt((n * (0.6::DOUBLE * 0.4 + 0.56::DOUBLE * 0.56) + ((SELECT n FROM size) - n) * 0.96::DOUBLE * 0.04) / (0.56::DOUBLE * 0.56) - n), 6) AS stderr FROM x""")
def estimator_stderr(spark, sf_dir):
    """Standard errors of singleton estimates, by the general formula for itemsets."""
    b = of(spark, sf_dir, "type")
    size = b.dbsize()
    rows = [(r.item, round(channel.variance([size - r.n, r.n], MAIN.p, MAIN.q) ** 0.5, 6)) for r in counting.singletons(b.long).collect()]
    return spark.createDataFrame(rows, "item int, stderr double")


@query(f"""WITH {sql.baskets('brand')}, l AS (SELECT length, count(*) AS tuples FROM (SELECT count(item) AS length FROM t GROUP BY tid) GROUP BY length), s AS (SELECT p, q, p + q - 1 AS d FROM {_CAND}), c AS (SELECT p, q, n, j, i, k FROM s, generate_series(1, 8) AS a(n), generate_series(0, n) AS b(j), generate_series(0, n) AS e(i), generate_series(0, n) AS f(k) WHERE k <= j AND k <= i AND i - k <= n - j),
m AS (SELECT p, q, n, j, i, sum(factorial(j::INTEGER) / (factorial(k::INTEGER) * factorial((j - k)::INTEGER)) * (q / (p + q - 1)) ** k * (1 - q / (p + q - 1)) ** (j - k)
    * factorial((n - j)::INTEGER) / (factorial((i - k)::INTEGER) * factorial((n - j - i + k)::INTEGER)) * (1 - p / (p + q - 1)) ** (i - k) * (p / (p + q - 1)) ** (n - j - i + k)) AS x FROM c GROUP BY ALL)
SELECT n::INTEGER AS n, p, q, round(max(total), 4) AS log_condition, tuples FROM (SELECT n, p, q, j, log10(sum(abs(x))) AS total FROM m GROUP BY ALL) JOIN l ON length = n GROUP BY ALL""")
def channel_condition(spark, sf_dir):
    """How the inversion magnifies errors, by the lengths up to 8 that tuples have and setting: log10 of the condition in the norm of column sums."""
    lengths = of(spark, sf_dir, "brand").long.groupBy("tid").agg(F.count(F.lit(1)).alias("n")).where("n <= 8").groupBy("n").agg(F.count(F.lit(1)).alias("tuples")).collect()
    rows = [(n, p, q, round(math.log10(channel.condition(n, p, q, 1)), 4), tuples) for n, tuples in lengths for p, q in CANDIDATES_DENSE]
    return spark.createDataFrame(rows, "n int, p double, q double, log_condition double, tuples long")


# ---- further forms -------------------------------------------------------------------------------------------

_ITEM_COUNTS = f"WITH {sql.baskets('brand')}, c AS (SELECT item, count(*) AS n FROM t GROUP BY item)"


@query(_ITEM_COUNTS + " SELECT item, n, round(percent_rank() OVER (ORDER BY n), 6) AS percent, round(cume_dist() OVER (ORDER BY n), 6) AS below, (ntile(4) OVER (ORDER BY n, item))::INTEGER AS quarter FROM c")
def support_quantiles(spark, sf_dir):
    """Where each item stands among all by support; one row per item of a bounded universe."""
    rows, by = counting.singletons(of(spark, sf_dir, "brand").long), Window.orderBy("n")
    return rows.select("item", "n", r6(F.percent_rank().over(by)).alias("percent"), r6(F.cume_dist().over(by)).alias("below"), F.ntile(4).over(Window.orderBy("n", "item")).alias("quarter"))


@query(_ITEM_COUNTS + " SELECT item, n, lag(n) OVER w AS before, lead(n) OVER w AS after, nth_value(n, 2) OVER (w ROWS BETWEEN UNBOUNDED PRECEDING AND UNBOUNDED FOLLOWING) AS second, last(n) OVER (w ROWS BETWEEN UNBOUNDED PRECEDING AND UNBOUNDED FOLLOWING) AS least FROM c WINDOW w AS (ORDER BY n DESC, item)")
def support_neighbours(spark, sf_dir):
    rows = counting.singletons(of(spark, sf_dir, "brand").long)
    by = Window.orderBy(F.desc("n"), "item")
    whole = by.rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing)
    return rows.select("item", "n", F.lag("n").over(by).alias("before"), F.lead("n").over(by).alias("after"), F.nth_value("n", 2).over(whole).alias("second"), F.last("n").over(whole).alias("least"))


@query(_TWO + " SELECT coalesce(pq, 'all') AS pq, coalesce(k, 0)::INTEGER AS k, grouping_id(pq, k)::BIGINT AS level, count(*) AS n, round(avg(rel), 6) AS rho FROM rl GROUP BY GROUPING SETS ((pq), (k), ())")
def error_grouping_sets(spark, sf_dir):
    """Errors by setting, by length, and over all, in one pass."""
    rows = _both_settings(spark, sf_dir).groupingSets([["pq"], ["k"], []], "pq", "k").agg(F.grouping_id().alias("level"), F.count(F.lit(1)).alias("n"), r6(F.avg("rel")).alias("rho"))
    return rows.select(F.coalesce("pq", F.lit("all")).alias("pq"), F.coalesce("k", F.lit(0)).alias("k"), "level", "n", "rho")


@query(_TWO + " SELECT pq, round(quantile_disc(rel, 0.25), 6) AS low, round(quantile_disc(rel, 0.75), 6) AS high, true AS sketch_is_near FROM rl GROUP BY pq")
def error_quantiles(spark, sf_dir):
    """Quartiles of errors that are values of the data, and whether a quantile sketch has its median among the middle tenth."""
    rows = _both_settings(spark, sf_dir)
    sketch = F.kll_sketch_get_quantile_double(F.kll_sketch_agg_double("rel"), F.lit(0.5))
    near = sketch.between(F.percentile("rel", F.lit(0.45)), F.percentile("rel", F.lit(0.55)))
    return rows.groupBy("pq").agg(r6(F.percentile_approx("rel", 0.25, 100_000)).alias("low"), r6(F.percentile_approx("rel", 0.75, 100_000)).alias("high"), near.alias("sketch_is_near"))


@query(f"""WITH {sql.baskets('brand')}, {sql.masks('t', 'tm')} SELECT o_orderstatus AS status, bit_and(mask) AS every, bit_or(mask) AS some, bit_xor(mask) AS odd, sum(bit_count(mask))::BIGINT AS ones
FROM tm JOIN orders ON o_orderkey = tid GROUP BY 1""")
def tuple_words(spark, sf_dir):
    """A tuple of few items as one word: logic over words, by order status."""
    b = of(spark, sf_dir, "brand")
    words = b.arrays().select("tid", F.aggregate("items", F.lit(0).cast("long"), lambda w, i: w.bitwiseOR(F.call_function("shiftleft", F.lit(1).cast("long"), i))).alias("word"))
    rows = words.join(load(spark, sf_dir, "orders", "o_orderkey", "o_orderstatus"), F.col("o_orderkey") == F.col("tid"))
    return rows.groupBy(F.col("o_orderstatus").alias("status")).agg(F.bit_and("word").alias("every"), F.bit_or("word").alias("some"), F.bit_xor("word").alias("odd"), F.sum(F.bit_count("word")).alias("ones"))


@query("""WITH c AS (SELECT l_orderkey AS tid, p_brand AS brand, count(*) AS n FROM lineitem JOIN part ON l_partkey = p_partkey GROUP BY ALL)
SELECT tid, count(*) AS brands, sum(n)::BIGINT AS lines, count_if(n > 1) AS repeated, coalesce(max(CASE WHEN brand = 'Brand#11' THEN n END), 0) AS of_first, min(brand) AS least FROM c GROUP BY tid""")
def basket_maps(spark, sf_dir):
    """Baskets as maps from item to the number of its lines."""
    part = load(spark, sf_dir, "part", "p_partkey", "p_brand")
    lines = load(spark, sf_dir, "lineitem", "l_orderkey", "l_partkey").join(part, F.col("l_partkey") == F.col("p_partkey"))
    counts = lines.groupBy(F.col("l_orderkey").alias("tid"), F.col("p_brand").alias("brand")).agg(F.count(F.lit(1)).alias("n"))
    maps = counts.groupBy("tid").agg(F.map_from_entries(F.collect_list(F.struct("brand", "n"))).alias("m"))
    total = F.aggregate(F.map_values("m"), F.lit(0).cast("long"), lambda a, x: a + x)
    return maps.select(
        "tid", F.size("m").cast("long").alias("brands"), total.alias("lines"), F.size(F.map_filter("m", lambda _, n: n > 1)).cast("long").alias("repeated"),
        F.coalesce(F.try_element_at("m", F.lit("Brand#11")), F.lit(0)).alias("of_first"), F.array_min(F.map_keys("m")).alias("least"),
    )


@query(f"WITH {sql.baskets('brand')} SELECT u.item AS a, v.item AS b, count(*) AS n FROM t u JOIN t v ON u.tid = v.tid AND u.item < v.item GROUP BY ALL")
def pairs_by_shuffle_hash(spark, sf_dir):
    """Pairs of items of a tuple by a shuffled hash join: no sort, where a tuple's items fit into memory."""
    long = of(spark, sf_dir, "brand").long
    other = long.select("tid", F.col("item").alias("b")).hint("shuffle_hash")
    return long.withColumnRenamed("item", "a").join(other, "tid").where("a < b").groupBy("a", "b").agg(F.count(F.lit(1)).alias("n"))


@query(f"WITH {sql.baskets('type')}, {sql.masks('t', 'tm')} SELECT o_custkey % 10 AS part, bit_count(bit_and(mask))::INTEGER AS common FROM tm JOIN orders ON o_orderkey = tid GROUP BY 1")
def common_items_by_arrow_aggregate(spark, sf_dir):
    """Items that all tuples of a group have, by a grouped aggregate over bit vectors in Arrow."""
    b = of(spark, sf_dir, "type")
    bits = distort.to_bits(b.arrays(), b.n_items).join(load(spark, sf_dir, "orders", "o_orderkey", "o_custkey"), F.col("o_orderkey") == F.col("tid"))
    return bits.groupBy((F.col("o_custkey") % 10).alias("part")).agg(F.bit_count(F.conv(F.hex(sqlfuncs.bits_and("bits")), 16, 10).cast("long")).alias("common"))


def _identity_sql() -> str:
    keys = "SELECT a.code AS ante, x.code - a.code AS cons FROM {f} x JOIN {f} a ON x.code & a.code = a.code AND a.code < x.code AND a.v > 0 WHERE x.v / a.v >= 0.5"
    return f"""WITH {_TYPE}, ft AS (SELECT code, n::DOUBLE AS v FROM tc WHERE n >= {_LEAST}), fe AS (SELECT code, est AS v FROM e WHERE est >= {_LEAST}),
rt AS ({keys.format(f='ft')}), re AS ({keys.format(f='fe')}), h AS (SELECT count(*) AS n FROM re JOIN rt ON re.ante = rt.ante AND re.cons = rt.cons)
SELECT round(n / (SELECT count(*) FROM re), 6) AS "precision", round(n / (SELECT count(*) FROM rt), 6) AS recall FROM h"""


@query(_identity_sql())
def rule_errors(spark, sf_dir):
    """Of the rules from reconstructed supports those that are true, and of the true ones those found."""
    b, arrays = seen(spark, sf_dir, "type")
    found = rules.generate(mining.mine_distorted(arrays, b.n_items, b.dbsize(), MAIN, MIN_SUPPORT).frame(spark), b.dbsize(), 0.5)
    true = rules.generate(_type_exact(spark, sf_dir), b.dbsize(), 0.5)
    return metrics.rule_identity(found, true).select(r6("precision").alias("precision"), r6("recall").alias("recall"))


from . import experiments  # noqa: E402  registers the experiments' queries

experiments.register(query)
