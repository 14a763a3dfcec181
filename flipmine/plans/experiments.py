"""The experiments: summary rows per setting, errors by level, cost and density, sweeps.

Queries leave run times out, so that they are the same each time; ``slowdowns`` measures them, queries count work instead.
"""

from __future__ import annotations

from collections.abc import Callable, Iterable

import numpy as np
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..config import CANDIDATES_DENSE, CANDIDATES_SPARSE, FlipParams
from ..operators import counting, distort, metrics, mining, privacy, tuning
from ..sources import baskets, generator
from ..sources.shared import stored, tasks
from . import oracles as sql

SEED = sql.SEED
SYMMETRIC = (0.9, 0.9)
SHARES = ("0.001", "0.003", "0.005", "0.01", "0.02")
ERRORS = ("sigma_plus", "sigma_minus", "rho", "var_sigma_plus", "var_sigma_minus", "var_rho")
SUMMARY = "p double, q double, bp double, rp double, density double, work double, sigma_plus double, sigma_minus double, rho double, var_sigma_plus double, var_sigma_minus double, var_rho double, longest int"
#: Decimals of figures that are sums of many floating-point numbers.
DIGITS = 4


def rounded(df: DataFrame) -> DataFrame:
    return df.select(*(F.round(c, DIGITS).alias(c) if kind == "double" else F.col(c) for c, kind in df.dtypes))


def kept(b: baskets.Baskets) -> DataFrame:
    """The true lists as a stored table, for as many tasks as there are cores."""
    return stored(b.arrays(tasks(b.long.sparkSession)), "exp-true")


def truth(b: baskets.Baskets, min_support: str, max_len: int) -> tuple[DataFrame, int, mining.Mined]:
    arrays, dbsize = kept(b), b.dbsize()
    return arrays, dbsize, mining.mine_exact(arrays, b.n_items, dbsize, min_support, max_len)


def distorted(arrays: DataFrame, n_items: int, p: float, q: float, sparse: bool = False) -> DataFrame:
    flip = distort.flip_sparse if sparse else distort.flip_arrays
    return stored(flip(arrays, n_items, FlipParams(p, q), SEED), "exp-seen")


def ones(arrays: DataFrame) -> int:
    return arrays.agg(F.sum(F.size("items"))).first()[0] or 0


def summary(spark: SparkSession, b: baskets.Baskets, settings: Iterable[tuple[float, float]], min_support: str = "0.003", max_len: int = 3, sparse: bool = False) -> DataFrame:
    """A row per setting: both privacies, density, work, errors and their variances over levels.

    ``density`` and ``work`` say how many times more items a tuple has, and how many times more counters
    are touched, than without distortion; run times are left to ``slowdowns``. ``sparse`` distorts with the sampler, for
    universes too wide to toss a coin for each cell. A coin is tossed once for all settings, and all tables are mined, a level in one pass;
    where single items are asked for, the sampler's items are counted as they are drawn, and no distorted table is kept.
    """
    settings = list(settings)
    arrays, params = kept(b), [FlipParams(p, q) for p, q in settings]
    dbsize, before = arrays.agg(F.count(F.lit(1)), F.coalesce(F.sum(F.size("items")), F.lit(0))).first()
    bps = [privacy.basic(before / (dbsize * b.n_items), p, q) for p, q in settings]
    if sparse and max_len == 1:
        ones_, seen, held = distort.flip_sparse_counts(arrays, b.n_items, params, SEED)
        true, *found = mining.mine_together(lambda levels: [ones_, *seen], b.n_items, dbsize, [None, *params], min_support, 1)
        after = seen.sum(1).tolist()
        rps = [_single_items_privacy(sorted(x for (x,) in true.support), before, n, k, bp) for n, k, bp in zip(seen, held, bps, strict=True)]
    else:
        names = [f"s{i}" for i in range(len(settings))]
        table = stored(distort.flip_lists(arrays, b.n_items, params, SEED, sparse, as_bytes=True), "exp-seen")
        true, *found = mining.mine_together(lambda levels: counting.count_tables(table, ["items", *names], levels, b.n_items), b.n_items, dbsize, [None, *params], min_support, max_len)
        after = [sum(n for x, n in m.counts.items() if len(x) == 1) for m in found]
        rps = [rp for rp, _ in privacy.reinterrogated_tables(table, names, sorted(true.support), b.n_items, bps)]
    mined, exact = mining.frames(spark, found), mining.frames(spark, [true] * len(found))
    errors = {r.run: r for r in metrics.rollup(metrics.by_level(mined, exact, "run"), "true", "run").collect()}
    touched, rows = sum(true.counts.values()), []
    for i, ((p, q), bp, rp, n, m) in enumerate(zip(settings, bps, rps, after, found, strict=True)):
        rows.append((p, q, bp, rp, n / max(before, 1), sum(m.counts.values()) / max(touched, 1), *(errors[i][c] if i in errors else None for c in ERRORS), max(map(len, m.support), default=0)))
    return rounded(spark.createDataFrame(rows, SUMMARY))


def _single_items_privacy(items: list[int], ones: int, seen: np.ndarray, held: np.ndarray, bp: float) -> float:
    """``privacy.reinterrogated_chunks`` where the itemsets are ``items`` alone: their breach is the share of their seen bits that are true."""
    if not ones:
        return float("nan")
    seen, held = seen[items].astype(float), held[items].astype(float)
    return float((np.sum(100 * held * (1 - held / np.maximum(seen, 1))) + (ones - held.sum()) * bp) / ones)


def _lattice(kind: str, times: int = 1) -> str:
    return f"{sql.baskets(kind, times)}, {sql.wide_masks('t', 'tm')}"


def _seen(p: float, q: float, i: int) -> str:
    """CTEs d{i} (tid, item) and dm{i} (tid, mask)."""
    return f"{sql.flips(p, q, name=f'd{i}')}, {sql.wide_masks(f'd{i}', f'dm{i}')}"


def _bp(p: float, q: float) -> str:
    s = "((SELECT count(*) FROM t) / ((SELECT n FROM size) * (SELECT count(*) FROM items)))::DOUBLE"
    return f"100 * (1 - ({s} * {p}::DOUBLE * {p} / ({s} * {p} + (1 - {s}) * (1 - {q}::DOUBLE)) + {s} * (1 - {p}::DOUBLE) * (1 - {p}::DOUBLE) / ({s} * (1 - {p}::DOUBLE) + (1 - {s}) * {q})))"


def _rounded(columns: Iterable[str]) -> str:
    return ", ".join(f"round({c}, {DIGITS}) AS {c}" for c in columns)


def summary_ctes(kind: str, settings: Iterable[tuple[float, float]], share: str = "0.003", levels: int = 3, times: int = 1) -> str:
    """CTEs up to ``sm``, with the rows of ``summary`` before they are rounded."""
    parts, rows = [_lattice(kind, times), sql.level_wise("tm", "x", share, levels)], []
    for i, (p, q) in enumerate(settings):
        parts += [_seen(p, q, i), sql.level_wise(f"dm{i}", f"f{i}", share, levels, FlipParams(p, q)), sql.errors("x", f"f{i}", f"lv{i}"), sql.attacked("x", "tm", f"dm{i}", f"a{i}", _bp(p, q))]
        rows.append(
            f"SELECT {p}::DOUBLE AS p, {q}::DOUBLE AS q, {_bp(p, q)} AS bp, (SELECT rp FROM a{i}) AS rp, (SELECT count(*) FROM d{i}) / (SELECT count(*) FROM t) AS density, "
            f"(SELECT sum(n) FROM f{i}_cand) / (SELECT sum(n) FROM x_cand) AS work, e.*, (SELECT coalesce(max(k), 0) FROM f{i})::INTEGER AS longest FROM ({sql.rolled(f'lv{i}')}) e"
        )
    return ", ".join([*parts, f"sm AS MATERIALIZED ({' UNION ALL '.join(rows)})"])


def _summary_sql(*args, **kwargs) -> str:  # noqa: ANN002, ANN003
    return f"WITH {summary_ctes(*args, **kwargs)} SELECT p, q, longest, {_rounded(('bp', 'rp', 'density', 'work', *ERRORS))} FROM sm"


def levels(spark: SparkSession, b: baskets.Baskets, settings: Iterable[tuple[float, float]], min_support: str = "0.003", max_len: int = 8, sparse: bool = False) -> DataFrame:
    """Errors by length of itemset, per setting."""
    arrays, dbsize, true = truth(b, min_support, max_len)
    out = None
    for p, q in settings:
        found = mining.mine_distorted(distorted(arrays, b.n_items, p, q, sparse), b.n_items, dbsize, FlipParams(p, q), min_support, max_len)
        one = metrics.by_level(found.frame(spark), true.frame(spark)).select(F.lit(p).alias("p"), F.lit(q).alias("q"), "*")
        out = one if out is None else out.unionByName(one)
    return rounded(out)


def _levels_sql(kind: str, settings: Iterable[tuple[float, float]], top: int, share: str = "0.003") -> str:
    parts, rows = [_lattice(kind), sql.level_wise("tm", "x", share, top)], []
    for i, (p, q) in enumerate(settings):
        parts += [_seen(p, q, i), sql.level_wise(f"dm{i}", f"f{i}", share, top, FlipParams(p, q)), sql.errors("x", f"f{i}", f"lv{i}")]
        rows.append(f"SELECT {p}::DOUBLE AS p, {q}::DOUBLE AS q, k::INTEGER AS k, n_true, n_found, hits, {_rounded(('sigma_plus', 'sigma_minus', 'rho'))} FROM lv{i}")
    return f"WITH {', '.join(parts)} {' UNION ALL '.join(rows)}"


def scheme_work(spark: SparkSession, name: str, b: baskets.Baskets, shares: Iterable[str], max_len: int, sparse: bool = False) -> DataFrame:
    """What exact and symmetric mining come to over minimum supports: candidates, itemsets found, counters, and updates of counters.

    The symmetric scheme's classes give the estimates that inclusion and exclusion give, so its candidates are found the
    cheap way and its cost is that of its own classes.
    """
    arrays, dbsize = kept(b), b.dbsize()
    seen, rows = distorted(arrays, b.n_items, *SYMMETRIC, sparse), []
    for share in shares:
        exact = mining.mine_exact(arrays, b.n_items, dbsize, share, max_len)
        found = mining.mine_distorted(seen, b.n_items, dbsize, FlipParams(*SYMMETRIC), share, max_len)
        for scheme, m, strategy in (("exact", exact, "ones"), ("symmetric", found, "weight")):
            rows.append((name, share, scheme, len(m.support), *metrics.work(m.candidates, sum(m.counts.values()), dbsize, strategy)))
    return spark.createDataFrame(rows, "workload string, min_support string, scheme string, found long, candidates long, counters long, updates long")


def _scheme_sql(kinds: Iterable[tuple[str, int]]) -> str:
    out = []
    for kind, top in kinds:
        parts, rows = [_lattice(kind), _seen(*SYMMETRIC, 0)], []
        for i, share in enumerate(SHARES):
            parts += [sql.level_wise("tm", f"x{i}", share, top), sql.level_wise("dm0", f"f{i}", share, top, FlipParams(*SYMMETRIC))]
            rows.append(f"SELECT '{kind}' AS workload, '{share}' AS min_support, 'exact' AS scheme, (SELECT count(*) FROM x{i}) AS found, count(*) AS candidates, count(*) AS counters, sum(n)::BIGINT AS updates FROM x{i}_cand")
            rows.append(f"SELECT '{kind}', '{share}', 'symmetric', (SELECT count(*) FROM f{i}), count(*), sum(k + 1)::BIGINT, (count(*) * (SELECT n FROM size))::BIGINT FROM f{i}_cand")
        out.append(f"(WITH {', '.join(parts)} {' UNION ALL '.join(rows)})")
    return " UNION ALL ".join(out)


def slowdowns(spark: SparkSession, b: baskets.Baskets, settings: Iterable[tuple[float, float]], min_support: str = "0.003", max_len: int = 3, repeats: int = 3, symmetric: bool = True) -> list[tuple[str, float]]:
    """Run time on distorted data over that of the exact miner on the original, the same code and physical strategy for both."""
    arrays, dbsize, _ = truth(b, min_support, max_len)
    exact = lambda: mining.mine_exact(arrays, b.n_items, dbsize, min_support, max_len)
    out = []
    for p, q in settings:
        seen = stored(distort.flip_arrays(arrays, b.n_items, FlipParams(p, q), SEED), "exp-seen")
        out.append((f"{p}/{q}", metrics.slowdown(lambda s=seen, f=FlipParams(p, q): mining.mine_distorted(s, b.n_items, dbsize, f, min_support, max_len), exact, repeats)))
    if symmetric:
        seen = stored(distort.flip_arrays(arrays, b.n_items, FlipParams(0.9, 0.9), SEED), "exp-seen")
        out.append(("symmetric 0.9", metrics.slowdown(lambda: mining.mine_symmetric(seen, b.n_items, dbsize, 0.9, min_support, max_len), exact, repeats)))
    return out


def _counters_sql(kind: str, top: int) -> str:
    parts, rows = [_lattice(kind)], []
    for i, (p, q) in enumerate((SYMMETRIC, (0.6, 0.96))):
        parts += [_seen(p, q, i), sql.level_wise(f"dm{i}", f"f{i}", "0.003", top, FlipParams(p, q))]
        for strategy, each in (("ones", "1"), ("weight", "k + 1"), ("pattern", "2 ** k")):
            updates = "sum(n)" if strategy == "ones" else "count(*) * (SELECT n FROM size)"
            rows.append(f"SELECT '{kind}' AS workload, {p}::DOUBLE AS p, {q}::DOUBLE AS q, '{strategy}' AS strategy, (SELECT count(*) FROM f{i}) AS found, count(*) AS candidates, sum({each})::BIGINT AS counters, ({updates})::BIGINT AS updates FROM f{i}_cand")
    return f"(WITH {', '.join(parts)} {' UNION ALL '.join(rows)})"


_LENGTHS = ("type", "brand", "name", "supp", "name_type", "clicks", "cust_supp")
_DENSITY = " UNION ALL ".join(
    f"(WITH {sql.baskets(kind)}, {', '.join(sql.flips(p, q, name=f'd{i}') for i, (p, q) in enumerate((SYMMETRIC, *CANDIDATES_DENSE)))}, b AS (SELECT (SELECT count(*) FROM t) / (SELECT n FROM size) AS l, (SELECT count(*) FROM items) AS w) "
    + " UNION ALL ".join(
        f"SELECT '{kind}' AS workload, {p}::DOUBLE AS p, {q}::DOUBLE AS q, round(l, 4) AS before, round((SELECT count(*) FROM d{i}) / (SELECT n FROM size), 4) AS after, round(l * {p} + (w - l) * (1 - {q}::DOUBLE), 4) AS expected, "
        f"CASE WHEN 4 * (l * {p} + (w - l) * (1 - {q}::DOUBLE)) < w / 8 THEN 'lists' ELSE 'bits' END AS layout FROM b"
        for i, (p, q) in enumerate((SYMMETRIC, *CANDIDATES_DENSE))
    )
    + ")"
    for kind in _LENGTHS
)
_SPARSITY = " UNION ALL ".join(
    f"""(WITH {sql.distorted(kind, 0.4, 0.98)}, s AS (SELECT (SELECT count(*) FROM t) / ((SELECT n FROM size) * (SELECT count(*) FROM items)) AS s0, (SELECT count(*) FROM items) AS w),
x AS (SELECT item, count(*) AS n FROM t GROUP BY item), y AS (SELECT item, count(*) AS n FROM d GROUP BY item),
e AS (SELECT x.n, (50 * coalesce(y.n, 0) - (SELECT n FROM size)) / 19.0::DOUBLE AS est FROM x LEFT JOIN y ON y.item = x.item WHERE 1000 * x.n >= 3 * (SELECT n FROM size))
SELECT '{kind}' AS workload, w::INTEGER AS items, round(s0, 4) AS s0, round({_bp(0.4, 0.98)}, 4) AS bp, round(100 * sqrt((s0 * (SELECT n FROM size) * 0.4::DOUBLE * 0.6 + (1 - s0) * (SELECT n FROM size) * 0.98::DOUBLE * 0.02)) / 0.38 / (s0 * (SELECT n FROM size)), 4) AS expected_error,
    round((SELECT 100 * avg(abs(est - n) / n) FROM e WHERE 1000 * est >= 3 * (SELECT n FROM size)), 4) AS rho, round((SELECT count(*) FROM d) / (SELECT count(*) FROM t), 4) AS density FROM s)"""
    for kind in _LENGTHS
)


def _sweep_sql() -> str:
    out = []
    for kind in ("brand", "name"):
        parts, rows = [_lattice(kind), _seen(0.6, 0.96, 0)], []
        for i, share in enumerate(SHARES):
            parts += [sql.level_wise("tm", f"x{i}", share, 2), sql.level_wise("dm0", f"f{i}", share, 2, FlipParams(0.6, 0.96)), sql.errors(f"x{i}", f"f{i}", f"lv{i}")]
            rows.append(f"SELECT '{kind}' AS workload, '{share}' AS min_support, (SELECT count(*) FROM x{i}) AS n_true, {_rounded(ERRORS[:3])} FROM ({sql.rolled(f'lv{i}')})")
        out.append(f"(WITH {', '.join(parts)} {' UNION ALL '.join(rows)})")
    return " UNION ALL ".join(out)


_SAMPLE = " UNION ALL ".join(
    f"""(WITH {sql.baskets('name_type')}, picked AS (SELECT tid FROM tids WHERE ('0x' || substr(md5('sample-42|' || tid), 1, 13))::BIGINT < {int(fraction * 2**52)}),
s AS (SELECT (SELECT count(*) FROM picked) AS tuples, (SELECT count(*) FROM t WHERE tid IN (SELECT tid FROM picked)) / ((SELECT count(*) FROM picked) * (SELECT count(*) FROM items)) AS s0),
g AS (SELECT a.i / 10 AS p, b.j / 100 AS q FROM generate_series(1, 9) AS a(i), generate_series(96, 99) AS b(j)),
c AS (SELECT p, q, 100 * (1 - (s0 * p * p / (s0 * p + (1 - s0) * (1 - q)) + s0 * (1 - p) * (1 - p) / (s0 * (1 - p) + (1 - s0) * q))) AS bp, sqrt(p * (1 - p) + (1 / s0 - 1) * q * (1 - q)) / abs(p + q - 1) AS error, sqrt(0.9::DOUBLE * (1 - 0.9::DOUBLE) * (1 + 1 / s0 - 1)) / 0.8 AS least FROM g, s)
SELECT {fraction}::DOUBLE AS fraction, tuples, round(s0, 9) AS s0, (SELECT count(*) FROM c WHERE bp >= 90 AND error <= least * 1.04) AS admitted FROM s)"""
    for fraction in (0.01, 0.05, 0.1, 1.0)
)
_ATTACKERS = (("brand", 3), ("type", 6))


def _attacker_sql() -> str:
    out = []
    for kind, top in _ATTACKERS:
        parts, rows = [_lattice(kind), _seen(0.6, 0.96, 0)], []
        for i, share in enumerate(("0.001", "0.003", "0.01", "0.03")):
            for knowledge, masks, params in (("exact", "tm", None), ("reconstructed", "dm0", FlipParams(0.6, 0.96))):
                name = f"{knowledge[0]}{i}"
                parts += [sql.level_wise(masks, name, share, top, params), sql.attacked(name, "tm", "dm0", f"a{name}", _bp(0.6, 0.96))]
                rows.append(f"SELECT '{kind}' AS workload, '{knowledge}' AS knowledge, '{share}' AS min_support, (SELECT count(*) FROM {name}) AS itemsets, round({_bp(0.6, 0.96)}, 4) AS bp, round((SELECT rp FROM a{name}), 4) AS rp")
        out.append(f"(WITH {', '.join(parts)} {' UNION ALL '.join(rows)})")
    return " UNION ALL ".join(out)


EXTREMES = ((0.6, 0.96), (0.3, 0.99))


def register(query: Callable) -> None:
    def summary_query(name: str, kind: str, settings: tuple, top: int, times: int = 1) -> None:
        def run(spark, sf_dir):
            b = baskets.from_events(spark, sf_dir) if kind == "clicks" else baskets.from_orders(spark, sf_dir, kind)
            return summary(spark, baskets.replicate(b, times) if times > 1 else b, settings, "0.003", top)

        run.__name__ = name
        query(_summary_sql(kind, settings, "0.003", top, times))(run)

    # privacy, work and errors of the candidate settings on brand baskets, and of all settings of the sparse regime on tenfold clicks, to four items
    summary_query("exp_summary_brand", "brand", (SYMMETRIC, *CANDIDATES_DENSE), 3)
    summary_query("exp_summary_clicks", "clicks", CANDIDATES_SPARSE, 4, 10)

    @query()
    def exp_summary_name_type(spark, sf_dir):
        """The same at the published average support of 0.01, pairs included."""
        return summary(spark, baskets.from_orders(spark, sf_dir, "name_type"), CANDIDATES_DENSE, "0.003", 2, sparse=True)

    @query()
    def exp_summary_parts(spark, sf_dir):
        """Singletons of the widest universe, sparser than the published real data, under all settings of that regime."""
        return summary(spark, baskets.from_orders(spark, sf_dir, "part"), CANDIDATES_SPARSE, "0.003", 1, sparse=True)

    @query()
    def exp_summary_patterns(spark, sf_dir):
        """The same on generated baskets of 1,000 items at 0.3 % and to eight items."""
        return summary(spark, generated(spark, sf_dir), CANDIDATES_DENSE, "0.003", 8, sparse=True)

    @query()
    def exp_levels_patterns(spark, sf_dir):
        """Errors by length on generated baskets at the two extreme settings."""
        return levels(spark, generated(spark, sf_dir), EXTREMES, sparse=True)

    @query(_levels_sql("type", EXTREMES, 6))
    def exp_levels_type(spark, sf_dir):
        """Errors by length up to six items at the two extreme settings."""
        return levels(spark, baskets.from_orders(spark, sf_dir, "type"), EXTREMES)

    @query(_levels_sql("brand", EXTREMES, 3))
    def exp_levels_brand(spark, sf_dir):
        """The same on brands, whose pairs are all frequent and whose triples are on the border."""
        return levels(spark, baskets.from_orders(spark, sf_dir, "brand"), EXTREMES, max_len=3)

    @query(_scheme_sql((("brand", 3), ("name", 2))))
    def exp_exact_vs_symmetric(spark, sf_dir):
        """Exact and symmetric mining over minimum supports, in counted work."""
        work = lambda kind, top: scheme_work(spark, kind, baskets.from_orders(spark, sf_dir, kind), SHARES, top)
        return work("brand", 3).unionByName(work("name", 2))

    @query()
    def exp_exact_vs_symmetric_patterns(spark, sf_dir):
        """The same on generated baskets, pairs at most: the published regime, where the gap is widest."""
        return scheme_work(spark, "patterns", generated(spark, sf_dir), SHARES[1:], 2, sparse=True)

    @query(" UNION ALL ".join(_counters_sql(kind, top) for kind, top in (("type", 3), ("brand", 2))))
    def exp_counters(spark, sf_dir):
        """The three counting strategies run on both kinds of distortion: what each finds and what its counting comes to."""
        rows = []
        for kind, top in (("type", 3), ("brand", 2)):
            b = baskets.from_orders(spark, sf_dir, kind)
            arrays, dbsize = kept(b), b.dbsize()
            for p, q in (SYMMETRIC, (0.6, 0.96)):
                params, seen = FlipParams(p, q), distorted(arrays, b.n_items, p, q)
                for strategy in ("ones", "weight", "pattern"):
                    m = mining.mine_distorted(seen, b.n_items, dbsize, params, "0.003", top) if strategy == "ones" else mining.mine_classes(seen, b.n_items, dbsize, params, "0.003", top, strategy)
                    rows.append((kind, p, q, strategy, len(m.support), *metrics.work(m.candidates, sum(m.counts.values()), dbsize, strategy)))
        return spark.createDataFrame(rows, "workload string, p double, q double, strategy string, found long, candidates long, counters long, updates long")

    @query(_DENSITY)
    def exp_density(spark, sf_dir):
        """Mean length before and after, expected and measured, and the layout that takes fewer bytes."""
        rows = []
        for kind in _LENGTHS:
            b = of(spark, sf_dir, kind)
            arrays, dbsize = kept(b), b.dbsize()
            length, settings = ones(arrays) / dbsize, (SYMMETRIC, *CANDIDATES_DENSE)
            seen = distort.flip_counts(arrays, b.n_items, [FlipParams(p, q) for p, q in settings], SEED)
            for (p, q), counts in zip(settings, seen, strict=True):
                rows.append((kind, p, q, length, int(counts.sum()) / dbsize, distort.expected_length(length, b.n_items, p, q), distort.choose_layout(length, b.n_items, p, q)))
        return rounded(spark.createDataFrame(rows, "workload string, p double, q double, before double, after double, expected double, layout string"))

    @query(_SPARSITY)
    def exp_sparsity(spark, sf_dir):
        """From dense to sparse baskets at the recommended setting: privacy, expected and measured error of frequent items, growth in length."""
        rows, params = [], FlipParams(0.4, 0.98)
        for kind in _LENGTHS:
            b = of(spark, sf_dir, kind)
            arrays, dbsize, true = truth(b, "0.003", 1)
            (counts,) = distort.flip_counts(arrays, b.n_items, [params], SEED)
            found = mining.mine_distorted(arrays, b.n_items, dbsize, params, "0.003", 1, singletons=counts)
            before, after = ones(arrays), int(counts.sum())
            s0 = before / (dbsize * b.n_items)
            rho = metrics.support_error(found.frame(spark), true.frame(spark)).first().rho
            rows.append((kind, b.n_items, s0, privacy.basic(s0, params.p, params.q), 100 * tuning.relative_error(s0 * dbsize, dbsize, params.p, params.q), rho, after / before))
        return rounded(spark.createDataFrame(rows, "workload string, items int, s0 double, bp double, expected_error double, rho double, density double"))

    @query(_sweep_sql())
    def exp_support_sweep(spark, sf_dir):
        """Errors at several minimum supports, pairs at most."""
        out = None
        for kind in ("brand", "name"):
            b = baskets.from_orders(spark, sf_dir, kind)
            arrays, dbsize = kept(b), b.dbsize()
            seen = distorted(arrays, b.n_items, 0.6, 0.96)
            for share in SHARES:
                true = mining.mine_exact(arrays, b.n_items, dbsize, share, 2)
                found = mining.mine_distorted(seen, b.n_items, dbsize, FlipParams(0.6, 0.96), share, 2)
                one = metrics.rollup(metrics.by_level(found.frame(spark), true.frame(spark)))
                one = one.select(F.lit(kind).alias("workload"), F.lit(share).alias("min_support"), F.lit(len(true.support)).cast("long").alias("n_true"), *ERRORS[:3])
                out = one if out is None else out.unionByName(one)
        return rounded(out)

    @query(_SAMPLE)
    def exp_sampling(spark, sf_dir):
        """Average support from samples, and how many settings it admits."""
        b, rows = baskets.from_orders(spark, sf_dir, "name_type"), []
        for fraction in (0.01, 0.05, 0.1, 1.0):
            row = tuning.average_support(b.long, b.tids, b.n_items, fraction).first()
            admitted = tuning.candidates(spark, row.s0, slack=0.04).count() if row.s0 else 0
            rows.append((fraction, row.tuples, round(row.s0, 9) if row.s0 else row.s0, admitted))
        return spark.createDataFrame(rows, "fraction double, tuples long, s0 double, admitted long")

    @query(_attacker_sql())
    def exp_attacker(spark, sf_dir):
        """Output-aided privacy against attackers who mine at several thresholds, and who know the true itemsets or the reconstructed ones."""
        rows, params = [], FlipParams(0.6, 0.96)
        for kind, top in _ATTACKERS:
            b = baskets.from_orders(spark, sf_dir, kind)
            arrays, dbsize = kept(b), b.dbsize()
            seen = distorted(arrays, b.n_items, params.p, params.q)
            pairs = stored(arrays.join(seen.withColumnRenamed("items", "seen"), "tid"), "exp-pairs")
            bp = privacy.basic(ones(arrays) / (dbsize * b.n_items), params.p, params.q)
            for share in ("0.001", "0.003", "0.01", "0.03"):
                for knowledge in ("exact", "reconstructed"):
                    m = mining.mine_exact(arrays, b.n_items, dbsize, share, top) if knowledge == "exact" else mining.mine_distorted(seen, b.n_items, dbsize, params, share, top)
                    rp, _ = privacy.reinterrogated_chunks(pairs, sorted(m.support), b.n_items, bp)
                    rows.append((kind, knowledge, share, len(m.support), bp, rp))
        return rounded(spark.createDataFrame(rows, "workload string, knowledge string, min_support string, itemsets long, bp double, rp double"))

    @query(f"""WITH {summary_ctes('brand', CANDIDATES_DENSE)}, o AS (SELECT *, lead(p) OVER w AS p2, lead(bp) OVER w AS bp2, lead(rp) OVER w AS rp2, lead(rho) OVER w AS rho2, lead(work) OVER w AS work2 FROM sm WINDOW w AS (ORDER BY p DESC))
SELECT p AS p_from, p2 AS p_to, bp2 > bp AS more_private, rp2 > rp AS more_private_against_output, rho2 > rho AS less_accurate, work2 < work AS less_work FROM o WHERE p2 IS NOT NULL""")
    def exp_trade_off(spark, sf_dir):
        """From each candidate setting to the next, p falling and q rising: which way privacy, error and work move."""
        rows = summary(spark, baskets.from_orders(spark, sf_dir, "brand"), CANDIDATES_DENSE)
        after = lambda c: F.lead(c).over(Window.orderBy(F.desc("p")))  # noqa: E731  four rows
        out = rows.select(F.col("p").alias("p_from"), after("p").alias("p_to"), (after("bp") > F.col("bp")).alias("more_private"), (after("rp") > F.col("rp")).alias("more_private_against_output"), (after("rho") > F.col("rho")).alias("less_accurate"), (after("work") < F.col("work")).alias("less_work"))
        return out.where("p_to IS NOT NULL")

    @query()
    def exp_percolation(spark, sf_dir):
        """Errors with candidates from reconstructed, slackened, and truly frequent itemsets."""
        b = baskets.from_orders(spark, sf_dir, "brand")
        arrays, dbsize, true = truth(b, "0.003", 3)
        params = FlipParams(0.4, 0.98)
        seen = distorted(arrays, b.n_items, params.p, params.q)
        out = None
        for name, extra in (("reconstructed", {}), ("slack", {"slack": 1.0}), ("true", {"true_frequent": set(true.support)})):
            found = mining.mine_distorted(seen, b.n_items, dbsize, params, "0.003", 3, **extra)
            one = metrics.by_level(found.frame(spark), true.frame(spark)).select(F.lit(name).alias("source"), "*")
            out = one if out is None else out.unionByName(one)
        return out

    @query(f"WITH {sql.baskets('brand')}, n AS (SELECT count(*) AS total FROM t u JOIN t v ON u.tid = v.tid AND u.item < v.item) SELECT physical, total FROM n, (VALUES ('chunks'), ('relational'), ('bitmaps'), ('gram'), ('trie')) AS w(physical)")
    def exp_physical(spark, sf_dir):
        """Pairs counted by each physical strategy: totals agree."""
        b = baskets.from_orders(spark, sf_dir, "brand")
        arrays = kept(b)
        sets = [(i, j) for i in range(b.n_items) for j in range(i + 1, b.n_items)]
        rows = [(way, sum(counting.count(arrays, sets, b.n_items, way).values())) for way in ("chunks", "relational", "bitmaps", "gram", "trie")]
        return spark.createDataFrame(rows, "physical string, total long")

    for kind, share in (("name", "0.003"), ("supp", "0.003"), ("cust_supp", "0.05")):

        def pairs_of(spark, sf_dir, kind=kind, share=share):
            b = of(spark, sf_dir, kind)
            arrays, dbsize = kept(b), b.dbsize()
            found = mining.mine_at_source(arrays, b.n_items, dbsize, FlipParams(0.6, 0.96), SEED, share, 2).frame(spark)
            return rounded(found.where("k = 2").select(F.concat_ws(",", "itemset").alias("itemset"), "est"))

        pairs_of.__name__ = f"mined_pairs_{kind}"
        query(f"WITH {_lattice(kind)}, {_seen(0.6, 0.96, 0)}, {sql.level_wise('dm0', 'f', share, 2, FlipParams(0.6, 0.96))} SELECT {sql.itemset()} AS itemset, round(est, {DIGITS}) AS est FROM f WHERE k = 2")(pairs_of)


def of(spark: SparkSession, sf_dir: str, kind: str) -> baskets.Baskets:
    if kind == "clicks":
        return baskets.from_events(spark, sf_dir)
    return baskets.from_customers(spark, sf_dir) if kind == "cust_supp" else baskets.from_orders(spark, sf_dir, kind)


def generated(spark: SparkSession, sf_dir: str) -> baskets.Baskets:
    """Generated baskets, as many as the given tables have orders, and 20,000 at least: with fewer, 0.3 % is within the noise of pairs."""
    return generator.pattern_baskets(spark, max(20_000, baskets.load(spark, sf_dir, "orders", "o_orderkey").count()))
