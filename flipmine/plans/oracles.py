"""SQL parts that several oracles share: baskets, coins and distorted cells, in DuckDB's dialect."""

from __future__ import annotations

from ..config import FlipParams, exact

SEED = 42

#: Labels of each universe, and members of its tuples.
_UNIVERSES = {
    "brand": ("SELECT DISTINCT p_brand AS label FROM part", "SELECT DISTINCT l_orderkey AS tid, p_brand AS label FROM lineitem JOIN part ON l_partkey = p_partkey"),
    "name": ("SELECT DISTINCT p_name AS label FROM part", "SELECT DISTINCT l_orderkey AS tid, p_name AS label FROM lineitem JOIN part ON l_partkey = p_partkey"),
    "type": ("SELECT DISTINCT p_type AS label FROM part", "SELECT DISTINCT l_orderkey AS tid, p_type AS label FROM lineitem JOIN part ON l_partkey = p_partkey"),
    "name_type": ("SELECT DISTINCT p_name || '/' || p_type AS label FROM part", "SELECT DISTINCT l_orderkey AS tid, p_name || '/' || p_type AS label FROM lineitem JOIN part ON l_partkey = p_partkey"),
    "supp": ("SELECT DISTINCT s_suppkey::VARCHAR AS label FROM supplier", "SELECT DISTINCT l_orderkey AS tid, l_suppkey::VARCHAR AS label FROM lineitem"),
    "cust_supp": ("SELECT DISTINCT s_suppkey::VARCHAR AS label FROM supplier", "SELECT DISTINCT o_custkey AS tid, l_suppkey::VARCHAR AS label FROM lineitem JOIN orders ON l_orderkey = o_orderkey"),
    "clicks": ("SELECT DISTINCT json_extract_string(props, '$.k') AS label FROM events", "SELECT DISTINCT user_id * 100000 + date_diff('day', DATE '1970-01-01', ts::DATE) AS tid, json_extract_string(props, '$.k') AS label FROM events"),
}
_TIDS = {"cust_supp": "SELECT DISTINCT o_custkey AS tid FROM orders", "clicks": "SELECT DISTINCT user_id * 100000 + date_diff('day', DATE '1970-01-01', ts::DATE) AS tid FROM events"}


def baskets(kind: str, times: int = 1) -> str:
    """CTEs items(item, label), tids(tid), t(tid, item), size(n); every tuple ``times`` times under new ids."""
    labels, members = _UNIVERSES[kind]
    if times > 1:
        copies = lambda q: f"SELECT tid * {times} + copy AS tid, * EXCLUDE (tid, copy) FROM ({q}), generate_series(0, {times - 1}) AS g(copy)"
        return f"""items AS (SELECT label, (row_number() OVER (ORDER BY label) - 1)::INTEGER AS item FROM ({labels})),
tids AS (SELECT tid * {times} + copy AS tid FROM ({_TIDS.get(kind, 'SELECT o_orderkey AS tid FROM orders')}), generate_series(0, {times - 1}) AS g(copy)),
t AS (SELECT tid, item FROM ({copies(members)}) JOIN items USING (label)),
size AS (SELECT count(*) AS n FROM tids)"""
    return f"""items AS (SELECT label, (row_number() OVER (ORDER BY label) - 1)::INTEGER AS item FROM ({labels})),
tids AS ({_TIDS.get(kind, 'SELECT o_orderkey AS tid FROM orders')}),
t AS (SELECT tid, item FROM ({members}) JOIN items USING (label)),
size AS (SELECT count(*) AS n FROM tids)"""


def distorted(kind: str, p: float, q: float, seed: int = SEED, name: str = "d") -> str:
    """CTEs of ``baskets`` and ``name`` (tid, item): the distorted table."""
    return baskets(kind) + ", " + flips(p, q, seed, name)


def flips(p: float, q: float, seed: int = SEED, name: str = "d") -> str:
    keep, absent = FlipParams(p, q, allow_negative=True).thresholds
    return f"""{name}_cells AS (SELECT tids.tid, items.item, t.tid IS NOT NULL AS x,
    ('0x' || substr(md5('{seed}|' || tids.tid || '|' || items.item), 1, 13))::BIGINT AS u
    FROM tids CROSS JOIN items LEFT JOIN t ON t.tid = tids.tid AND t.item = items.item),
{name} AS (SELECT tid, item FROM {name}_cells WHERE (x AND u < {keep}) OR (NOT x AND u >= {absent}))"""


def masks(source: str, name: str) -> str:
    """CTE ``name`` (tid, mask) for universes of few items."""
    return f"{name} AS (SELECT tids.tid, coalesce(bit_or(1::BIGINT << s.item), 0) AS mask FROM tids LEFT JOIN {source} s ON s.tid = tids.tid GROUP BY tids.tid)"


def codes(masks_name: str, name: str, n_items: int = 6) -> str:
    """CTE ``name`` (code, k, n, itemset): counts of all itemsets of a small universe."""
    text = "concat_ws(',', " + ", ".join(f"CASE WHEN code & {1 << i} > 0 THEN '{i}' END" for i in range(n_items)) + ")"
    return f"""{name} AS (SELECT code, bit_count(code)::INTEGER AS k, n, {text} AS itemset FROM
    (SELECT code, (SELECT count(*) FROM {masks_name} WHERE mask & code = code) AS n FROM generate_series(1, {(1 << n_items) - 1}) AS g(code)))"""


def estimates(codes_name: str, name: str, p: float, q: float) -> str:
    """CTE ``name`` (code, k, itemset, num, est): signed integer sums over the counts of all subsets."""
    a, scale, b = FlipParams(p, q).integers
    return f"""{name} AS (SELECT c.code, c.k, c.itemset, num, num::DOUBLE / ({b}::DOUBLE ** c.k) AS est FROM {codes_name} c JOIN
    (SELECT x.code, (sum(s.n * ({scale}.0::DOUBLE ** s.k) * ((-{a}.0)::DOUBLE ** (x.k - s.k))) + (SELECT n FROM size) * ((-{a}.0)::DOUBLE ** x.k))::BIGINT AS num
     FROM (SELECT code, k FROM {codes_name}) x JOIN {codes_name} s ON x.code & s.code = s.code GROUP BY x.code, x.k) USING (code))"""


def wide_masks(source: str, name: str) -> str:
    """CTE ``name`` (tid, mask) for universes of up to 126 items; tuples without items have mask 0."""
    return f"{name} AS MATERIALIZED (SELECT tids.tid, coalesce(bit_or(1::HUGEINT << s.item), 0::HUGEINT) AS mask FROM tids LEFT JOIN {source} s ON s.tid = tids.tid GROUP BY tids.tid)"


def level_wise(masks_name: str, name: str, share: str, levels: int, params: FlipParams | None = None) -> str:
    """CTEs of a level-wise search over bit masks: ``name`` (k, code, n, num, est) and ``name_cand`` (k, code, n).

    ``name`` has the frequent itemsets, ``name_cand`` all candidates with their counts. With ``params`` estimates are
    signed integer sums over the counts of all subsets; without, they are the counts.
    """
    a, scale, b = params.integers if params else (0, 1, 1)
    least = exact(share)
    out = []
    for k in range(1, levels + 1):
        if k == 1:
            fresh = "SELECT 1::HUGEINT << item AS code, 1::HUGEINT << item AS top, 0::HUGEINT AS rest FROM items"
        else:
            prune = f" WHERE (SELECT count(*) FROM {name}_f{k - 1} f WHERE f.code & j.code = f.code) = {k}" if k > 2 else ""
            fresh = f"SELECT j.code, j.top, j.rest FROM (SELECT x.code + y.top AS code, y.top, x.code AS rest FROM {name}_f{k - 1} x JOIN {name}_f{k - 1} y ON x.rest = y.rest AND x.top < y.top) j{prune}"
        out.append(f"{name}_c{k} AS MATERIALIZED (SELECT c.code, c.top, c.rest, count(m.tid) AS n FROM ({fresh}) c LEFT JOIN {masks_name} m ON m.mask & c.code = c.code GROUP BY ALL)")
        seen = " UNION ALL ".join(f"SELECT {j} AS k, code, n FROM {name}_c{j}" for j in range(1, k + 1))
        terms = "CASE s.k " + " ".join(f"WHEN {j} THEN {scale**j * (-a) ** (k - j)}::HUGEINT" for j in range(1, k + 1)) + " END"
        if params:
            sums = f"SELECT c.code, c.top, c.rest, c.n, (sum(s.n::HUGEINT * {terms}) + (SELECT n FROM size)::HUGEINT * {(-a) ** k}::HUGEINT)::HUGEINT AS num FROM {name}_c{k} c JOIN ({seen}) s ON c.code & s.code = s.code GROUP BY ALL"
        else:
            sums = f"SELECT code, top, rest, n, n::HUGEINT AS num FROM {name}_c{k}"
        out.append(f"{name}_f{k} AS MATERIALIZED (SELECT *, num::DOUBLE / {b**k}::DOUBLE AS est FROM ({sums}) WHERE num * {least.denominator} >= {least.numerator * b**k}::HUGEINT * (SELECT n FROM size))")
    out.append(f"{name} AS MATERIALIZED ({' UNION ALL '.join(f'SELECT {k} AS k, code, n, num, est FROM {name}_f{k}' for k in range(1, levels + 1))})")
    out.append(f"{name}_cand AS MATERIALIZED ({' UNION ALL '.join(f'SELECT {k} AS k, code, n FROM {name}_c{k}' for k in range(1, levels + 1))})")
    return ", ".join(out)


def itemset(code: str = "code") -> str:
    """Expression: the items of a code as text."""
    return f"(SELECT string_agg(item::VARCHAR, ',' ORDER BY item) FROM items WHERE {code} & (1::HUGEINT << item) <> 0)"


def errors(true: str, found: str, name: str) -> str:
    """CTE ``name`` (k, n_true, n_found, hits, sigma_plus, sigma_minus, rho) by length of itemset."""
    return f"""{name} AS (SELECT *, 100 * (n_found - hits) / n_true AS sigma_plus, 100 * (n_true - hits) / n_true AS sigma_minus FROM
    (SELECT coalesce(x.k, y.k) AS k, count(x.code) AS n_true, count(y.code) AS n_found, count(CASE WHEN x.code IS NOT NULL AND y.code IS NOT NULL THEN 1 END) AS hits, 100 * avg(abs(y.est - x.est) / x.est) AS rho
     FROM {true} x FULL JOIN {found} y ON x.code = y.code GROUP BY 1))"""


def rolled(levels_name: str) -> str:
    """Select list of the means over levels and the variances across them, weighted by the number of true itemsets."""
    out = []
    for x in ("sigma_plus", "sigma_minus", "rho"):
        mean = f"sum(n_true * coalesce({x}, 0)) / sum(n_true)"
        out.append(f"{mean} AS {x}, sum(n_true * coalesce({x}, 0) * coalesce({x}, 0)) / sum(n_true) - ({mean}) * ({mean}) AS var_{x}")
    return f"SELECT {', '.join(out)} FROM {levels_name} WHERE n_true > 0"


def attacked(true: str, true_masks: str, seen_masks: str, name: str, bp: str) -> str:
    """CTE ``name`` (rp): privacy of all 1s against one who knows the itemsets ``true``; flipped and infrequent 1s keep ``bp``."""
    return f"""{name}_hit AS MATERIALIZED (SELECT x.code, s.tid, t.mask AS tmask, s.mask AS smask FROM {true} x JOIN {seen_masks} s ON s.mask & x.code = x.code JOIN {true_masks} t ON t.tid = s.tid),
{name}_br AS MATERIALIZED (SELECT h.code, items.item, count(*) AS matched, count_if(h.tmask & (1::HUGEINT << items.item) <> 0) AS present FROM {name}_hit h JOIN items ON h.code & (1::HUGEINT << items.item) <> 0 GROUP BY ALL),
{name}_w AS MATERIALIZED (SELECT h.tid, b.item, max(b.present / b.matched) AS breach FROM {name}_hit h JOIN {name}_br b ON b.code = h.code WHERE h.tmask & h.smask & (1::HUGEINT << b.item) <> 0 GROUP BY ALL),
{name} AS (SELECT (sum(100 * (1 - breach)) + ((SELECT count(*) FROM t) - count(*)) * ({bp})) / (SELECT count(*) FROM t) AS rp FROM {name}_w)"""
