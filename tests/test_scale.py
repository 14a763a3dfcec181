"""Forms for tables and universes at size: the same results as the plain forms, without what made those too slow or too large."""

from itertools import combinations

import numpy as np
import pyarrow as pa
import pytest
from pyspark.sql import functions as F

from flipmine.config import FlipParams
from flipmine.functions import native
from flipmine.functions.coins import below, coins
from flipmine.operators import counting, distort, mining, privacy
from flipmine.plans import catalog, experiments
from flipmine.sources.shared import stored

SF = "/root/testdata/sf0.001"
P = FlipParams(0.6, 0.96)


def refuse(*_, **__):
    raise AssertionError("called")


def sql_coins(spark, seed, tids, items):
    """{(tid, item): coin} by the built-in functions."""
    cells = spark.createDataFrame([(t, i) for t in tids for i in items], "tid long, item int")
    return {(r.tid, r.item): r.u for r in cells.select("tid", "item", distort.coin(F.col("tid"), F.col("item"), seed).alias("u")).collect()}


@pytest.mark.parametrize("seed", [42, 10**60])
def test_blocks_of_coins_are_the_built_in_ones(spark, seed):
    tids, items = [None, 0, -3, 7, 99, 12345, 2**63 - 1], [0, 9, 10, 99, 100, 12345, 1_199_999]
    got = {(tids[c], items[r]): int(u[i, j]) for rows, columns, u in coins(seed, tids, np.array(items)) for i, r in enumerate(rows) for j, c in enumerate(columns)}
    assert got == sql_coins(spark, seed, tids, items)


def test_f2_density_tosses_a_coin_once_for_all_settings(spark, tiny, monkeypatch):
    settings = [FlipParams(0.9, 0.9), P]
    both = distort.flip_counts(tiny.arrays(), tiny.n_items, settings, 42)
    for params, counts in zip(settings, both, strict=True):
        seen = distort.flip_arrays(tiny.arrays(), tiny.n_items, params, 42).select(F.explode("items").alias("item")).groupBy("item").count()
        assert {r.item: r["count"] for r in seen.collect()} == {i: n for i, n in enumerate(counts.tolist()) if n}
    monkeypatch.setattr(distort, "flip_arrays", refuse)
    assert catalog.QUERIES["exp_density"](spark, SF).count() == 35


def test_f3_sparsity_keeps_no_distorted_table(spark, monkeypatch):
    monkeypatch.setattr(experiments, "distorted", refuse)
    assert catalog.QUERIES["exp_sparsity"](spark, SF).count() == 7


def test_f6_pairs_mined_at_the_source_are_those_of_the_kept_table(spark, tiny, monkeypatch):
    arrays, size = stored(tiny.arrays(), "true"), tiny.dbsize()
    plain = mining.mine_distorted(stored(distort.flip_arrays(arrays, tiny.n_items, P, 42), "seen"), tiny.n_items, size, P, "0.485", 3)
    found = mining.mine_at_source(arrays, tiny.n_items, size, P, 42, "0.485", 3)
    assert (found.support, found.counts, found.candidates) == (plain.support, plain.counts, plain.candidates)
    assert 0 < len({i for x in found.support for i in x}) < tiny.n_items
    monkeypatch.setattr(experiments, "distorted", refuse)
    assert catalog.QUERIES["mined_pairs_supp"](spark, SF).count()


def test_f8_customers_pairs_keep_no_distorted_table(spark, monkeypatch):
    monkeypatch.setattr(experiments, "distorted", refuse)
    assert catalog.QUERIES["mined_pairs_cust_supp"](spark, SF).count()


def test_f10_singletons_are_counted_where_they_are_distorted(spark, monkeypatch):
    plain = counting.singletons(distort.flip_cells(catalog.of(spark, SF, "cust_supp"), catalog.MAIN, 42).long)
    want = {r["item"]: r.n for r in plain.collect()}
    monkeypatch.setattr(distort, "flip_cells", refuse)
    assert {r["item"]: r.n for r in catalog.QUERIES["cust_supp_recon"](spark, SF).collect()} == want


def test_f1_patterns_are_counted_in_blocks(spark, tiny, monkeypatch):
    arrays = stored(distort.flip_arrays(tiny.arrays(), tiny.n_items, P, 42), "seen")
    sets = [(0, 1, 3), (1, 2, 5), (0, 4, 5)]
    plain = counting.pattern_counts(arrays.select("tid", F.explode("items").alias("item")), sets, tiny.dbsize())
    got = {(r.cand, r.pattern): r.n for r in counting.patterns_by_chunks(arrays, sets, tiny.n_items).collect()}
    assert got == {(r.cand, r.pattern): r.n for r in plain.collect() if r.n}
    monkeypatch.setattr(counting, "pattern_counts", refuse)
    assert mining.mine_full_pattern(arrays, tiny.n_items, tiny.dbsize(), P, "0.003", 2).support


SETTINGS = [FlipParams(0.3, 0.99), P, FlipParams(0.8, 0.96)]
NAMES = ["s0", "s1", "s2"]


def test_f4_settings_share_a_toss_a_pass_and_the_result(spark, tiny):
    arrays, size = stored(tiny.arrays(), "true"), tiny.dbsize()
    table = stored(distort.flip_lists(arrays, tiny.n_items, SETTINGS, 42), "seen")
    plain = [stored(distort.flip_arrays(arrays, tiny.n_items, s, 42), "plain") for s in SETTINGS]
    for name, one in zip(NAMES, plain, strict=True):
        assert sorted(map(repr, table.select("tid", name).collect())) == sorted(map(repr, one.withColumnRenamed("items", name).collect()))
    found = mining.mine_together(lambda levels: counting.count_tables(table, ["items", *NAMES], levels, tiny.n_items), tiny.n_items, size, [None, *SETTINGS], "0.1", 3)
    want = [mining.mine_exact(arrays, tiny.n_items, size, "0.1", 3)] + [mining.mine_distorted(one, tiny.n_items, size, s, "0.1", 3) for one, s in zip(plain, SETTINGS, strict=True)]
    for a, b in zip(found, want, strict=True):
        assert (a.support, a.counts, a.candidates, a.counters) == (b.support, b.counts, b.candidates, b.counters)
    sets = sorted(want[0].support)
    assert {len(x) for x in sets} == {1, 2, 3}
    itemsets = spark.createDataFrame([(i, list(x), len(x)) for i, x in enumerate(sets)], "cand int, itemset array<int>, k int")
    for one, (rp, _) in zip(plain, privacy.reinterrogated_tables(table, NAMES, sets, tiny.n_items, [60.0] * 3), strict=True):
        seen = one.select("tid", F.explode("items").alias("item"))
        assert privacy.reinterrogated(tiny.long, seen, itemsets, 60.0).first().privacy == pytest.approx(rp)


def test_f4_summary_keeps_one_table_for_all_settings(spark, monkeypatch):
    for module, name in ((experiments, "distorted"), (mining, "mine_distorted"), (mining, "mine_exact")):
        monkeypatch.setattr(module, name, refuse)
    assert catalog.QUERIES["exp_summary_clicks"](spark, SF).count() == 11


def test_f5_sampled_items_are_counted_as_they_are_drawn(spark, tiny, monkeypatch):
    arrays = stored(tiny.arrays(), "true")
    true, seen, held = distort.flip_sparse_counts(arrays, tiny.n_items, SETTINGS, 42)
    rows = distort.flip_lists(arrays.repartition(3), tiny.n_items, SETTINGS, 42, sparse=True).collect()
    for i in range(tiny.n_items):
        assert true[i] == sum(i in r["items"] for r in rows)
        assert seen[:, i].tolist() == [sum(i in r[n] for r in rows) for n in NAMES]
        assert held[:, i].tolist() == [sum(i in r[n] and i in r["items"] for r in rows) for n in NAMES]
    assert all(r[n] == sorted(set(r[n])) for r in rows for n in NAMES)
    sets = [(i,) for i in range(tiny.n_items)]
    table = distort.flip_lists(arrays, tiny.n_items, SETTINGS, 42, sparse=True)
    for n, k, (rp, _) in zip(seen, held, privacy.reinterrogated_tables(table, NAMES, sets, tiny.n_items, [60.0] * 3), strict=True):
        assert experiments._single_items_privacy(list(range(tiny.n_items)), int(true.sum()), n, k, 60.0) == pytest.approx(rp)
    monkeypatch.setattr(distort, "flip_lists", refuse)
    assert catalog.QUERIES["exp_summary_parts"](spark, SF).count() == 11


@pytest.mark.parametrize(("n_items", "tuples"), [(40, 6000), (5000, 60)])
def test_f7_f11_blocks_of_draws_have_the_rates_asked_for(n_items, tuples):
    """Each setting shows absent items at 1 - q and keeps true ones at p, wherever they stand, whatever the cut of the tuples."""
    lists = pa.array([[i % n_items, n_items - 1] if i % n_items < n_items - 1 else [n_items - 1] for i in range(tuples)], pa.list_(pa.int32()))
    low, bars, keeps = distort._levels_of(SETTINGS)
    false, kept, got = np.zeros((3, n_items)), np.zeros(3), {}
    for at, cells, levels, held, toss in distort._draws(np.arange(tuples), lists, n_items, low, 42):
        assert (np.diff(cells) > 0).all()
        got |= {(at + c // n_items, c % n_items): x for c, x in zip(cells.tolist(), levels.tolist(), strict=True)}
        for i in range(3):
            false[i] += np.bincount(cells[levels >= bars[i]] % n_items, minlength=n_items)
            kept[i] += (toss < keeps[i]).sum()
    held_cells = len(lists.flatten())
    for i, s in enumerate(SETTINGS):
        n = n_items * tuples
        assert abs(false[i].sum() - n * (1 - s.q)) < 5 * (n * s.q * (1 - s.q)) ** 0.5
        assert abs(kept[i] - held_cells * s.p) < 5 * (held_cells * s.p * (1 - s.p)) ** 0.5
        half = false[i][: n_items // 2].sum()
        assert abs(half - n / 2 * (1 - s.q)) < 5 * (n / 2 * (1 - s.q)) ** 0.5
    cut = {}
    for begin in (0, 17):
        part = slice(begin, 17 if not begin else None)
        tids = np.arange(tuples)[part]
        for at, cells, levels, _, _ in distort._draws(tids, lists[part], n_items, low, 42):
            cut |= {(int(tids[0]) + at + c // n_items, c % n_items): x for c, x in zip(cells.tolist(), levels.tolist(), strict=True)}
    assert cut == got


def test_f9_wide_universes_are_numbered_and_their_items_counted_as_they_are_drawn(spark, monkeypatch):
    labels = spark.range(200_001).select(F.col("id").cast("string").alias("label"))
    assert catalog.baskets.dictionary(labels)[1] == 200_001
    plain = distort.flip_sparse(catalog.of(spark, SF, "part").arrays(), 200, FlipParams(0.3, 0.99), 42).select(F.explode("items").alias("item")).groupBy("item").count()
    seen, size = {r["item"]: r["count"] for r in plain.collect()}, catalog.of(spark, SF, "part").dbsize()
    monkeypatch.setattr(distort, "flip_sparse", refuse)
    got = catalog.QUERIES["part_sparse_recon"](spark, SF).collect()
    assert len(got) == catalog.of(spark, SF, "part").n_items == 200
    assert all(r.est == pytest.approx((100 * seen.get(r["item"], 0) - size) / 29, abs=1e-6) for r in got)


@pytest.mark.parametrize(("n_items", "settings", "kind"), [(5000, SETTINGS, np.int32), (1_999_999, [FlipParams(0.5, 0.99999999)], np.int64)])
def test_f5_cells_take_four_bytes_where_they_fit(n_items, settings, kind):
    """Small cells, and no list of all keys beside them; cells that are true as well are counted by their own coins alone."""
    lists = pa.array([[0, i, n_items - 1] for i in range(1, 4001)], pa.list_(pa.int32()))
    low, bars, keeps = distort._levels_of(settings)
    for _, cells, levels, _, _ in distort._draws(np.arange(4000), lists, n_items, low, 42):
        assert cells.dtype == kind and levels.dtype == np.int32
        assert ((cells >= 0) & (np.diff(cells, prepend=-1) > 0)).all()
    above, below = np.unique(bars), np.unique(keeps)
    assert distort._classes(np.array([0, 1 << 23, (1 << 24) - 1], np.int32), above).tolist() == [np.count_nonzero(above[1:] <= x) for x in (0, 1 << 23, (1 << 24) - 1)]
    for table, bar, keep in zip(distort._shown(above, below, bars, keeps), bars, keeps, strict=True):
        assert table.tolist() == [b >= bar for b in above] + [True] * (np.searchsorted(below, keep) + 1) + [False] * (len(below) - np.searchsorted(below, keep)) + [False]


def test_f7_lists_are_gathered_without_a_join(spark, monkeypatch):
    b = catalog.of(spark, SF, "name_type")
    plain = sorted(map(tuple, b.arrays().collect()))
    assert sorted(map(tuple, catalog.baskets.gathered(b.pairs, b.tids, 3).collect())) == plain and plain
    tids = spark.createDataFrame([(1,), (1,), (None,), (5,)], "tid long")
    pairs = spark.createDataFrame([(1, 3), (1, 3), (1, 2), (7, 1)], "tid long, item int")
    assert sorted(map(repr, catalog.baskets.gathered(pairs, tids, 2).collect())) == sorted(["Row(tid=1, items=[2, 3])"] * 2 + ["Row(tid=None, items=[])", "Row(tid=5, items=[])"])
    monkeypatch.setattr(catalog.baskets.Baskets, "_plain_arrays", refuse)
    assert catalog.QUERIES["exp_summary_name_type"](spark, SF).count() == 4


@pytest.mark.parametrize("sparse", [False, True])
def test_f7_f11_packed_lists_count_and_betray_as_lists_do(spark, tiny, monkeypatch, sparse):
    arrays, n = stored(tiny.arrays(), "true"), tiny.n_items
    plain, table = (stored(distort.flip_lists(arrays, n, SETTINGS, 42, sparse, as_bytes=x), "seen") for x in (False, True))
    assert dict(table.dtypes)["s0"] == "binary"
    sets = sorted(x for m in (1, 2, 3) for x in combinations(range(n), m))
    for cost in (0, 10**9):  # all pairs of the tuples, or all candidates
        monkeypatch.setattr(counting, "PAIR_COST", cost)
        for k in (1, 2, 3):
            level = [x for x in sets if len(x) == k][1:]
            for name, got in zip(NAMES, counting.count_tables(table, NAMES, [level] * 3, n), strict=True):
                assert got.tolist() == list(counting.count(plain.select("tid", plain[name].alias("items")), level, n, "relational").values())
    want = privacy.reinterrogated_tables(plain, NAMES, sets, n, [60.0] * 3)
    monkeypatch.setattr(privacy, "WORDS", 1)
    got = privacy.reinterrogated_tables(table, NAMES, sets, n, [60.0] * 3)
    itemsets = spark.createDataFrame([(i, list(x), len(x)) for i, x in enumerate(sets)], "cand int, itemset array<int>, k int")
    for name, (a, breaches), (b, others) in zip(NAMES, got, want, strict=True):
        assert (a, breaches) == (pytest.approx(b), others)
        seen = plain.select("tid", F.explode(name).alias("item"))
        assert privacy.reinterrogated(tiny.long, seen, itemsets, 60.0).first().privacy == pytest.approx(a)


def test_f11_generated_lists_are_made_where_they_are_needed(spark):
    from flipmine.sources import generator

    b = generator.pattern_baskets(spark, 300, 50)
    assert "Exchange" not in b.arrays()._jdf.queryExecution().executedPlan().toString()
    assert sorted(map(tuple, b.arrays().collect())) == sorted(map(tuple, b._plain_arrays().collect()))


#: Queries that once made up what they worked on.
READ_A_TABLE = [
    "zero_privacy",
    "transition_matrix",
    "transition_column_sums",
    "spurious_probability",
    "pattern_generator",
    "param_grid",
    "param_candidates_001",
    "param_candidates_0005",
    "expected_density",
    "error_index",
    "channel_condition",
    "basic_privacy_surface",
]


@pytest.mark.parametrize("name", READ_A_TABLE)
def test_reads_a_given_table_and_equals_its_sql(spark, monkeypatch, name):
    import duckdb

    asked, read = [], catalog.baskets.load
    for module in (catalog, catalog.baskets):
        monkeypatch.setattr(module, "load", lambda *a: asked.append(a[2]) or read(*a))
    df = catalog.QUERIES[name](spark, SF)
    got, names = df.collect(), df.columns
    assert "orders" in asked or "lineitem" in asked
    if name in catalog.ORACLES:
        con = duckdb.connect()
        for table in ("orders", "lineitem", "part"):
            con.execute(f"CREATE VIEW {table} AS SELECT * FROM '{SF}/{table}.parquet'")
        want = con.execute(f"SELECT {', '.join(names)} FROM ({catalog.ORACLES[name]})").fetchall()
        plain = lambda rows: sorted(tuple(round(x, 6) if isinstance(x, float) else x for x in r) for r in rows)
        assert plain(want) == plain(tuple(r) for r in got)


@pytest.mark.parametrize("seed", [42, 10**40])
def test_f8_first_bits_decide_as_whole_coins_do(seed):
    """Bars that are a coin, or next to one, are met to the last bit; the digest's last steps are left out, not its bits."""
    from hashlib import md5

    from flipmine.functions.coins import below

    tids, items = [5, None, 123, 99_999, 10**12, -7], np.array([0, 7, 12, 345, 6_789, 60_001])
    text = lambda i, t: f"{seed}|{t}|{i}" if t is not None else f"{seed}|{i}"
    want = {(i, j): int(md5(text(i, t).encode()).hexdigest()[:13], 16) for i in items.tolist() for j, t in enumerate(tids)}
    some = want[345, 2]
    bars, met = [0, 1, int(0.3 * 2**52), some - 1, some, some + 1, (some >> 20) << 20, 2**52], set()
    for rows, columns, under in below(seed, tids, items, bars):
        for i, row in enumerate(rows):
            for j, column in enumerate(columns):
                cell = int(items[row]), int(column)
                met.add(cell)
                assert [bool(u[i, j]) for u in under] == [want[cell] < bar for bar in bars]
    assert met == set(want)


@pytest.mark.parametrize(("seed", "n_items", "tids"), [(42, 12_345, range(95, 115)), (42, 1_030, [None, 7, 10**12, -3]), (10**40, 105, [1, 12_345_678_901]), (-7, 3, [0, 1])])
def test_f1_a_process_counts_the_coins_that_columns_count(spark, seed, n_items, tids):
    tids = list(tids)
    lists = [[i for i in range(n_items) if i % 7 == j % 5] * (1 + j % 2) for j in range(len(tids))]
    batch = pa.RecordBatch.from_arrays([pa.array(tids, pa.int64()), pa.array(lists, pa.list_(pa.int32()))], ["tid", "items"])
    settings = [(2**51, 2**51), (1 << 50, 3 << 50), (0, 2**52), (2**52, 0), FlipParams(0.6, 0.96).thresholds]
    # a bar on a coin itself: its first bits are a tie, the last ones decide
    (rows, columns, u), *_ = coins(seed, tids[:1], np.arange(min(n_items, 10)))
    settings += [(int(u[0, 0]), int(u[0, 0])), (int(u[0, 0]) + 1, int(u[0, 0]) + 1)]
    want = np.zeros((len(settings), n_items), int)
    held = np.array([[i in set(x) for x in lists] for i in range(n_items)])
    for rows, columns, under in below(seed, tids, np.arange(n_items), [bar for pair in settings for bar in pair]):
        for i in range(len(settings)):
            want[i, rows] += np.where(held[np.ix_(rows, columns)], under[2 * i], ~under[2 * i + 1]).sum(1)
    code = native.compiled(spark)
    assert code
    assert (native.flipped(code, seed, n_items, settings, iter([batch.slice(0, 1), batch.slice(1)])) == want).all()


def test_f1_wide_universes_are_counted_by_a_process(spark, monkeypatch):
    """As many cells as make it worth its start, and again where there is no Java: the same counts."""
    arrays = spark.range(64).selectExpr("id AS tid", "array(cast(id AS int), 40000) AS items").coalesce(1)
    settings = [FlipParams(0.9, 0.9), FlipParams(0.3, 0.99)]
    monkeypatch.setattr(distort, "spread", lambda df: df)
    by_process = distort.flip_counts(arrays, 50_000, settings, 42)
    monkeypatch.setattr(native, "compiled", lambda _: {})
    by_columns = distort.flip_counts(arrays, 50_000, settings, 42)
    assert native.WORTH <= 64 * 50_000
    assert all((a == b).all() for a, b in zip(by_process, by_columns, strict=True))


def test_f2_single_items_are_counted_from_the_lists(spark, tiny, monkeypatch):
    arrays = stored(tiny.arrays(), "true")
    plain = {(r["item"],): r.n for r in counting.singletons(tiny.long).collect()}
    monkeypatch.setattr(counting, "_dense", refuse)
    monkeypatch.setattr(counting, "_partials", refuse)
    sets = [(i,) for i in reversed(range(tiny.n_items))]
    assert counting.count(arrays, sets, tiny.n_items) == {x: plain.get(x, 0) for x in sets}
    assert counting.count(arrays, sets[1:2], tiny.n_items) == {sets[1]: plain[sets[1]]}
