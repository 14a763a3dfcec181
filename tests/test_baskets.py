from itertools import combinations

import numpy as np
import pytest
from pyspark.sql import functions as F

from flipmine.config import CandidateBudgetExceeded, FlipParams
from flipmine.functions import channel, sqlfuncs
from flipmine.operators import counting, distort, metrics, mining, privacy, reconstruct, rules
from flipmine.sources import baskets, generator, tables
from flipmine.sources.shared import stored

P = FlipParams(0.6, 0.96)


@pytest.fixture(scope="module")
def arrays(tiny):
    return stored(tiny.arrays(), "t")


@pytest.fixture(scope="module")
def truth(arrays):
    return {r.tid: tuple(r["items"]) for r in arrays.collect()}


@pytest.fixture(scope="module")
def seen(arrays, tiny):
    return stored(distort.flip_arrays(arrays, tiny.n_items, P, 42), "d")


def support(rows, itemset):
    return sum(set(itemset) <= set(x) for x in rows.values())


def test_empty_tuples_count(tiny, truth):
    assert len(truth) == 1500 == tiny.dbsize()
    assert any(not x for x in truth.values())


def test_distortion_does_not_depend_on_partitions_and_equals_the_owner_s(arrays, truth, seen, tiny):
    again = {r.tid: r["items"] for r in distort.flip_arrays(arrays.repartition(7), tiny.n_items, P, 42).collect()}
    assert again == {r.tid: r["items"] for r in seen.collect()}
    for tid in list(truth)[:50]:
        assert distort.flip_tuple(list(truth[tid]), tiny.n_items, P, 42, tid) == again[tid]


def test_no_distortion_is_the_identity(arrays, truth, tiny):
    assert {r.tid: tuple(r["items"]) for r in distort.flip_arrays(arrays, tiny.n_items, FlipParams(1, 1), 42).collect()} == truth


def test_sparse_sampler_and_bits_have_the_right_rates(arrays, truth, tiny):
    bits = distort.to_bits(arrays, tiny.n_items)
    assert {r.tid: tuple(r["items"]) for r in distort.from_bits(bits, tiny.n_items).collect()} == truth
    ones = sum(map(len, truth.values()))
    zeros = len(truth) * tiny.n_items - ones
    for df in (distort.flip_sparse(arrays, tiny.n_items, P, 3), distort.from_bits(distort.flip_bitvectors(bits, tiny.n_items, P, 3), tiny.n_items)):
        rows = {r.tid: set(r["items"]) for r in df.collect()}
        kept = sum(len(rows[t] & set(x)) for t, x in truth.items())
        made = sum(len(rows[t] - set(x)) for t, x in truth.items())
        assert abs(kept - 0.6 * ones) < 5 * (ones * 0.24) ** 0.5
        assert abs(made - 0.04 * zeros) < 5 * (zeros * 0.0384) ** 0.5


@pytest.mark.parametrize("way", ["chunks", "relational", "bitmaps", "gram"])
def test_physical_ways_agree(arrays, truth, tiny, way):
    sets = list(combinations(range(tiny.n_items), 2))
    assert counting.count(arrays, sets, tiny.n_items, way) == {x: support(truth, x) for x in sets}


def test_strategies_agree(seen, tiny):
    sets, n = list(combinations(range(tiny.n_items), 3)), tiny.dbsize()
    long = seen.select("tid", F.explode("items").alias("item"))
    patterns = {(r.cand, r.pattern): r.n for r in counting.pattern_counts(long, sets, n).collect()}
    weights = {(r.cand, r.weight): r.n for r in counting.weight_counts(long, sets, n).collect()}
    dense = {(r.cand, r.weight): r.n for r in counting.weights_by_chunks(seen, sets, tiny.n_items).collect()}
    ones = counting.count(seen, sets, tiny.n_items)
    assert {k: v for k, v in weights.items() if v} == {k: v for k, v in dense.items() if v}
    for i, x in enumerate(sets):
        assert patterns.get((i, 7), 0) == ones[x] == weights.get((i, 3), 0)
        assert sum(v for (c, _), v in patterns.items() if c == i) == n
    assert [counting.counters(3, s) for s in ("pattern", "weight", "weight_explicit", "ones")] == [8, 4, 3, 1]


def test_pair_patterns_of_the_example(spark):
    known = spark.createDataFrame([([0], 30), ([1], 20), ([0, 1], 12)], "itemset array<int>, n long")
    cand = spark.createDataFrame([([0, 1], 2)], "itemset array<int>, k int")
    got = {r.pattern: r.n for r in reconstruct.pattern_from_subsets(cand, known, 100).collect()}
    assert got == {3: 12, 1: 18, 2: 8, 0: 62}
    classes = {r.weight: r.n for r in reconstruct.classes_from_subsets(cand, known, 100).collect()}
    assert classes == {2: 12, 1: 26, 0: 62}


def test_singleton_of_the_example(spark):
    row = spark.createDataFrame([(1743,)], "n long").select(reconstruct.singleton_expr(F.col("n"), 15000, P)).first()
    assert row[0] == pytest.approx(2041.0714285714)


def test_exact_miner_against_brute_force_and_fpgrowth(arrays, truth, tiny):
    found = mining.mine_exact(arrays, tiny.n_items, tiny.dbsize(), "0.1")
    every = {x: support(truth, x) for k in range(1, 7) for x in combinations(range(tiny.n_items), k)}
    assert {x: int(s) for x, s in found.support.items()} == {x: n for x, n in every.items() if n >= 150}
    theirs = {tuple(r.itemset): r.n for r in mining.fpgrowth(arrays, 0.1).collect()}
    assert theirs == {x: int(s) for x, s in found.support.items()}


def test_miners_of_distorted_data_agree(seen, tiny):
    a = mining.mine_distorted(seen, tiny.n_items, tiny.dbsize(), P, "0.05", 3)
    b = mining.mine_full_pattern(seen, tiny.n_items, tiny.dbsize(), P, "0.05", 3)
    assert a.support == b.support and a.counters < b.counters
    s = FlipParams(0.9, 0.9)
    d = stored(distort.flip_arrays(tiny.arrays(), tiny.n_items, s, 1), "s")
    assert mining.mine_symmetric(d, tiny.n_items, tiny.dbsize(), 0.9, "0.05", 3).support == mining.mine_distorted(d, tiny.n_items, tiny.dbsize(), s, "0.05", 3).support


def test_nothing_distorted_nothing_wrong(spark, arrays, tiny):
    exact = mining.mine_exact(arrays, tiny.n_items, tiny.dbsize(), "0.1")
    same = mining.mine_distorted(arrays, tiny.n_items, tiny.dbsize(), FlipParams(1, 1), "0.1")
    for r in metrics.by_level(same.frame(spark), exact.frame(spark)).collect():
        assert (r.sigma_plus, r.sigma_minus, r.rho) == (0, 0, 0)


def test_estimates_are_unbiased_and_vary_as_foretold():
    rng, p, q = np.random.default_rng(0), 0.6, 0.96
    table = np.zeros((1500, 2), bool)
    table[:400, 0] = table[300:700, 1] = True
    row = channel.support_row(2, p, q)
    got = []
    for _ in range(400):
        u = rng.random(table.shape)
        w = np.where(table, u < p, u >= q).sum(1)
        got.append(np.dot(row, np.bincount(w, minlength=3)))
    classes = np.bincount(table.sum(1), minlength=3).tolist()
    foretold = channel.variance(classes, p, q)
    assert abs(np.mean(got) - 100) < 4 * (foretold / 400) ** 0.5
    assert 0.75 < np.var(got) / foretold < 1.3


def test_candidates_both_ways(spark):
    frequent = [(0, 1), (0, 2), (1, 2), (1, 3), (2, 3)]
    plan = mining.candidates_frame(spark.createDataFrame([(list(x),) for x in frequent], "itemset array<int>"))
    assert mining.candidates(frequent) == [(0, 1, 2), (1, 2, 3)] == sorted(tuple(r.itemset) for r in plan.collect())
    with pytest.raises(CandidateBudgetExceeded):
        mining.candidates([(i,) for i in range(100)], budget=50)
    with pytest.raises(ValueError):
        mining.mine_exact(plan, 3, 1, 0)


def test_rules_and_shapes(spark):
    f = spark.createDataFrame([([0], 1, 50.0), ([1], 1, 40.0), ([0, 1], 2, 30.0)], "itemset array<int>, k int, est double")
    got = {(tuple(r.antecedent), tuple(r.consequent)): (r.support, r.confidence) for r in rules.generate(f, 100, 0.7).collect()}
    assert got == {((1,), (0,)): (0.3, 0.75)}
    assert [tuple(r.itemset) for r in mining.maximal(f).collect()] == [(0, 1)]
    wild = spark.createDataFrame([([0], 1, -2.0), ([1], 1, 10.0), ([0, 1], 2, 12.0)], "itemset array<int>, k int, est double")
    assert {tuple(r.itemset): r.est for r in reconstruct.sanitize(wild, 100, "monotone").collect()} == {(0,): 0.0, (1,): 10.0, (0, 1): 0.0}


def test_breach_of_the_example(spark):
    seen = spark.createDataFrame([(t, i) for t in range(100) for i in (0, 1, 2)], "tid long, item int")
    true = spark.createDataFrame([(t, 1) for t in range(20)], "tid long, item int")
    sets = counting.frame(spark, [(0, 1, 2)])
    assert {r.item: r.breach for r in privacy.breaches(true, seen, sets).collect()} == {0: 0.0, 1: 0.2, 2: 0.0}


def test_reinterrogation_both_ways(spark, tiny, arrays, seen):
    sets = sorted(mining.mine_exact(arrays, tiny.n_items, tiny.dbsize(), "0.2").support)
    long = seen.select("tid", F.explode("items").alias("item"))
    a = privacy.reinterrogated(tiny.long, long, counting.frame(spark, sets), 60.0).first().privacy
    b, _ = privacy.reinterrogated_chunks(arrays.join(seen.withColumnRenamed("items", "seen"), "tid"), sets, tiny.n_items, 60.0)
    assert a == pytest.approx(b) and a < 60


def test_weighted_privacy_is_never_above_the_average_one(spark):
    s = spark.createDataFrame([(i, x) for i, x in enumerate((0.01, 0.02, 0.3))], "item int, s double")
    assert privacy.basic_weighted(s, P).first().privacy <= privacy.basic(0.11, P.p, P.q) + 1e-9


def test_empty_truth_gives_nulls(spark):
    none = spark.createDataFrame([], "itemset array<int>, k int, est double")
    some = spark.createDataFrame([([0], 1, 5.0)], "itemset array<int>, k int, est double")
    row = metrics.identity_error(some, none).first()
    assert row.sigma_plus is None and row.sigma_minus is None


def test_files_and_functions(spark, tmp_path, arrays):
    for fmt in ("json", "orc", "parquet", "csv"):
        tables.write_item_lists(arrays, str(tmp_path / fmt), fmt)
        back = tables.read_item_lists(spark, str(tmp_path / fmt), fmt)
        assert {r.tid: [x for x in r["items"] or []] for r in back.collect()} == {r.tid: r["items"] for r in arrays.collect()}
    bits = distort.to_bits(arrays, 6)
    tables.write_bits(bits, str(tmp_path / "bits"), P, 6, 1500)
    again, params, n, size = tables.read_bits(spark, str(tmp_path / "bits"))
    assert again.count() == 1500 and (params.p, params.q, n, size) == (0.6, 0.96, 6, 1500)
    sqlfuncs.register(spark)
    assert spark.sql("SELECT basic_privacy(0.01, 0.4, 0.98)").first()[0] == pytest.approx(92.9085, abs=1e-3)
    assert spark.sql("SELECT count(*) FROM transition(3, 0.6D, 0.96D)").first()[0] == 16
    assert spark.sql("SELECT count(*) FROM itemset_subsets(array(1, 2, 3))").first()[0] == 8
    made = spark.read.format("pattern_baskets").option("tuples", 200).load()
    assert made.count() == 200 and made.where("size(items) > 0").count() == 200


def test_generator_and_adapters(spark):
    b = generator.pattern_baskets(spark, 2000)
    mean = b.long.count() / 2000
    assert 6 < mean < 16 and b.long.agg(F.max("item")).first()[0] < 1000
    sf = "/root/testdata/sf0.001"
    for one in (baskets.from_events(spark, sf), baskets.from_customers(spark, sf), baskets.from_pages(spark, sf), baskets.from_conversations(spark, sf), baskets.from_embeddings(spark, sf), baskets.from_documents(spark, sf, slice_=True), baskets.from_events(spark, sf, "type")):
        assert one.n_items > 1 and one.long.join(one.tids, "tid", "left_anti").isEmpty()
    twice = baskets.replicate(baskets.from_events(spark, sf), 2)
    assert twice.dbsize() == 2 * baskets.from_events(spark, sf).dbsize()
    with pytest.raises(ValueError):
        baskets.from_orders(spark, sf, "colour")
