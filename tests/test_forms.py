"""Further forms: trie counting, vectorised reconstruction, Arrow functions, late rows, sinks."""

import datetime as dt
import random
from itertools import combinations

import numpy as np
import pytest
from pyspark.sql import functions as F

from flipmine.config import FlipParams
from flipmine.functions import sqlfuncs
from flipmine.operators import counting, distort, metrics, mining, reconstruct
from flipmine.schemas import EVENTS
from flipmine.sources import shared, tables
from flipmine.streaming import streams

MAIN = FlipParams(0.6, 0.96)


def test_trie_counts_like_the_others(tiny):
    arrays = tiny.arrays()
    for k in (1, 2, 3, 6):
        sets = list(combinations(range(tiny.n_items), k))
        assert counting.count(arrays, sets, tiny.n_items, "trie") == counting.count(arrays, sets, tiny.n_items)
    assert counting.count(arrays.limit(0), [(0, 1)], tiny.n_items, "trie") == {(0, 1): 0}


@pytest.mark.parametrize("dbsize", [1000, 10**17])
def test_numerators_at_once_are_those_one_by_one(dbsize):
    rng = random.Random(1)
    store, counts = mining.PassStore(), {}
    for k in (1, 2, 3, 4):
        found = {x: rng.randrange(dbsize) for x in combinations(range(7), k)}
        store.keep(dict(rng.sample(sorted(found.items()), len(found))))
        counts |= found
        level = list(found)
        assert reconstruct.numerators(level, store.tables, dbsize, MAIN).tolist() == [reconstruct.numerator(x, counts.__getitem__, dbsize, MAIN) for x in level]
    with pytest.raises(KeyError):
        reconstruct.numerators([(0, 9)], store.tables, dbsize, MAIN)


def test_blocks_cut_by_bytes(tiny, monkeypatch):
    sets = list(combinations(range(tiny.n_items), 2))
    whole = counting.count(tiny.arrays(), sets, tiny.n_items)
    monkeypatch.setattr(counting, "BLOCK_BYTES", 60)
    assert counting.count(tiny.arrays(), sets, tiny.n_items) == whole


def test_arrow_functions_over_bit_vectors(spark, tiny):
    bits = distort.to_bits(tiny.arrays(), tiny.n_items)
    got = {r.tid: bytes(r.bits) for r in bits.select("tid", sqlfuncs.flip_bits(MAIN, tiny.n_items, 5)("bits", "tid").alias("bits")).collect()}
    assert got == {r.tid: bytes(r.bits) for r in distort.flip_bitvectors(bits, tiny.n_items, MAIN, 5).collect()}
    sqlfuncs.register(spark, MAIN, tiny.n_items, 5)
    bits.createOrReplaceTempView("row_bits")
    held = [np.frombuffer(bytes(r.bits), np.uint8) for r in bits.collect()]
    assert bytes(spark.sql("SELECT bits_and(bits) AS b FROM row_bits").first().b) == np.bitwise_and.reduce(held).tobytes()
    assert {r.tid: bytes(r.b) for r in spark.sql("SELECT tid, flip_bits(bits, tid) AS b FROM row_bits").collect()} == got


def test_rules_of_an_itemset_by_table_function(spark):
    sqlfuncs.register(spark)
    rows = spark.sql("SELECT * FROM itemset_rules(array(3, 7), array(1.0D, 0.5D, 0.4D, 0.3D), 0.7D)").collect()
    assert [(r.antecedent, r.consequent, r.confidence) for r in rows] == [([7], [3], pytest.approx(0.75))]
    assert spark.sql("SELECT * FROM itemset_rules(array(3, 7))").count() == 2


def test_work_and_privacy_rows():
    assert metrics.work({1: 4, 2: 6}, 50, 100, "ones") == (10, 10, 50)
    assert metrics.work({1: 4, 2: 6}, 50, 100, "weight") == (10, 26, 1000)
    assert metrics.privacy_row(90.0, 70.0) == {"bp": 90.0, "rp": 70.0, "lost": 20.0}


def event(i, minute, user=1, value=1.0):
    return (i, dt.datetime(2024, 1, 1) + dt.timedelta(minutes=minute), user, "view", value, '{"k": 1}')


def test_late_rows_are_counted(spark, tmp_path):
    for i, rows in enumerate(([event(1, 0), event(2, 4 * 1440)], [event(3, 5 * 1440)], [event(4, 1)])):
        spark.createDataFrame(rows, EVENTS).coalesce(1).write.mode("append").parquet(str(tmp_path / "in"))
        del i
    seen = []
    out = streams.run_once(streams.window_counts(streams.read_folder(spark, str(tmp_path / "in"), EVENTS)), "append", lambda q: seen.append(streams.late_rows(q)))
    assert seen == [1] and out.agg(F.sum("n")).first()[0] == 1  # later windows are still open


def test_running_totals(spark, tmp_path):
    spark.createDataFrame([event(1, 0, 1, 2.0), event(2, 1, 1, 3.0), event(3, 2, 2, 1.0)], EVENTS).coalesce(1).write.parquet(str(tmp_path / "in"))
    out = streams.run_once(streams.running_totals(streams.read_folder(spark, str(tmp_path / "in"), EVENTS)), "update")
    assert sorted(map(tuple, out.collect())) == [(1, 2, 5.0), (2, 1, 1.0)]


def test_sinks(spark, tiny, tmp_path):
    columns = counting.column_bits(tiny.long)
    tables.write_columns(columns, str(tmp_path / "columns"))
    key = lambda r: (r.chunk, r.item)
    assert sorted(map(key, spark.read.parquet(str(tmp_path / "columns")).collect())) == sorted(map(key, columns.collect()))
    for run, n in (("a", 1), ("b", 2), ("a", 3)):
        tables.write_result(spark.range(n).toDF("x"), str(tmp_path / "out"), run)
    assert {r.run: r["count"] for r in spark.read.parquet(str(tmp_path / "out")).groupBy("run").count().collect()} == {"a": 3, "b": 2}


def test_text_lists_have_the_same_tids_however_they_are_split(spark, tmp_path):
    (tmp_path / "lists.txt").write_text("1 2\n3\n1 2\n\n")
    read = lambda: sorted((r.tid, r["items"]) for r in tables.read_item_lists(spark, str(tmp_path / "lists.txt")).collect())
    whole = read()
    before = spark.conf.get("spark.sql.files.maxPartitionBytes")
    spark.conf.set("spark.sql.files.maxPartitionBytes", "3b")
    try:
        assert read() == whole
    finally:
        spark.conf.set("spark.sql.files.maxPartitionBytes", before)
    assert len({tid for tid, _ in whole}) == 4 and sorted(x for _, x in whole) == [[], [1, 2], [1, 2], [3]]


def test_rule_identity(spark):
    rows = lambda *x: spark.createDataFrame([([a], [b]) for a, b in x], "antecedent array<int>, consequent array<int>")
    got = metrics.rule_identity(rows((1, 2), (2, 1), (3, 1)), rows((1, 2), (5, 1))).first()
    assert (got.precision, got.recall) == (pytest.approx(1 / 3), 0.5)


def test_stored_tables_can_be_discarded(spark):
    kept = shared.stored(spark.range(3).toDF("x"), "thrown")
    path = kept.inputFiles()[0]
    assert kept.count() == 3
    import os

    assert os.path.exists(path.removeprefix("file://"))
    shared.discard(spark)
    assert not os.path.exists(path.removeprefix("file://"))
