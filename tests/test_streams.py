import datetime as dt

from pyspark.sql import functions as F

from flipmine.config import FlipParams
from flipmine.operators import distort
from flipmine.schemas import EVENTS
from flipmine.streaming import streams

SF = "/root/testdata/sf0.001"


def folder(spark, tmp_path, batches):
    for i, rows in enumerate(batches):
        spark.createDataFrame(rows, EVENTS).coalesce(1).write.mode("append").parquet(str(tmp_path / "in"))
        del i
    return streams.read_folder(spark, str(tmp_path / "in"), EVENTS)


def row(i, minute, user=1, kind="view", value=1.0):
    return (i, dt.datetime(2024, 1, 1) + dt.timedelta(minutes=minute), user, kind, value, '{"k": 1}')


def test_stream_equals_batch(spark, tiny):
    p = FlipParams(0.6, 0.96)
    arrays = tiny.arrays()
    got = {r.tid: r["items"] for r in streams.distort_table(arrays, tiny.n_items, p, 42).collect()}
    assert got == {r.tid: r["items"] for r in distort.flip_arrays(arrays, tiny.n_items, p, 42).collect()}


def test_windows_in_all_modes(spark, tmp_path):
    rows = [row(i, 60 * i) for i in range(60)]
    for mode in ("complete", "append"):
        out = streams.run_once(streams.window_counts(folder(spark, tmp_path / mode, [rows])), mode)
        expected = 3 if mode == "complete" else 2  # the last window is still open
        assert out.count() == expected
    sliding = streams.run_once(streams.window_counts(folder(spark, tmp_path / "slide", [rows]), slide="12 hours"), "complete")
    assert sliding.agg(F.sum("n")).first()[0] == 120


def test_sessions_repeats_and_joins(spark, tmp_path):
    rows = [row(1, 0), row(1, 0), row(2, 10), row(3, 100), row(4, 10_000)]
    assert streams.run_once(streams.without_repeats(folder(spark, tmp_path / "a", [rows]))).count() == 4
    baskets = streams.run_once(streams.session_baskets(folder(spark, tmp_path / "b", [rows]))).collect()
    assert len(baskets) == 2  # the last session has not ended
    pair = [row(1, 0), row(2, 5, kind="purchase"), row(3, 500, kind="purchase")]
    assert [tuple(r) for r in streams.run_once(streams.click_then_purchase(folder(spark, tmp_path / "c", [pair]))).collect()] == [(1, 2)]
    items = spark.createDataFrame([(0, "view")], "item int, label string")
    assert streams.run_once(streams.with_dictionary(folder(spark, tmp_path / "d", [rows]), items)).count() == 5


def test_incremental_counts_and_redelivery(spark):
    one, two = spark.createDataFrame([(1, "a"), (2, "b")], "i int, k string"), spark.createDataFrame([(3, "a")], "i int, k string")
    counts = streams.IncrementalCounts(spark, lambda df: df.groupBy("k").agg(F.count(F.lit(1)).alias("n")))
    for number, batch in ((0, one), (1, two), (1, two)):
        counts(batch, number)
    assert {r.k: r.n for r in counts.total(["k"]).collect()} == {"a": 2, "b": 1}


def test_window_estimates(spark, tmp_path):
    schema = "tid long, ts timestamp, items array<int>"
    day = dt.datetime(2024, 1, 1)
    rows = [(i, day, [0] if i < 1743 else []) for i in range(15000)] + [(99999, day + dt.timedelta(days=5), [])]
    spark.createDataFrame(rows, schema).coalesce(1).write.parquet(str(tmp_path / "in"))
    from pyspark.sql import types as T

    p = FlipParams(0.6, 0.96)
    stream = streams.read_folder(spark, str(tmp_path / "in"), T.StructType.fromDDL(schema))
    got = streams.estimates_of(streams.run_once(streams.window_recon(stream, p)), p).first()
    assert got.n == 1743 and abs(got.est - 2041.0714) < 1e-3
