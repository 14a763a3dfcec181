"""Streams: distortion at the source, and running counts. Each is a plan on a streaming DataFrame; ``run_once`` drains one."""

from __future__ import annotations

import uuid
from collections.abc import Callable, Iterator

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming import StreamingQuery

from ..config import FlipParams
from ..operators.distort import flip_arrays
from ..schemas import EVENTS
from ..sources.shared import shared_dir


def read_events(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The events table as a file stream."""
    return spark.readStream.schema(EVENTS).option("pathGlobFilter", "*.parquet").parquet(f"{sf_dir}/events.parquet*")


def read_folder(spark: SparkSession, path: str, schema, files_per_batch: int = 1) -> DataFrame:  # noqa: ANN001
    return spark.readStream.schema(schema).option("maxFilesPerTrigger", files_per_batch).parquet(path)


def read_table(df: DataFrame) -> DataFrame:
    """A table that was read from files, as a stream of these files."""
    folder = df.inputFiles()[0].rsplit("/", 1)[0]
    return df.sparkSession.readStream.schema(df.schema).parquet(folder)


def distort_stream(arrays: DataFrame, n_items: int, params: FlipParams, seed: int) -> DataFrame:
    """Stateless and narrow: a tuple is distorted where it arrives, by the coins of the batch form."""
    return flip_arrays(arrays, n_items, params, seed)


def window_counts(events: DataFrame, window: str = "1 day", slide: str | None = None, late: str = "1 hour") -> DataFrame:
    """(day, event_type, n) by tumbling or sliding windows; rows behind the watermark are dropped; ``late_rows`` says how many."""
    at = F.window("ts", window, slide) if slide else F.window("ts", window)
    return events.withWatermark("ts", late).groupBy(at.alias("w"), "event_type").agg(F.count(F.lit(1)).alias("n")).select(F.col("w.start").alias("day"), "event_type", "n")


def window_recon(arrays: DataFrame, params: FlipParams, window: str = "1 day", late: str = "1 hour") -> DataFrame:
    """(day, tuples, item, n, est) from distorted tuples (tid, ts, items): estimates per window.

    A window's state is one row: its number of tuples and a map from item to count would not merge in
    Spark's own aggregates, so items and the tuple itself (item -1) are counted as keys of one aggregate
    and brought together after it.
    """
    each = arrays.withWatermark("ts", late).select("ts", F.explode(F.concat(F.array(F.lit(-1)), "items")).alias("item"))
    return each.groupBy(F.window("ts", window).alias("w"), "item").agg(F.count(F.lit(1)).alias("n")).select(F.col("w.start").alias("day"), "item", "n")


def estimates_of(counts: DataFrame, params: FlipParams) -> DataFrame:
    """(day, item, n, est) from the drained output of ``window_recon``."""
    totals = counts.where("item = -1").select("day", F.col("n").alias("tuples"))
    a, scale, b = params.integers
    return counts.where("item >= 0").join(totals, "day").select("day", "item", "n", ((F.col("n") * scale - F.col("tuples") * a) / b).alias("est"))


def session_baskets(events: DataFrame, gap: str = "30 minutes", late: str = "1 hour") -> DataFrame:
    """(user_id, begin, items): event types of a session as a basket."""
    return events.withWatermark("ts", late).groupBy("user_id", F.session_window("ts", gap).alias("w")).agg(F.sort_array(F.collect_set("event_type")).alias("items")).select("user_id", F.col("w.start").alias("begin"), "items")


def without_repeats(events: DataFrame, late: str = "1 hour") -> DataFrame:
    return events.withWatermark("ts", late).dropDuplicatesWithinWatermark(["event_id"])


def with_dictionary(events: DataFrame, items: DataFrame) -> DataFrame:
    """Stream-static join: item ids for labels."""
    return events.join(F.broadcast(items), events.event_type == items.label)


def click_then_purchase(events: DataFrame, within: str = "1 hour") -> DataFrame:
    """Stream-stream join of a user's views and later purchases; the bounds on time let state go."""
    a = events.where("event_type <> 'purchase'").select(F.col("user_id").alias("u"), F.col("ts").alias("seen_at"), F.col("event_id").alias("seen")).withWatermark("seen_at", within)
    b = events.where("event_type = 'purchase'").select("user_id", F.col("ts").alias("bought_at"), F.col("event_id").alias("bought")).withWatermark("bought_at", within)
    return a.join(b, F.expr(f"u = user_id AND bought_at >= seen_at AND bought_at <= seen_at + INTERVAL {within}")).select("seen", "bought")


def running_totals(events: DataFrame) -> DataFrame:
    """(user_id, events, value) with a user's running totals after each batch, as arbitrary state."""
    import pandas as pd
    from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

    def update(key: tuple, batches: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        n, total = state.get if state.exists else (0, 0.0)
        for rows in batches:
            n, total = n + len(rows), total + float(rows["value"].sum())
        state.update((n, total))
        yield pd.DataFrame({"user_id": [key[0]], "events": [n], "value": [total]})

    return events.groupBy("user_id").applyInPandasWithState(update, "user_id long, events long, value double", "n long, total double", "update", GroupStateTimeout.NoTimeout)


class IncrementalCounts:
    """Additive counts merged batch by batch (``foreachBatch``); equal to a recount of everything seen so far.

    A batch that is delivered again after a failure is recognised by its number and not added twice.
    """

    def __init__(self, spark: SparkSession, count: Callable[[DataFrame], DataFrame]):
        self.spark, self.count, self.folder = spark, count, f"{shared_dir(spark)}/counts/{uuid.uuid4().hex}"

    def __call__(self, batch: DataFrame, number: int) -> None:
        self.count(batch).write.mode("overwrite").parquet(f"{self.folder}/batch={number}")

    def total(self, keys: list[str]) -> DataFrame:
        return self.spark.read.parquet(self.folder).groupBy(*keys).agg(F.sum("n").alias("n"))


def late_rows(query: StreamingQuery) -> int:
    """Rows (partial aggregates, as Spark counts them) that came behind the watermark in the batches whose progress is still held."""
    return sum(operator.numRowsDroppedByWatermark for progress in query.recentProgress for operator in progress.stateOperators)


def run_once(stream: DataFrame, mode: str = "append", ended: Callable[[StreamingQuery], None] | None = None) -> DataFrame:
    """Drains what the source has now into a table of the shared folder and returns that table; ``ended`` gets the query afterwards."""
    spark = stream.sparkSession
    folder = f"{shared_dir(spark)}/streams/{uuid.uuid4().hex}"
    if mode == "append":
        writer = stream.writeStream.format("parquet").option("path", f"{folder}/out")
    else:
        # a complete or updated result replaces the one before it
        def write(batch: DataFrame, number: int) -> None:
            batch.write.mode("overwrite").parquet(f"{folder}/out")

        writer = stream.writeStream.foreachBatch(write)
    query = writer.outputMode(mode).option("checkpointLocation", f"{folder}/state").trigger(availableNow=True).start()
    query.awaitTermination()
    if ended:
        ended(query)
    return spark.read.schema(stream.schema).parquet(f"{folder}/out")


def distort_table(arrays: DataFrame, n_items: int, params: FlipParams, seed: int) -> DataFrame:
    """A table streamed through ``distort_stream``: equal, row for row, to distorting it in one batch."""
    folder = f"{shared_dir(arrays.sparkSession)}/streams/{uuid.uuid4().hex}"
    arrays.write.parquet(folder)
    return run_once(distort_stream(read_folder(arrays.sparkSession, folder, arrays.schema), n_items, params, seed))
