"""Scans of the given tables, item-list files, and sinks."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from ..config import FlipParams


def load(spark: SparkSession, sf_dir: str, table: str, *columns: str) -> DataFrame:
    """A table of ``sf_dir``, only the columns asked for; missing ones are an error before any job."""
    df = spark.read.parquet(f"{sf_dir}/{table}.parquet")
    if missing := set(columns) - set(df.columns):
        raise ValueError(f"{table} lacks {sorted(missing)}")
    return df.select(*columns) if columns else df


def read_item_lists(spark: SparkSession, path: str, fmt: str = "text") -> DataFrame:
    """(tid, items) from files of item lists.

    ``text``: a tuple's ordered items on each line, blank-separated; its tid is a digest of file, line and, where a file
    repeats a line, which time it is, so that another split of the files gives the same tids; ``csv``: tid, then blank-separated items; ``json``, ``orc`` and ``parquet``: columns tid and items.
    """
    items = lambda c: F.transform(F.filter(F.split(c, r"\s+"), lambda x: x != ""), lambda x: x.cast("int"))
    if fmt == "text":
        lines = spark.read.text(path).groupBy(F.input_file_name().alias("file"), "value").agg(F.count(F.lit(1)).alias("n"))
        lines = lines.select("file", "value", F.explode(F.sequence(F.lit(1).cast("long"), "n")).alias("time"))
        return lines.select(F.xxhash64(F.regexp_extract("file", "[^/]*$", 0), "value", "time").alias("tid"), items("value").alias("items"))
    if fmt == "csv":
        return spark.read.schema("tid long, list string").csv(path).select("tid", items("list").alias("items"))
    if fmt in ("json", "orc", "parquet"):
        return spark.read.schema("tid long, items array<int>").format(fmt).load(path)
    raise ValueError(f"unknown format {fmt}")


def write_item_lists(baskets: DataFrame, path: str, fmt: str = "text") -> None:
    """The counterpart of ``read_item_lists``; text keeps no tids."""
    words = F.concat_ws(" ", F.transform("items", lambda x: x.cast("string")))
    if fmt == "text":
        baskets.select(words.alias("value")).write.text(path)
    elif fmt == "csv":
        baskets.select("tid", words.alias("list")).write.csv(path)
    elif fmt in ("json", "orc", "parquet"):
        baskets.select("tid", "items").write.format(fmt).save(path)
    else:
        raise ValueError(f"unknown format {fmt}")


def write_bits(bits: DataFrame, path: str, params: FlipParams, n_items: int, dbsize: int, tuples_per_part: int = 1 << 20) -> None:
    """Bit-vector rows partitioned by range of tid, with the channel (never the coin's seed) beside them."""
    part = F.floor(F.col("tid") / tuples_per_part)
    bits.withColumn("part", part).write.partitionBy("part").parquet(f"{path}/bits")
    bits.sparkSession.createDataFrame([(params.p, params.q, n_items, dbsize)], "p double, q double, n_items int, dbsize long").coalesce(1).write.parquet(f"{path}/channel")


def read_bits(spark: SparkSession, path: str) -> tuple[DataFrame, FlipParams, int, int]:
    row = spark.read.parquet(f"{path}/channel").first()
    return spark.read.parquet(f"{path}/bits").drop("part"), FlipParams(row.p, row.q, row.p + row.q < 1), row.n_items, row.dbsize


def write_columns(columns: DataFrame, path: str) -> None:
    """Vertical bitmaps, clustered by chunk so that a chunk's columns are read together."""
    columns.repartition("chunk").sortWithinPartitions("chunk", "item").write.parquet(path)


def write_result(df: DataFrame, path: str, run: str) -> None:
    """Results of a run; writing the same run again replaces it and no other."""
    df.withColumn("run", F.lit(run)).write.mode("overwrite").option("partitionOverwriteMode", "dynamic").partitionBy("run").parquet(path)


def itemset_text(c: Column | str = "itemset") -> Column:
    return F.concat_ws(",", F.transform(c, lambda x: x.cast("string")))
