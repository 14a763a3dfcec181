"""Tables in the folder that driver and executors share; they cut lineage and survive lost executors."""

from __future__ import annotations

import tempfile
import uuid

from pyspark.sql import DataFrame, SparkSession


def shared_dir(spark: SparkSession) -> str:
    """``spark.checkpoint.dir`` of the session. Where it is unset, a local master gets a temporary folder; any other is an error."""
    found = spark.conf.get("spark.checkpoint.dir", None) or spark.sparkContext.getCheckpointDir()
    if found:
        return found
    if not spark.sparkContext.master.startswith("local["):
        raise ValueError("set spark.checkpoint.dir to a folder that all executors share")
    made = "file://" + tempfile.mkdtemp(prefix="flipmine-")
    spark.sparkContext.setCheckpointDir(made)
    return made


def stored(df: DataFrame, name: str) -> DataFrame:
    """``df`` written as a table in the shared folder and read again."""
    path = f"{shared_dir(df.sparkSession)}/tables/{name}-{uuid.uuid4().hex}"
    df.write.parquet(path)
    return df.sparkSession.read.schema(df.schema).parquet(path)


def spread(df: DataFrame) -> DataFrame:
    """``df`` dealt evenly to more tasks than there are cores, where rows are short and the work on each is long: by bytes alone they would meet in one task."""
    return df.repartition(tasks(df.sparkSession))


def tasks(spark: SparkSession) -> int:
    return 8 * spark.sparkContext.defaultParallelism


def discard(spark: SparkSession) -> None:
    """Deletes the tables, archives and streams that the library left in the shared folder; frames that read them end with this."""
    root = shared_dir(spark)
    for name in ("tables", "streams", "counts", "warc"):
        path = spark._jvm.org.apache.hadoop.fs.Path(f"{root}/{name}")
        path.getFileSystem(spark._jsc.hadoopConfiguration()).delete(path, True)
