"""Synthetic baskets with planted patterns: as a plan over ``spark.range`` and as a Python data source."""

from __future__ import annotations

from collections.abc import Iterator

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition

from .baskets import Baskets


def _draw(*parts: object, modulus: int) -> Column:
    return F.pmod(F.xxhash64(*(p if isinstance(p, Column) else F.lit(p) for p in parts)), F.lit(modulus))


def pattern_baskets(spark: SparkSession, tuples: int | DataFrame, n_items: int = 1000, length: float = 10, pattern: float = 4, patterns: int = 2000, seed: int = 7) -> Baskets:
    """Baskets of mean length about ``length`` that hold planted patterns of mean length about ``pattern``.

    A tuple takes a number of patterns, popular ones more often, and of each pattern all items but for
    a share that is left out; the rest of the basket is noise. All draws are hashes of the tuple's id, so
    a task that runs again makes the same tuples, and tuples are made where they are needed: no shuffle. ``tuples`` is their number, or a frame of their tids.
    """
    per, most = max(1.0, length / pattern), 2 * round(pattern) - 1
    unit = lambda *parts: _draw(*parts, modulus=1 << 30) / float(1 << 30)
    tid = F.col("tid")
    chosen = F.transform(F.sequence(F.lit(1), F.floor(unit("number", seed, tid) * (2 * per - 1)).cast("int") + 1), lambda j: F.floor(F.pow(unit("which", seed, tid, j), F.lit(3.0)) * patterns))
    size = lambda w: 1 + _draw("size", seed, w, modulus=most)
    member = lambda w: F.transform(F.sequence(F.lit(1), size(w).cast("int")), lambda i: F.struct(F.floor(F.pow(unit("item", seed, w, i), F.lit(1.5)) * n_items).cast("int").alias("item"), unit("left", seed, tid, w, i).alias("u")))
    planted = F.transform(F.filter(F.flatten(F.transform(chosen, member)), lambda x: x["u"] < 0.85), lambda x: x["item"])
    noise = F.transform(F.sequence(F.lit(1), F.lit(max(1, round(length / 4)))), lambda i: _draw("noise", seed, tid, i, modulus=n_items).cast("int"))
    tids = spark.range(tuples).select(F.col("id").alias("tid")) if isinstance(tuples, int) else tuples
    lists = tids.select("tid", F.array_sort(F.array_distinct(F.concat(planted, noise))).alias("items"))
    long = lists.select("tid", F.explode("items").alias("item"))
    items = spark.range(n_items).select(F.col("id").cast("int").alias("item"), F.lpad(F.col("id").cast("string"), 6, "0").alias("label"))
    return Baskets(long, tids, items, n_items, lists=lists)


class PatternSource(DataSource):
    """``spark.read.format("pattern_baskets").option("tuples", n)``: (tid, items) rows, made in parallel slices."""

    @classmethod
    def name(cls) -> str:
        return "pattern_baskets"

    def schema(self) -> str:
        return "tid long, items array<int>"

    def reader(self, schema) -> DataSourceReader:  # noqa: ANN001
        return _PatternReader(int(self.options.get("tuples", "1000")), int(self.options.get("items", "1000")), int(self.options.get("seed", "7")), int(self.options.get("slices", "8")))


class _Slice(InputPartition):
    def __init__(self, begin: int, end: int):
        self.begin, self.end = begin, end


class _PatternReader(DataSourceReader):
    def __init__(self, tuples: int, items: int, seed: int, slices: int):
        self.tuples, self.items, self.seed, self.slices = tuples, items, seed, slices

    def partitions(self) -> list[_Slice]:
        cuts = [self.tuples * i // self.slices for i in range(self.slices + 1)]
        return [_Slice(a, b) for a, b in zip(cuts, cuts[1:], strict=False)]

    def read(self, partition: _Slice) -> Iterator[tuple[int, list[int]]]:
        import numpy as np

        for tid in range(partition.begin, partition.end):
            rng = np.random.default_rng([self.seed, tid])
            found: set[int] = set()
            for which in (rng.random(rng.integers(1, 5)) ** 3 * 2000).astype(int):
                own = np.random.default_rng([self.seed, 1 << 40, which])
                members = (own.random(own.integers(1, 8)) ** 1.5 * self.items).astype(int)
                found.update(members[rng.random(len(members)) < 0.85].tolist())
            found.update(rng.integers(0, self.items, 2).tolist())
            yield tid, sorted(found)
