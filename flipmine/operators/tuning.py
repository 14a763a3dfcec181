"""Choice of the distortion parameters from formulas: error of estimates, privacy, speed."""

from __future__ import annotations

from collections.abc import Sequence

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from .privacy import basic


def count_stddev(n: float, dbsize: float, p: float, q: float) -> float:
    """Standard deviation of an item's distorted count."""
    return (n * p * (1 - p) + (dbsize - n) * q * (1 - q)) ** 0.5


def abs_error(n: float, dbsize: float, p: float, q: float) -> float:
    """Standard error of the estimated count."""
    return count_stddev(n, dbsize, p, q) / abs(p + q - 1)


def relative_error(n: float, dbsize: float, p: float, q: float) -> float:
    """Standard error over the count: what a measured support error may be held against."""
    return abs_error(n, dbsize, p, q) / n


def relative_error_index(s0: float | Column, p: float | Column, q: float | Column) -> Column:
    """The error without its factor 1 / sqrt(n): ranks settings at equal counts, and nothing else."""
    lit = lambda x: x if isinstance(x, Column) else F.lit(x)
    s0, p, q = lit(s0), lit(p), lit(q)
    return F.sqrt(p * (1 - p) + (1 / s0 - 1) * q * (1 - q)) / F.abs(p + q - 1)


def average_support(long: DataFrame, tids: DataFrame, n_items: int, fraction: float = 1.0, seed: int = 42) -> DataFrame:
    """One row (tuples, ones, s0), from all tuples or from a sample that a keyed hash of the tid takes."""
    if not 0 < fraction <= 1:
        raise ValueError("fraction must lie in (0, 1]")
    # the same tuples whatever the partitioning, and the same in any engine
    unit = F.conv(F.substring(F.md5(F.concat_ws("|", F.lit(f"sample-{seed}"), F.col("tid").cast("string"))), 1, 13), 16, 10).cast("long")
    some = tids.where(unit < int(fraction * 2**52))
    held = long.join(some, "tid", "left_semi").agg(F.count(F.lit(1)).alias("ones"))
    return some.agg(F.count(F.lit(1)).alias("tuples")).join(held, F.lit(True)).select("tuples", "ones", (F.col("ones") / (F.col("tuples") * n_items)).alias("s0"))


def grid(spark: SparkSession, s0: float, bp_min: float = 90.0, reference: tuple[float, float] = (0.9, 0.9), slack: float = 0.0) -> DataFrame:
    """(p, q, bp, error, private, accurate) over p = .1, ... .9 and q = .90, ... .99."""
    cells = spark.range(90).select(((F.floor(F.col("id") / 10) + 1) / 10).alias("p"), ((F.col("id") % 10 + 90) / 100).alias("q"))
    cells = cells.select("p", "q", basic(F.lit(s0), F.col("p"), F.col("q")).alias("bp"), F.when(F.abs(F.col("p") + F.col("q") - 1) > 1e-9, relative_error_index(s0, F.col("p"), F.col("q"))).alias("error"))
    return cells.withColumns({"private": F.col("bp") >= bp_min, "accurate": F.col("error") <= relative_error_index(s0, *reference) * (1 + slack)})


def candidates(spark: SparkSession, s0: float, bp_min: float = 90.0, reference: tuple[float, float] = (0.9, 0.9), slack: float = 0.0, min_q_exclusive: float = 0.95, max_p: float | None = None) -> DataFrame:
    """Settings private and accurate enough, with q above the bar that keeps the table sparse. A slack of 0.04 admits the published ones."""
    found = grid(spark, s0, bp_min, reference, slack).where("private AND accurate").where(F.round("q", 6) > min_q_exclusive)
    return found.where(F.col("p") <= max_p) if max_p is not None else found


def pick(settings: Sequence[tuple[float, float]], goal: str) -> tuple[float, float]:
    """By goal: accuracy asks for a high p, privacy for a low one, speed for a high q."""
    keys = {"accuracy": lambda x: (x[0], -x[1]), "privacy": lambda x: (-x[0], x[1]), "speed": lambda x: (x[1], -x[0])}
    if goal not in keys:
        raise ValueError(f"unknown goal {goal}; there are {sorted(keys)}")
    return max(settings, key=keys[goal])
