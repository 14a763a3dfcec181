"""Supports of itemsets in the true data, estimated from counts in the distorted data."""

from __future__ import annotations

from collections.abc import Callable, Sequence
from itertools import combinations, takewhile

import numpy as np
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..config import FlipParams
from ..functions import channel

Itemset = tuple[int, ...]


def singleton_expr(n: Column, dbsize: int, params: FlipParams) -> Column:
    """Estimate of an item's count from its distorted count."""
    a, scale, b = params.integers
    return (n * scale - a * dbsize).cast("double") / F.lit(float(b))


def singletons(counts: DataFrame, dbsize: int, params: FlipParams) -> DataFrame:
    """The same by the inverse of the 2x2 matrix, from counts of 1 and of 0: adds est and est0."""
    inverse = np.linalg.inv(channel.single(params.p, params.q))
    zeros = F.lit(dbsize) - F.col("n")
    combine = lambda row: F.col("n") * float(row[0]) + zeros * float(row[1])
    return counts.withColumns({"est": combine(inverse[0]), "est0": combine(inverse[1])})


def by_pattern(pattern_counts: DataFrame, k: int, params: FlipParams) -> DataFrame:
    """(cand, est) from all 2**k pattern counts; the all-ones row of the inverse Kronecker power, pattern by pattern."""
    q, d = params.q, float(params.d)
    ones = F.bit_count("pattern")
    weight = F.pow(F.lit(q / d), ones) * F.pow(F.lit(-(1 - q) / d), F.lit(k) - ones)
    return pattern_counts.groupBy("cand").agg(F.sum(F.col("n") * weight).alias("est"))


def by_pattern_matrix(pattern_counts: DataFrame, k: int, params: FlipParams) -> DataFrame:
    """(cand, pattern, est) for every pattern, one small solve per candidate in an Arrow function."""
    import pandas as pd

    def solve(rows: pd.DataFrame) -> pd.DataFrame:
        seen = np.zeros(1 << k)
        # the matrix orders patterns from all ones down, its first axis being the highest bit
        seen[(1 << k) - 1 - rows["pattern"].to_numpy()] = rows["n"].to_numpy()
        true = channel.solve_patterns(seen, params.p, params.q)[::-1]
        return pd.DataFrame({"cand": rows["cand"].iloc[0], "pattern": np.arange(1 << k), "est": true})

    return pattern_counts.groupBy("cand").applyInPandas(solve, "cand int, pattern long, est double")


def by_weight(weight_counts: DataFrame, k: int, params: FlipParams) -> DataFrame:
    """(cand, est) from weight classes with the last row of the inverse transition matrix."""
    row = np.linalg.inv(channel.weight_matrix(k, params.p, params.q))[-1]
    weights = F.array(*(F.lit(float(x)) for x in row))
    return weight_counts.groupBy("cand").agg(F.sum(F.col("n") * F.element_at(weights, F.col("weight").cast("int") + 1)).alias("est"))


def subsets() -> Column:
    """All subsets of the column ``itemset``, the empty one first; native."""
    return F.expr("transform(sequence(0, cast(pow(2, size(itemset)) as int) - 1), code -> filter(itemset, (x, i) -> getbit(code, i) = 1))")


def by_subsets(candidates: DataFrame, counts: DataFrame, dbsize: int, params: FlipParams) -> DataFrame:
    """(itemset, k, num, est) of ``candidates`` (itemset, k): signed integer sum over the distorted counts of all subsets.

    ``counts`` (itemset, n) holds the all-ones counts of every subset; the empty set counts ``dbsize``
    tuples. Sums are exact in DECIMAL(38); ``est`` is num / b**k.
    """
    a, scale, b = params.integers
    each = candidates.select("itemset", "k", F.explode(subsets()).alias("part"))
    known = counts.select(F.col("itemset").alias("part"), "n")
    n = F.when(F.size("part") == 0, F.lit(dbsize)).otherwise(F.coalesce("n", F.lit(0))).cast("decimal(20,0)")
    # exact powers; one beyond 18 digits is an error of the array's bounds, not a wrong number
    powers = lambda base: F.array(*(F.lit(x).cast("decimal(18,0)") for x in takewhile(lambda x: abs(x) < 10**18, (base**e for e in range(64)))))
    power = lambda base, e: F.element_at(powers(base), (e + 1).cast("int"))
    term = n * power(scale, F.size("part")) * power(-a, F.col("k") - F.size("part"))
    sums = each.join(known, "part", "left").groupBy("itemset", "k").agg(F.sum(term.cast("decimal(38,0)")).cast("decimal(38,0)").alias("num"))
    return sums.withColumn("est", F.col("num").cast("double") / F.pow(F.lit(float(b)), F.col("k")))


def numerator(itemset: Itemset, counted: Callable[[Itemset], int], dbsize: int, params: FlipParams) -> int:
    """Exact numerator of one estimate from the store of earlier counts."""
    terms = channel.numerator_terms(len(itemset), params)
    return sum(terms[s] * (counted(part) if s else dbsize) for s in range(len(itemset) + 1) for part in combinations(itemset, s))


def keys_of(rows: np.ndarray) -> np.ndarray:
    """Sorted itemsets of one length as byte strings that compare in the same order."""
    rows = np.ascontiguousarray(rows.astype(">i4"))
    return rows.view(f"S{4 * rows.shape[1]}").ravel()


def numerators(level: Sequence[Itemset], tables: dict[int, tuple[np.ndarray, np.ndarray]], dbsize: int, params: FlipParams) -> np.ndarray:
    """Exact numerators of all candidates of a level at once; ``tables`` has, by length, the sorted keys and counts of all levels so far."""
    rows, k = np.array(level, np.int32), len(level[0])
    terms = channel.numerator_terms(k, params)
    a, scale, _ = params.integers
    small = dbsize * (abs(a) + scale) ** k < 1 << 62
    total = np.full(len(rows), terms[0] * dbsize, np.int64 if small else object)
    for s in range(1, k + 1):
        keys, counts = tables[s]
        for places in combinations(range(k), s):
            wanted = keys_of(rows[:, places])
            at = np.minimum(np.searchsorted(keys, wanted), len(keys) - 1)
            if not (keys[at] == wanted).all():
                raise KeyError(f"a subset of {s} items was not counted")
            total += (counts[at] if small else counts[at].astype(object)) * terms[s]
    return total


def pattern_from_subsets(candidates: DataFrame, counts: DataFrame, dbsize: int) -> DataFrame:
    """(itemset, pattern, n): counts of every pattern by inclusion and exclusion, from all-ones counts alone.

    Tuples with exactly the pattern's items: the alternating sum over the sets between the pattern and
    the whole itemset; an empty positive part counts all tuples.
    """
    each = candidates.select("itemset", "k", F.explode(F.expr("sequence(0, cast(pow(2, size(itemset)) as int) - 1)")).alias("pattern"))
    each = each.withColumn("wider", F.explode(F.expr("filter(sequence(pattern, cast(pow(2, k) as int) - 1), x -> (x & pattern) = pattern)")))
    part = F.filter("itemset", lambda _, i: F.getbit(F.col("wider"), i) == 1)
    each = each.withColumn("part", part).withColumn("sign", F.when((F.bit_count("wider") - F.bit_count("pattern")) % 2 == 0, 1).otherwise(-1))
    known = counts.select(F.col("itemset").alias("part"), "n")
    n = F.when(F.size("part") == 0, F.lit(dbsize)).otherwise(F.coalesce("n", F.lit(0)))
    return each.join(known, "part", "left").groupBy("itemset", "pattern").agg(F.sum(F.col("sign") * n).alias("n"))


def classes_from_subsets(candidates: DataFrame, counts: DataFrame, dbsize: int) -> DataFrame:
    """(itemset, weight, n) from the patterns above."""
    return pattern_from_subsets(candidates, counts, dbsize).groupBy("itemset", F.bit_count("pattern").alias("weight")).agg(F.sum("n").alias("n"))


def sanitize(estimates: DataFrame, dbsize: int, clamp: str = "none") -> DataFrame:
    """Estimates can be negative, above ``dbsize`` or above a subset's: ``range`` clips, ``monotone`` also caps by subsets."""
    if clamp not in ("none", "range", "monotone"):
        raise ValueError(f"unknown clamp {clamp}")
    if clamp == "none":
        return estimates
    clipped = estimates.withColumn("est", F.least(F.greatest("est", F.lit(0.0)), F.lit(float(dbsize))))
    if clamp == "range":
        return clipped
    each = clipped.select("itemset", F.explode(subsets()).alias("part"))
    low = each.join(clipped.select(F.col("itemset").alias("part"), F.col("est").alias("part_est")), "part").groupBy("itemset").agg(F.min("part_est").alias("low"))
    return clipped.join(low, "itemset").withColumn("est", F.least("est", "low")).drop("low")
