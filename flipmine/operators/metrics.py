"""Errors of mined itemsets against the truth, and costs of the ways to mine them."""

from __future__ import annotations

from collections.abc import Callable, Sequence
from statistics import median
from time import perf_counter

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F


def by_level(found: DataFrame, true: DataFrame, *runs: str) -> DataFrame:
    """(k, n_true, n_found, hits, sigma_plus, sigma_minus, rho) from ``found`` and ``true`` (itemset, k, est), each run by itself if columns tell ``runs``.

    Percent of the true itemsets that are found in excess or missed, and the mean error of support of those
    in both. rho is null at a level without hits, all are null where nothing is truly frequent.
    """
    f = found.select(*runs, F.col("itemset"), F.col("k").alias("fk"), F.col("est").alias("f"))
    t = true.select(*runs, F.col("itemset"), F.col("k").alias("tk"), F.col("est").alias("t"))
    both = f.join(t, [*runs, "itemset"], "full").select(*runs, F.coalesce("fk", "tk").alias("k"), "f", "t")
    sums = both.groupBy(*runs, "k").agg(
        F.count("t").alias("n_true"), F.count("f").alias("n_found"), F.count(F.when(F.col("f").isNotNull() & F.col("t").isNotNull(), 1)).alias("hits"),
        (100 * F.avg(F.abs(F.col("f") - F.col("t")) / F.col("t"))).alias("rho"),
    )
    share = lambda n: F.when(F.col("n_true") > 0, 100 * n / F.col("n_true"))
    return sums.select(*runs, "k", "n_true", "n_found", "hits", share(F.col("n_found") - F.col("hits")).alias("sigma_plus"), share(F.col("n_true") - F.col("hits")).alias("sigma_minus"), "rho")


def support_error(found: DataFrame, true: DataFrame) -> DataFrame:
    both = found.select("itemset", F.col("est").alias("f")).join(true.select("itemset", F.col("est").alias("t")), "itemset")
    return both.agg((100 * F.avg(F.abs(F.col("f") - F.col("t")) / F.col("t"))).alias("rho"))


def identity_error(found: DataFrame, true: DataFrame) -> DataFrame:
    """One row (sigma_plus, sigma_minus) over all levels; null where nothing is truly frequent."""
    total = true.agg(F.count(F.lit(1)).alias("n"))
    extra = found.join(true.select("itemset"), "itemset", "left_anti").agg(F.count(F.lit(1)).alias("extra"))
    missed = true.join(found.select("itemset"), "itemset", "left_anti").agg(F.count(F.lit(1)).alias("missed"))
    row = total.join(extra, F.lit(True)).join(missed, F.lit(True))
    return row.select(F.when(F.col("n") > 0, 100 * F.col("extra") / F.col("n")).alias("sigma_plus"), F.when(F.col("n") > 0, 100 * F.col("missed") / F.col("n")).alias("sigma_minus"))


def rollup(levels: DataFrame, weight: str = "true", *runs: str) -> DataFrame:
    """One row, or one for each of ``runs``: means over levels and population variances across them, weighted by the number of true itemsets.

    ``weight``: ``true``, ``hits`` or ``none``. A level without hits counts with rho 0, as in the published tables.
    """
    if weight not in ("true", "hits", "none"):
        raise ValueError(f"unknown weight {weight}")
    w: Column = {"true": F.col("n_true"), "hits": F.col("hits") if "hits" in levels.columns else F.lit(1), "none": F.lit(1)}[weight].cast("double")
    rows = levels.where("n_true > 0").select(*runs, w.alias("w"), "sigma_plus", "sigma_minus", F.coalesce("rho", F.lit(0.0)).alias("rho"))
    out = []
    for name in ("sigma_plus", "sigma_minus", "rho"):
        mean, square = F.sum(F.col("w") * F.col(name)) / F.sum("w"), F.sum(F.col("w") * F.col(name) * F.col(name)) / F.sum("w")
        out += [mean.alias(name), (square - mean * mean).alias(f"var_{name}")]
    return rows.groupBy(*runs).agg(*out)


def density_ratio(seen: DataFrame, true: DataFrame) -> DataFrame:
    """One row: how many times more items a tuple has after distortion."""
    return seen.agg(F.count(F.lit(1)).alias("after")).join(true.agg(F.count(F.lit(1)).alias("before")), F.lit(True)).select("before", "after", (F.col("after") / F.col("before")).alias("ratio"))


def slowdown(distorted: Callable[[], object], exact: Callable[[], object], repeats: int = 3) -> float:
    """Median run time on distorted data over that on the original; the two alternate, after one run of each."""
    times: tuple[list[float], list[float]] = ([], [])
    for i in range(repeats + 1):
        for k, run in enumerate((distorted, exact)):
            begin = perf_counter()
            run()
            if i:
                times[k].append(perf_counter() - begin)
    return median(times[0]) / median(times[1])


def counter_cost(levels: Sequence[tuple[int, int]], strategy: str) -> int:
    """Counters of all candidates, from (k, number of candidates)."""
    from .counting import counters

    return sum(n * counters(k, strategy) for k, n in levels)


def work(candidates: dict[int, int], counted: int, dbsize: int, strategy: str) -> tuple[int, int, int]:
    """(candidates, counters, updates): what a miner's counting comes to, whatever the machine.

    ``counted`` is the sum of the candidates' all-ones counts. Who counts all ones only touches a counter where
    a tuple holds the whole candidate; with classes or patterns every tuple touches one for every candidate.
    """
    total = sum(candidates.values())
    return total, counter_cost(list(candidates.items()), strategy), counted if strategy == "ones" else total * dbsize


def privacy_row(bp: float, rp: float) -> dict[str, float]:
    """Both privacies of a setting in percent, and what the miner's output takes off the first."""
    return {"bp": bp, "rp": rp, "lost": bp - rp}


def rule_identity(found: DataFrame, true: DataFrame) -> DataFrame:
    """One row (precision, recall) of rules by antecedent and consequent."""
    keys = ["antecedent", "consequent"]
    hits = found.join(true.select(*keys), keys, "left_semi").agg(F.count(F.lit(1)).alias("hits"))
    row = hits.join(found.agg(F.count(F.lit(1)).alias("f")), F.lit(True)).join(true.agg(F.count(F.lit(1)).alias("t")), F.lit(True))
    return row.select((F.col("hits") / F.nullif("f", F.lit(0))).alias("precision"), (F.col("hits") / F.nullif("t", F.lit(0))).alias("recall"))
