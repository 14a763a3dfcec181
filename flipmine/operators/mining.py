"""Level-wise mining of frequent itemsets: exact, and from distorted data under three counting strategies.

A level's candidates are broadcast, counted in one pass over the table, and come back as one number
each; they are bounded by a budget, beyond which mining stops with an error instead of a dead driver.
"""

from __future__ import annotations

from collections.abc import Callable, Generator, Iterable, Sequence
from dataclasses import dataclass, field
from fractions import Fraction

import numpy as np
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..config import CANDIDATE_BUDGET, CandidateBudgetExceeded, FlipParams, exact
from ..functions import channel
from ..sources.shared import stored
from . import counting, distort, reconstruct

Itemset = tuple[int, ...]


@dataclass
class PassStore:
    """Distorted counts of earlier passes, needed to reconstruct longer itemsets."""

    counts: dict[Itemset, int] = field(default_factory=dict)
    tables: dict[int, tuple[np.ndarray, np.ndarray]] = field(default_factory=dict)  # by length: sorted keys and counts

    def keep(self, found: dict[Itemset, int]) -> None:
        self.counts |= found
        sets = sorted(found)
        self.tables[len(sets[0])] = reconstruct.keys_of(np.array(sets, np.int32)), np.array([found[x] for x in sets], np.int64)
        if len(self.counts) > 4 * CANDIDATE_BUDGET:
            raise CandidateBudgetExceeded(f"{len(self.counts)} counts in the store of earlier passes")


@dataclass
class Mined:
    """Estimated counts of frequent itemsets, and the work that each level took."""

    dbsize: int
    support: dict[Itemset, Fraction] = field(default_factory=dict)
    counts: dict[Itemset, int] = field(default_factory=dict)
    candidates: dict[int, int] = field(default_factory=dict)
    counters: int = 0

    def frame(self, spark: SparkSession) -> DataFrame:
        """(itemset, k, est, support)."""
        rows = [(list(x), len(x), float(s), float(s / self.dbsize)) for x, s in self.support.items()]
        return spark.createDataFrame(rows, "itemset array<int>, k int, est double, support double")


def frames(spark: SparkSession, runs: Sequence[Mined]) -> DataFrame:
    """(run, itemset, k, est) of several results."""
    rows = [(i, list(x), len(x), float(s)) for i, m in enumerate(runs) for x, s in m.support.items()]
    return spark.createDataFrame(rows, "run int, itemset array<int>, k int, est double")


def candidates(frequent: Iterable[Itemset], budget: int = CANDIDATE_BUDGET) -> list[Itemset]:
    """Joins of itemsets that share all but their last item, less those with an infrequent subset."""
    known = set(frequent)
    by_prefix: dict[Itemset, list[int]] = {}
    for x in sorted(known):
        by_prefix.setdefault(x[:-1], []).append(x[-1])
    out = []
    for prefix, last in by_prefix.items():
        for i, a in enumerate(last):
            for b in last[i + 1 :]:
                new = (*prefix, a, b)
                if all(new[:j] + new[j + 1 :] in known for j in range(len(new) - 2)):
                    out.append(new)
        if len(out) > budget:
            raise CandidateBudgetExceeded(f"more than {budget} candidates of {len(out[0])} items")
    return out


def candidates_frame(frequent: DataFrame) -> DataFrame:
    """The same as a plan over ``frequent`` (itemset): prefix join, then a subset check by counting hits."""
    f = frequent.select("itemset", F.expr("slice(itemset, 1, size(itemset) - 1)").alias("prefix"), F.expr("element_at(itemset, -1)").alias("last"))
    other = f.select(F.col("prefix"), F.col("last").alias("next"))
    joined = f.join(other, "prefix").where("last < next").select(F.expr("concat(itemset, array(next))").alias("itemset"))
    parts = joined.select("itemset", F.expr("explode(transform(sequence(1, size(itemset)), j -> filter(itemset, (x, i) -> i + 1 <> j)))").alias("part"))
    hits = parts.join(frequent.select(F.col("itemset").alias("part")), "part", "left_semi").groupBy("itemset").agg(F.count(F.lit(1)).alias("n"))
    return hits.where("n = size(itemset)").select("itemset")


def _steps(items: Iterable[int], least: Callable[[int, Itemset], Fraction], max_len: int, result: Mined, generate_from: Callable[[int, list[Itemset]], list[Itemset]] | None = None) -> Generator[list[Itemset], dict[Itemset, Fraction]]:
    """Asks for the estimates of one level after the other; one that is left out is below the bar."""
    level: list[Itemset] = [(i,) for i in sorted(items)]
    for k in range(1, max_len + 1):
        if not level:
            break
        result.candidates[k] = len(level)
        estimates = yield level
        kept = [x for x in level if x in estimates and estimates[x] >= least(k, x)]
        result.support |= {x: estimates[x] for x in level if x in estimates and estimates[x] >= least(k, ())}
        level = candidates(generate_from(k, kept) if generate_from else kept) if k < max_len else []


def _levels(items: Iterable[int], count: Callable[[list[Itemset]], dict[Itemset, Fraction]], least: Callable[[int, Itemset], Fraction], max_len: int, result: Mined, generate_from: Callable[[int, list[Itemset]], list[Itemset]] | None = None) -> Mined:
    steps = _steps(items, least, max_len, result, generate_from)
    level = next(steps, None)
    while level:
        try:
            level = steps.send(count(level))
        except StopIteration:
            break
    return result


def _checked(min_support: float | str, max_len: int) -> Fraction:
    share = exact(min_support)
    if share <= 0:
        raise ValueError("min_support must be positive")
    if max_len < 1:
        raise ValueError("max_len must be 1 or more")
    return share


def mine_exact(arrays: DataFrame, n_items: int, dbsize: int, min_support: float | str, max_len: int = 64, physical: str = "chunks", strict: bool = False) -> Mined:
    """Frequent itemsets of the undistorted data; ``strict`` asks for more than, not at least, the share."""
    least = _checked(min_support, max_len) * dbsize
    if strict:
        least = Fraction(least.__floor__() + 1)
    result = Mined(dbsize)

    def count(level: list[Itemset]) -> dict[Itemset, Fraction]:
        result.counters += len(level)
        found = counting.count(arrays, level, n_items, physical)
        result.counts |= found
        return {x: Fraction(n) for x, n in found.items()}

    return _levels(range(n_items), count, lambda k, x: least, max_len, result)


def mine_distorted(
    arrays: DataFrame, n_items: int, dbsize: int, params: FlipParams, min_support: float | str, max_len: int = 64, physical: str = "chunks", strict: bool = False, slack: float = 0.0, true_frequent: set[Itemset] | None = None,
    singletons: np.ndarray | None = None, narrowed: Callable[[list[int]], DataFrame] | None = None,
) -> Mined:
    """Only all-ones counts are taken; estimates follow at the end of each pass from the counts of all subsets.

    ``slack`` lowers the bar by so many standard errors where candidates are generated, not in the result.
    With ``true_frequent`` each level is generated from the truly frequent itemsets instead: an ablation that
    shows what errors cost when they pass from level to level. ``singletons`` are the items' distorted counts where they
    are known already; ``narrowed`` then gives the distorted lists of the items that longer candidates hold, called by their places.
    """
    least = _checked(min_support, max_len) * dbsize
    if strict:
        least = Fraction(least.__floor__() + 1)
    store, result = PassStore(), Mined(dbsize)
    b, part = params.integers[2], []

    def counted(level: list[Itemset]) -> dict[Itemset, int]:
        if singletons is not None and len(level[0]) == 1:
            return {x: int(singletons[x[0]]) for x in level}
        if narrowed is None:
            return counting.count(arrays, level, n_items, physical)
        if not part:
            items = sorted({i for x in level for i in x})
            part.extend((narrowed(items), {item: i for i, item in enumerate(items)}))
        lists, at = part
        places = {tuple(at[i] for i in x): x for x in level}
        return {places[x]: n for x, n in counting.count(lists, list(places), len(at), physical).items()}

    def count(level: list[Itemset]) -> dict[Itemset, Fraction]:
        result.counters += len(level)
        store.keep(counted(level))
        nums = reconstruct.numerators(level, store.tables, dbsize, params).tolist()
        return {x: Fraction(n, b ** len(x)) for x, n in zip(level, nums, strict=True)}

    def bar(k: int, x: Itemset) -> Fraction:
        if not slack or not x:
            return least
        classes = [0.0] * k + [float(least)]
        classes[0] = dbsize - float(least)
        return least - exact(round(slack * max(channel.variance(classes, params.p, params.q), 0.0) ** 0.5, 6))

    source = None if true_frequent is None else lambda k, _: [x for x in true_frequent if len(x) == k]
    _levels(range(n_items), count, bar, max_len, result, source)
    result.counts = store.counts
    return result


def mine_at_source(arrays: DataFrame, n_items: int, dbsize: int, params: FlipParams, seed: int, min_support: float | str, max_len: int) -> Mined:
    """``mine_distorted`` from the true lists and the seed, for universes whose distorted lists are too long to keep.

    Items are counted as they are distorted; lists are kept only of the items of longer candidates, whose coins are tossed again.
    """
    (singletons,) = distort.flip_counts(arrays, n_items, [params], seed)
    narrowed = lambda items: stored(distort.flip_arrays(arrays, n_items, params, seed, items), "narrowed")
    return mine_distorted(arrays, n_items, dbsize, params, min_support, max_len, singletons=singletons, narrowed=narrowed)


def mine_together(counted: Callable[[list[list[Itemset]]], list[np.ndarray]], n_items: int, dbsize: int, settings: Sequence[FlipParams | None], min_support: float | str, max_len: int) -> list[Mined]:
    """``mine_exact`` (where a setting is None) and ``mine_distorted`` of several tables, a level of all of them in one call of ``counted``."""
    least = _checked(min_support, max_len) * dbsize
    results, stores = [Mined(dbsize) for _ in settings], [PassStore() for _ in settings]
    steps = [_steps(range(n_items), lambda k, x: least, max_len, r) for r in results]
    levels = [next(s, []) for s in steps]
    while any(levels):
        for i, (level, n) in enumerate(zip(levels, counted(levels), strict=True)):
            if not level:
                continue
            found, params = dict(zip(level, n.tolist(), strict=True)), settings[i]
            results[i].counters += len(level)
            if params is None:
                results[i].counts |= found
                nums, below = n.astype(object), 1
            else:
                stores[i].keep(found)
                results[i].counts = stores[i].counts
                nums, below = reconstruct.numerators(level, stores[i].tables, dbsize, params).astype(object), params.integers[2] ** len(level[0])
            over = np.flatnonzero(nums * least.denominator >= least.numerator * below)
            estimates = {level[j]: Fraction(nums[j], below) for j in over.tolist()}
            try:
                levels[i] = steps[i].send(estimates)
            except StopIteration:
                levels[i] = []
    return results


def mine_symmetric(arrays: DataFrame, n_items: int, dbsize: int, p: float, min_support: float | str, max_len: int = 64) -> Mined:
    """The symmetric scheme: weight classes of every tuple for every candidate, and the inverse transition matrix."""
    return mine_classes(arrays, n_items, dbsize, FlipParams(p, p, allow_negative=True), min_support, max_len, "weight")


def mine_full_pattern(arrays: DataFrame, n_items: int, dbsize: int, params: FlipParams, min_support: float | str, max_len: int = 64) -> Mined:
    """The plain way: a counter for each of the 2**k patterns of a candidate."""
    return mine_classes(arrays, n_items, dbsize, params, min_support, max_len, "pattern")


def mine_classes(arrays: DataFrame, n_items: int, dbsize: int, params: FlipParams, min_support: float | str, max_len: int, strategy: str) -> Mined:
    """Counters for the ``weight`` classes or the ``pattern``s of every candidate, and estimates from the inverse's last row."""
    least, result = _checked(min_support, max_len) * dbsize, Mined(dbsize)
    a, scale, b = params.integers

    def count(level: list[Itemset]) -> dict[Itemset, Fraction]:
        k = len(level[0])
        result.counters += len(level) * counting.counters(k, strategy)
        if strategy == "weight":
            rows = counting.weights_by_chunks(arrays, level, n_items).select("cand", "weight", "n")
        else:
            rows = counting.patterns_by_chunks(arrays, level, n_items).select("cand", F.bit_count("pattern").alias("weight"), "n")
        sums = dict.fromkeys(level, 0)
        for cand, weight, n in rows.collect():
            # the closed form of the inverse's last row, over b ** k: q = (Q - a) / Q, d = b / Q
            sums[level[cand]] += n * (scale - a) ** weight * (-a) ** (k - weight)
        return {x: Fraction(s, b**k) for x, s in sums.items()}

    return _levels(range(n_items), count, lambda k, x: least, max_len, result)


def fpgrowth(arrays: DataFrame, min_support: float) -> DataFrame:
    """(itemset, n) by Spark's own miner: an independent check of the exact one."""
    from pyspark.ml.fpm import FPGrowth

    found = FPGrowth(itemsCol="items", minSupport=min_support).fit(arrays.where(F.size("items") >= 0)).freqItemsets
    return found.select(F.array_sort("items").alias("itemset"), F.col("freq").alias("n"))


def maximal(frequent: DataFrame) -> DataFrame:
    """Itemsets without a frequent superset of one more item (and so without any)."""
    parts = frequent.where("k > 1").select(F.expr("explode(transform(sequence(1, size(itemset)), j -> filter(itemset, (x, i) -> i + 1 <> j)))").alias("itemset")).distinct()
    return frequent.join(parts, "itemset", "left_anti")


def closed(frequent: DataFrame) -> DataFrame:
    """Itemsets of which no superset of one more item has the same count (n)."""
    parts = frequent.where("k > 1").select(F.expr("explode(transform(sequence(1, size(itemset)), j -> filter(itemset, (x, i) -> i + 1 <> j)))").alias("itemset"), "n").distinct()
    return frequent.join(parts, ["itemset", "n"], "left_anti")


def top_k(frequent: DataFrame, k: int, column: str = "est") -> DataFrame:
    return frequent.orderBy(F.desc(column), "itemset").limit(k)
