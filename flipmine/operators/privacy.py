"""Privacy of the entries of a basket table: from the channel alone, and helped by the miner's output."""

from __future__ import annotations

from collections.abc import Iterator, Sequence
from itertools import groupby
from math import fsum

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..config import FlipParams
from .counting import MOST_BROADCAST, bit_columns, together
from .distort import BLOCK_BYTES, added, unpacked

Number = float | Column
#: Words of the bit vectors that are held against itemsets at once, within ``BLOCK_BYTES`` for all items: calls are few.
WORDS = 1024


def reconstruction(s: Number, p: Number, q: Number) -> Number:
    """Probability that a true 1 is guessed right, when the guess is drawn from the posterior of the seen symbol; item support ``s``."""
    seen_one = s * p + (1 - s) * (1 - q)
    seen_none = s * (1 - p) + (1 - s) * q
    return s * p * p / seen_one + s * (1 - p) * (1 - p) / seen_none


def basic(s0: Number, p: Number, q: Number) -> Number:
    """Privacy of a 1 in percent, from the average support."""
    return 100 * (1 - reconstruction(s0, p, q))


def basic_symmetric(s0: Number, p: Number) -> Number:
    """The same with one keep-probability."""
    return 100 * (1 - s0 * (p * p / (s0 * p + (1 - s0) * (1 - p)) + (1 - p) * (1 - p) / (s0 * (1 - p) + (1 - s0) * p)))


def basic_item(s: Column, params: FlipParams) -> Column:
    return basic(s, params.p, params.q)


def basic_weighted(supports: DataFrame, params: FlipParams) -> DataFrame:
    """One row: mean privacy over all 1s, items weighted by their support ``s``. Never above the figure for the average support."""
    r = reconstruction(F.col("s"), params.p, params.q)
    return supports.where("s > 0").agg((100 * (1 - F.sum(F.col("s") * r) / F.sum("s"))).alias("privacy"))


def basic_zero(s0: Number, p: Number, q: Number) -> Number:
    """Privacy of a 0: the same with the symbols exchanged."""
    return 100 * (1 - reconstruction(1 - s0, q, p))


def basic_mix(s0: Number, p: Number, q: Number, alpha: float) -> Number:
    """``alpha`` of the privacy of 1s and the rest of that of 0s."""
    return alpha * basic(s0, p, q) + (1 - alpha) * basic_zero(s0, p, q)


def basic_empirical(true: DataFrame, seen: DataFrame, dbsize: int) -> DataFrame:
    """One row: the same from counted cells of both tables (tid, item) instead of the formula."""
    both = true.withColumn("x", F.lit(1)).join(seen.withColumn("y", F.lit(1)), ["tid", "item"], "full")
    by = both.groupBy("item").agg(F.count("x").alias("ones"), F.count("y").alias("seen"), F.count(F.when(F.col("x").isNotNull() & F.col("y").isNotNull(), 1)).alias("kept"))
    lost, unseen = F.col("ones") - F.col("kept"), F.lit(dbsize) - F.col("seen")
    part = lambda a, b: F.when(b > 0, a * a / b).otherwise(0.0)
    return by.agg((100 * (1 - F.sum(part(F.col("kept"), F.col("seen")) + part(lost, unseen)) / F.sum("ones"))).alias("privacy"))


def surface(spark, s0: float, steps: int = 10) -> DataFrame:  # noqa: ANN001
    """Privacy over a grid of p and q, without the corners where it is undefined."""
    grid = spark.range((steps + 1) ** 2).select((F.floor(F.col("id") / (steps + 1)) / steps).alias("p"), ((F.col("id") % (steps + 1)) / steps).alias("q"))
    grid = grid.where(~((F.col("p").isin(0.0, 1.0)) & (F.col("q") == 1 - F.col("p"))))
    return grid.select("p", "q", basic(F.lit(s0), F.col("p"), F.col("q")).alias("privacy"))


def spurious_probability(n: int, q: float, support: float) -> float:
    """All n items seen in a tuple that has none of them, times the share of tuples without the itemset."""
    return (1 - q) ** n * (1 - support)


def few(df: DataFrame) -> DataFrame:
    """``df`` marked for broadcast if it has at most ``MOST_BROADCAST`` rows; Spark chooses for more."""
    return F.broadcast(df) if df.limit(MOST_BROADCAST + 1).count() <= MOST_BROADCAST else df


def matches(seen: DataFrame, itemsets: DataFrame) -> DataFrame:
    """(tid, cand) where all items of a candidate (cand, itemset, k; few) are seen in the tuple."""
    return seen.join(few(itemsets.select("cand", "k", F.explode("itemset").alias("item"))), "item").groupBy("tid", "cand", "k").agg(F.count(F.lit(1)).alias("w")).where("w = k").select("tid", "cand")


def breaches(true: DataFrame, seen: DataFrame, itemsets: DataFrame) -> DataFrame:
    """(cand, item, matched, present, breach): of the tuples in which an itemset is seen, the share that truly has the item."""
    found = matches(seen, itemsets)
    items = itemsets.select("cand", F.explode("itemset").alias("item"))
    total = found.groupBy("cand").agg(F.count(F.lit(1)).alias("matched"))
    hits = found.join(few(items), "cand").join(true, ["tid", "item"], "left_semi").groupBy("cand", "item").agg(F.count(F.lit(1)).alias("present"))
    return items.join(total, "cand").join(hits, ["cand", "item"], "left").select("cand", "item", "matched", F.coalesce("present", F.lit(0)).alias("present"), (F.coalesce("present", F.lit(0)) / F.col("matched")).alias("breach"))


def reinterrogated(true: DataFrame, seen: DataFrame, itemsets: DataFrame, bp: float, match: str = "seen") -> DataFrame:
    """One row (privacy, ones, kept, flipped, rare): mean privacy of all 1s against an attacker who knows the frequent itemsets.

    A kept 1 of a frequent item is as private as the worst breach among the itemsets that hold it and
    are seen in the tuple leaves it; flipped 1s and those of infrequent items have the basic privacy
    ``bp``. ``match='true'`` takes itemsets of the original tuple instead, for comparison.
    """
    table = breaches(true, seen, itemsets).select("cand", "item", "breach")
    found = matches(seen if match == "seen" else true, itemsets)
    worst = found.join(few(table), "cand").groupBy("tid", "item").agg(F.max("breach").alias("breach"))
    kept = true.join(seen, ["tid", "item"]).join(worst, ["tid", "item"], "left")
    frequent = itemsets.where("k = 1").select(F.col("itemset")[0].alias("item"))
    own = kept.join(few(frequent.withColumn("f", F.lit(1))), "item", "left").agg(
        F.count(F.lit(1)).alias("kept"), F.count(F.when(F.col("f").isNull(), 1)).alias("rare"),
        F.coalesce(F.sum(F.when(F.col("f").isNotNull(), 100 * (1 - F.coalesce("breach", F.lit(0.0)))).otherwise(bp)), F.lit(0.0)).alias("sum"),
    )
    ones = true.agg(F.count(F.lit(1)).alias("ones"))
    both = own.join(ones, F.lit(True))  # one row each
    return both.select(((F.col("sum") + (F.col("ones") - F.col("kept")) * bp) / F.col("ones")).alias("privacy"), "ones", "kept", (F.col("ones") - F.col("kept")).alias("flipped"), "rare")


def reinterrogated_chunks(pairs: DataFrame, itemsets: list[tuple[int, ...]], n_items: int, bp: float) -> tuple[float, dict[tuple[int, ...], dict[int, float]]]:
    """The same in two passes over ``pairs`` (tid, items, seen: true and distorted lists), on columns of bits."""
    return reinterrogated_tables(pairs, ["seen"], itemsets, n_items, [bp])[0]


def reinterrogated_tables(table: DataFrame, columns: Sequence[str], itemsets: list[tuple[int, ...]], n_items: int, bps: Sequence[float]) -> list[tuple[float, dict[tuple[int, ...], dict[int, float]]]]:
    """The same for each of ``columns`` of distorted lists beside the true ``items``, in two passes over all of them.

    First the breaches: AND of an itemset's seen columns, popcounts with each true column. Then, for each
    item, kept bits are peeled off by the itemsets that hold it, worst breach first. Nothing is sent
    but counts; itemsets and their order are broadcast.
    """
    by_length = [np.array([x for x in itemsets if len(x) == k], np.int32) for k in sorted(set(map(len, itemsets)))]
    sizes = [len(x) * (1 + x.shape[1]) for x in by_length]
    context, width = table.sparkSession.sparkContext, 1 + sum(sizes)
    lists = table.select("items", *columns)
    only = np.array(sorted({i for x in itemsets for i in x}), np.int32)

    def blocks(batches: Iterator[pa.RecordBatch]) -> Iterator[tuple[int, np.ndarray, list[np.ndarray]]]:
        waiting, words, ones = [], 0, 0
        for batch in batches:
            waiting.append([bit_columns(c, n_items, only) for c in batch.columns])
            words, ones = words + waiting[-1][0].shape[1], ones + len(unpacked(batch.column(0), n_items)[1])
            if words >= min(WORDS, BLOCK_BYTES // (8 * max(len(only), 1) * len(batch.columns))):
                true, *seen = (np.concatenate(x, axis=1) for x in zip(*waiting, strict=True))
                yield ones, true, seen
                waiting, words, ones = [], 0, 0
        if waiting:
            true, *seen = (np.concatenate(x, axis=1) for x in zip(*waiting, strict=True))
            yield ones, true, seen

    def matched(batches: Iterator[pa.RecordBatch]) -> np.ndarray:
        out = np.zeros((len(columns), width), np.int64)
        for ones, true, tables in blocks(batches):
            for sums, seen in zip(out, tables, strict=True):
                sums[0] += ones
                at = 1
                for sets in shared.value:
                    step = max(1, 65_536 // max(seen.shape[1], 1))
                    n = np.empty((1 + sets.shape[1], len(sets)), np.int64)
                    for x in range(0, len(sets), step):
                        part = sets[x : x + step]
                        bits = together(seen, part)
                        n[0, x : x + step] = np.bitwise_count(bits).sum(1, dtype=np.int64)
                        for j in range(sets.shape[1]):
                            n[1 + j, x : x + step] = np.bitwise_count(bits & true[part[:, j]]).sum(1, dtype=np.int64)
                    sums[at : at + n.size] += n.ravel()
                    at += n.size
        return out.ravel()

    shared = context.broadcast([np.searchsorted(only, sets) for sets in by_length])  # called by their places in ``only``
    found = added(lists, matched, len(columns) * width).reshape(len(columns), width)
    tables, order = [], []
    for sums in found.tolist():
        breach, ranked, at = {}, {}, 1
        for sets in by_length:
            m, k = sets.shape
            for i, x in enumerate(map(tuple, sets.tolist())):
                n = sums[at + i]
                breach[x] = {b: sums[at + (1 + j) * m + i] / n if n else 0.0 for j, b in enumerate(x)}
            at += m * (1 + k)
        for x, by_item in breach.items():
            for b, share in by_item.items():
                ranked.setdefault(b, []).append((share, x))
        tables.append(breach)
        # an item's own column holds all of its kept bits: no itemset below it is ever reached
        order.append([(b, share, x) for b, sets in sorted(ranked.items()) for share, x in _reached(sorted(sets, reverse=True), b)])

    places, place = np.cumsum([0, *map(len, order)]), {int(i): at for at, i in enumerate(only)}
    ranks = context.broadcast([[_padded(place[b], [[place[i] for i in x] for _, _, x in sets]) for b, sets in groupby(one, lambda r: r[0])] for one in order])

    def peeled(batches: Iterator[pa.RecordBatch]) -> np.ndarray:
        out = np.zeros(places[-1], np.int64)
        for _, true, tables in blocks(batches):
            for seen, ranked, at in zip(tables, ranks.value, places, strict=False):
                for b, lengths, sets in ranked:
                    left, step = true[b] & seen[b], max(1, 262_144 // max(seen.shape[1], 1))
                    for x in range(0, len(sets), step):
                        if not left.any():
                            break
                        part, size = sets[x : x + step], lengths[x : x + step]
                        bits = seen[part[:, 0]]
                        bits &= left
                        for k in range(1, int(size.max())):
                            longer = np.flatnonzero(size > k)
                            bits[longer] &= seen[part[longer, k]]
                        np.bitwise_or.accumulate(bits, axis=0, out=bits)
                        out[at + x : at + x + len(part)] += np.diff(np.bitwise_count(bits).sum(1, dtype=np.int64), prepend=0)
                        left &= ~bits[-1]
                    at += len(sets)
        return out

    hits = added(lists, peeled, int(places[-1])).tolist() if places[-1] else []
    out = []
    for i, bp in enumerate(bps):
        ones, here = int(found[i, 0]), hits[places[i] : places[i + 1]]
        own = fsum(n * 100 * (1 - share) for n, (_, share, _) in zip(here, order[i], strict=True))
        out.append((((own + (ones - sum(here)) * bp) / ones if ones else float("nan")), tables[i]))
    return out


def _padded(item: int, sets: list[list[int]]) -> tuple[int, np.ndarray, np.ndarray]:
    """An item, and the lengths and items of its ranked itemsets as arrays."""
    lengths = np.array([len(x) for x in sets])
    out = np.zeros((len(sets), int(lengths.max())), np.int32)
    out[np.arange(out.shape[1]) < lengths[:, None]] = np.concatenate(sets)
    return item, lengths, out


def _reached(sets: list[tuple[float, tuple[int, ...]]], item: int) -> list[tuple[float, tuple[int, ...]]]:
    """The ranked itemsets of an item up to the item alone, if it is among them."""
    ends = [i for i, (_, x) in enumerate(sets) if x == (item,)]
    return sets[: ends[0] + 1] if ends else sets
