"""Counting strategies: every pattern, weight classes, or all ones only; and physical ways to count all ones."""

from __future__ import annotations

from collections.abc import Iterator, Sequence

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..config import CANDIDATE_BUDGET, CandidateBudgetExceeded
from .distort import BLOCK_BYTES, _dense, added, unpacked

Itemset = tuple[int, ...]
#: Tuples of a chunk in the vertical bitmap form of Spark's own functions.
CHUNK = 32_768
#: Rows of candidates and their items that are broadcast without asking; Spark chooses beyond.
MOST_BROADCAST = 500_000


def frame(spark: SparkSession, itemsets: Sequence[Itemset]) -> DataFrame:
    """(cand, itemset, k) of a list of candidates of bounded length."""
    if len(itemsets) > CANDIDATE_BUDGET:
        raise CandidateBudgetExceeded(f"{len(itemsets)} candidates; at most {CANDIDATE_BUDGET}")
    return spark.createDataFrame([(i, list(x), len(x)) for i, x in enumerate(itemsets)], "cand int, itemset array<int>, k int")


def exploded(spark: SparkSession, itemsets: Sequence[Itemset], *columns: str, places: bool = False) -> DataFrame:
    """(cand, item, and ``columns``): the items of candidates, with their ``at`` if asked for; broadcast if there are few."""
    items = F.posexplode("itemset").alias("at", "item") if places else F.explode("itemset").alias("item")
    each = frame(spark, itemsets).select("cand", *columns, items)
    return F.broadcast(each) if sum(map(len, itemsets)) <= MOST_BROADCAST else each


def singletons(long: DataFrame) -> DataFrame:
    """(item, n); partial counts before the shuffle."""
    return long.groupBy("item").agg(F.count(F.lit(1)).alias("n"))


def column_bits(long: DataFrame) -> DataFrame:
    """(chunk, item, bits): vertical bitmaps of CHUNK tuples; an item in all tuples costs no more than a rare one."""
    at = F.col("tid") + 1  # the first bucket would hold tid 0 alone
    return long.groupBy(F.bitmap_bucket_number(at).alias("chunk"), "item").agg(F.bitmap_construct_agg(F.bitmap_bit_position(at)).alias("bits"))


def count_relational(long: DataFrame, itemsets: Sequence[Itemset]) -> DataFrame:
    """(cand, n) by joining items of tuples with items of candidates; the plain way, and the oracle's."""
    met = long.join(exploded(long.sparkSession, itemsets, "k"), "item").groupBy("tid", "cand", "k").agg(F.count(F.lit(1)).alias("w")).where("w = k")
    return met.groupBy("cand").agg(F.count(F.lit(1)).alias("n"))


def count_bitmaps(columns: DataFrame, itemsets: Sequence[Itemset]) -> DataFrame:
    """(cand, n) from vertical bitmaps, all in Spark's own functions; for small candidate sets."""
    both = columns.join(exploded(columns.sparkSession, itemsets, "k"), "item").groupBy("chunk", "cand", "k").agg(F.bitmap_and_agg("bits").alias("bits"), F.count(F.lit(1)).alias("w"))
    return both.where("w = k").groupBy("cand").agg(F.sum(F.bitmap_count("bits")).alias("n"))


def _partials(arrays: DataFrame, shared, n_items: int, of) -> DataFrame:  # noqa: ANN001
    """Counts that ``of`` (dense block, candidates) gives, added up within a task before they are shuffled."""

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        total, step = None, max(1, BLOCK_BYTES // max(n_items, 1))
        for batch in batches:
            for at in range(0, batch.num_rows, step):
                n = of(_dense(batch.column(0).slice(at, step), n_items), shared.value)
                total = n if total is None else total + n
        if total is not None:
            flat = total.ravel()
            at = np.flatnonzero(flat)
            yield pa.RecordBatch.from_arrays([pa.array(at, pa.int64()), pa.array(flat[at], pa.int64())], ["at", "n"])

    return arrays.select("items").mapInArrow(work, "at long, n long").groupBy("at").agg(F.sum("n").alias("n"))


def count_chunks(arrays: DataFrame, itemsets: Sequence[Itemset], n_items: int) -> DataFrame:
    """(cand, n) by bit vectors of the columns of each batch: AND and popcount for all candidates.

    The default at scale. The table is read once per level and never shuffled; candidates are
    broadcast, within a budget; a task sends one number per candidate that it met.
    """
    frame(arrays.sparkSession, itemsets[:0])
    if len(itemsets) > CANDIDATE_BUDGET:
        raise CandidateBudgetExceeded(f"{len(itemsets)} candidates; at most {CANDIDATE_BUDGET}")
    if itemsets and len(itemsets[0]) == 1:
        return _count_singles(arrays, itemsets, n_items)
    shared = arrays.sparkSession.sparkContext.broadcast(np.array(itemsets, np.int32).reshape(len(itemsets), -1))

    def of(block: np.ndarray, candidates: np.ndarray) -> np.ndarray:
        columns = np.packbits(np.ascontiguousarray(block.T), axis=1)
        pad = -columns.shape[1] % 8
        columns = np.ascontiguousarray(np.pad(columns, ((0, 0), (0, pad)))).view(np.uint64)
        out = np.zeros(len(candidates), np.int64)
        step = max(1, 4_000_000 // max(columns.shape[1], 1))
        for at in range(0, len(candidates), step):
            part = candidates[at : at + step]
            bits = columns[part[:, 0]]
            for k in range(1, part.shape[1]):
                bits = bits & columns[part[:, k]]
            out[at : at + step] = np.bitwise_count(bits).sum(1)
        return out

    return _partials(arrays, shared, n_items, of).select(F.col("at").cast("int").alias("cand"), "n")


def _count_singles(arrays: DataFrame, itemsets: Sequence[Itemset], n_items: int) -> DataFrame:
    """(cand, n) of single items from the lists as they are: no dense block of tuples and items is made for them."""
    spark, items = arrays.sparkSession, np.array(itemsets, np.int32)[:, 0]

    def totals(batches: Iterator[pa.RecordBatch]) -> np.ndarray:
        return sum((np.bincount(batch.column(0).flatten().to_numpy(zero_copy_only=False), minlength=n_items) for batch in batches), np.zeros(n_items, np.int64))

    n = added(arrays.select("items"), totals, n_items)[items]
    return spark.createDataFrame(pa.table({"cand": pa.array(np.arange(len(items)), pa.int32()), "n": pa.array(n, pa.int64())}))


def bit_columns(lists: pa.ListArray | pa.BinaryArray, n_items: int, only: np.ndarray | None = None) -> np.ndarray:
    """(items, words): a bit vector of the tuples for each item, or for each of the ascending ``only``, cut to dense blocks on the way."""
    wide = n_items if only is None else len(only)
    step = min(8192, max(64, BLOCK_BYTES // max(wide, 1) // 64 * 64))
    out = np.zeros((wide, -(-len(lists) // 64) * 8), np.uint8)
    offsets, flat = unpacked(lists, n_items)
    rows = np.repeat(np.arange(len(lists)), np.diff(offsets))
    if wide < n_items:
        flat, rows = _renumbered(flat, rows, n_items, only)
    base = np.searchsorted(rows, np.arange(0, len(lists) + step, step))
    for at, x, y in zip(range(0, len(lists), step), base, base[1:], strict=False):
        dense = np.zeros((wide, min(step, len(lists) - at)), bool)
        dense[flat[x:y], rows[x:y] - at] = True
        part = np.packbits(dense, axis=1)
        out[:, at // 8 : at // 8 + part.shape[1]] = part
    return out.view(np.uint64)


def _renumbered(flat: np.ndarray, rows: np.ndarray, n_items: int, only: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Items of ``only`` by their places there, and their rows; others are left out, no tuple is."""
    places = np.full(n_items, -1, np.int32)
    places[only] = np.arange(len(only))
    flat = places.take(flat)
    at = np.flatnonzero(flat >= 0)
    return flat.take(at), rows.take(at)


#: What a pair of a tuple's items costs against a word of a bit vector; counters of pairs that a task may hold; pairs that are counted at once.
PAIR_COST, PAIR_COUNTERS, PAIRS = 6, 1 << 22, 1 << 22


class PairCounts:
    """Counts of all pairs of items in sparse lists, from the pairs that tuples have: no candidate is held against every tuple."""

    def __init__(self, n: int):
        self.n, self.total, self.room, self.filled = n, np.zeros(n * n, np.int64), np.empty(PAIRS, np.int64), 0

    def add(self, flat: np.ndarray, sizes: np.ndarray) -> None:
        """Lists of ``sizes`` items; the longest come first, so that each pair of places is a pair of columns."""
        order = np.argsort(-sizes, kind="stable")
        begin, sizes = (np.cumsum(sizes) - sizes)[order], sizes[order]
        columns, scaled = [], []
        for j in range(int(sizes[0]) if len(sizes) else 0):
            m = int(np.searchsorted(-sizes, -j))  # lists with more than j items
            columns.append(flat.take(begin[:m] + j).astype(np.int64))
            for one in scaled:
                if self.filled + m > len(self.room):
                    self.flush()
                if m > len(self.room):
                    self.room = np.empty(m, np.int64)
                np.add(one[:m], columns[j], out=self.room[self.filled : self.filled + m])
                self.filled += m
            scaled.append(columns[j] * self.n)

    def flush(self) -> None:
        if self.filled:
            found = np.bincount(self.room[: self.filled])
            self.total[: len(found)] += found
            self.filled = 0

    def of(self, pairs: np.ndarray) -> np.ndarray:
        self.flush()
        a, b = pairs[:, 0].astype(np.int64), pairs[:, 1].astype(np.int64)
        return self.total[a * self.n + b] + self.total[b * self.n + a]


def together(columns: np.ndarray, itemsets: np.ndarray) -> np.ndarray:
    """The bit vector of each of ``itemsets`` (one length a call)."""
    bits = columns[itemsets[:, 0]]
    for k in range(1, itemsets.shape[1]):
        bits &= columns[itemsets[:, k]]
    return bits


def _few_pairs(lists: pa.ListArray | pa.BinaryArray, n_items: int, only: np.ndarray, candidates: int) -> bool:
    """Whether the pairs that tuples have are less work than the candidates' bit vectors."""
    sizes = np.diff(unpacked(lists, n_items)[0]).astype(np.int64)
    return len(only) ** 2 <= PAIR_COUNTERS and PAIR_COST * int((sizes * (sizes - 1) // 2).sum()) < candidates * (len(lists) // 64 + 1)


def count_tables(table: DataFrame, columns: Sequence[str], levels: Sequence[Sequence[Itemset]], n_items: int) -> list[np.ndarray]:
    """All-ones counts of a list of candidates (of one length, if any) for each of ``columns`` of item lists, in one pass over the table."""
    for level in levels:
        if len(level) > CANDIDATE_BUDGET:
            raise CandidateBudgetExceeded(f"{len(level)} candidates; at most {CANDIDATE_BUDGET}")
    at = np.cumsum([0, *map(len, levels)])
    asked = [i for i, level in enumerate(levels) if len(level)]
    if not asked:
        return [np.zeros(0, np.int64) for _ in levels]
    shared = table.sparkSession.sparkContext.broadcast([np.array(level, np.int32) for level in levels])

    only = [np.unique(np.array(level, np.int32)) for level in levels]

    def totals(batches: Iterator[pa.RecordBatch]) -> np.ndarray:
        out, pairs = np.zeros(at[-1], np.int64), {}
        placed = {i: np.searchsorted(only[i], shared.value[i]) for i in asked}
        for batch in batches:
            for j, i in enumerate(asked):
                lists, sets, here = batch.column(j), placed[i], out[at[i] : at[i + 1]]
                if sets.shape[1] == 1:
                    here += np.bincount(unpacked(lists, n_items)[1], minlength=n_items)[only[i][sets[:, 0]]]
                elif sets.shape[1] == 2 and _few_pairs(lists, n_items, only[i], len(sets)):
                    offsets, flat = unpacked(lists, n_items)
                    flat, rows = _renumbered(flat, np.repeat(np.arange(len(lists)), np.diff(offsets)), n_items, only[i])
                    pairs.setdefault(i, PairCounts(len(only[i]))).add(flat, np.bincount(rows, minlength=len(lists)))
                else:
                    bits = bit_columns(lists, n_items, only[i])
                    step = max(1, 32_768 // max(bits.shape[1], 1))
                    for x in range(0, len(sets), step):
                        part = sets[x : x + step]
                        here[x : x + len(part)] += np.bitwise_count(together(bits, part)).sum(1, dtype=np.int64)
        for i, found in pairs.items():
            out[at[i] : at[i + 1]] += found.of(placed[i])
        return out

    found = added(table.select(*(columns[i] for i in asked)), totals, int(at[-1]))
    return [found[at[i] : at[i + 1]] for i in range(len(levels))]


def trie(itemsets: Sequence[Itemset]) -> dict:
    """Nested dictionaries by item; the number of a candidate under None at its end."""
    root: dict = {}
    for i, x in enumerate(itemsets):
        node = root
        for item in x:
            node = node.setdefault(item, {})
        node[None] = i
    return root


def count_trie(arrays: DataFrame, itemsets: Sequence[Itemset]) -> DataFrame:
    """(cand, n) tuple by tuple: its sorted items walk a trie of the candidates, which is broadcast within the budget."""
    frame(arrays.sparkSession, itemsets[:0])
    if len(itemsets) > CANDIDATE_BUDGET:
        raise CandidateBudgetExceeded(f"{len(itemsets)} candidates; at most {CANDIDATE_BUDGET}")
    shared = arrays.sparkSession.sparkContext.broadcast(list(itemsets))

    def walk(node: dict, items: list[int], at: int, out: dict[int, int]) -> None:
        for i in range(at, len(items)):
            if (below := node.get(items[i])) is not None:
                if None in below:
                    out[below[None]] = out.get(below[None], 0) + 1
                walk(below, items, i + 1, out)

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        root, out = trie(shared.value), {}
        for batch in batches:
            for items in batch.column(0).to_pylist():
                walk(root, items, 0, out)
        if out:
            yield pa.RecordBatch.from_arrays([pa.array(list(out), pa.int32()), pa.array(list(out.values()), pa.int64())], ["cand", "n"])

    return arrays.select("items").mapInArrow(work, "cand int, n long").groupBy("cand").agg(F.sum("n").alias("n"))


def count_gram(arrays: DataFrame, itemsets: Sequence[Itemset], n_items: int) -> DataFrame:
    """(cand, n) of pairs from the product of each block with itself."""
    if any(len(x) != 2 for x in itemsets):
        raise ValueError("a Gram matrix counts pairs only")
    shared = arrays.sparkSession.sparkContext.broadcast(None)
    pairs = _partials(arrays, shared, n_items, lambda block, _: (block.T.astype(np.float32) @ block.astype(np.float32)).astype(np.int64))
    each = frame(arrays.sparkSession, itemsets).select("cand", (F.col("itemset")[0].cast("long") * n_items + F.col("itemset")[1]).alias("at"))
    return pairs.join(F.broadcast(each), "at").select("cand", "n")


def pattern_counts(long: DataFrame, itemsets: Sequence[Itemset], dbsize: int) -> DataFrame:
    """(cand, pattern, n) for all 2**k patterns of each candidate; bit i of a pattern is the i-th item, 0 comes from ``dbsize``."""
    seen = long.join(exploded(long.sparkSession, itemsets, places=True), "item").groupBy("tid", "cand").agg(F.sum(F.expr("shiftleft(1L, at)")).alias("pattern"))
    seen = seen.groupBy("cand", "pattern").agg(F.count(F.lit(1)).alias("n"))
    return _with_rest(seen, "pattern", itemsets, dbsize)


def weight_counts(long: DataFrame, itemsets: Sequence[Itemset], dbsize: int) -> DataFrame:
    """(cand, weight, n): tuples by how many of the candidate's items they have; the class of none comes from ``dbsize``."""
    seen = long.join(exploded(long.sparkSession, itemsets), "item").groupBy("tid", "cand").agg(F.count(F.lit(1)).alias("weight"))
    return _with_rest(seen.groupBy("cand", "weight").agg(F.count(F.lit(1)).alias("n")), "weight", itemsets, dbsize)


def _with_rest(seen: DataFrame, name: str, itemsets: Sequence[Itemset], dbsize: int) -> DataFrame:
    others = frame(seen.sparkSession, itemsets).select("cand").join(seen.groupBy("cand").agg(F.sum("n").alias("met")), "cand", "left")
    rest = others.select("cand", F.lit(0).cast("long").alias(name), (F.lit(dbsize) - F.coalesce("met", F.lit(0))).cast("long").alias("n"))
    return seen.select("cand", name, "n").unionByName(rest)


def _classes_by_chunks(arrays: DataFrame, itemsets: Sequence[Itemset], n_items: int, classes: int, powers: Sequence[int]) -> DataFrame:
    """(cand, class, n): the class is the sum of ``powers`` of the places of a candidate's items that a tuple has; every tuple is looked at for every candidate."""
    shared = arrays.sparkSession.sparkContext.broadcast(np.array(itemsets, np.int32))

    def of(block: np.ndarray, candidates: np.ndarray) -> np.ndarray:
        kind = np.uint8 if classes <= 256 else np.int64
        columns, out = np.ascontiguousarray(block.T).astype(kind), np.zeros((len(candidates), classes), np.int64)
        for i, items in enumerate(candidates):
            codes = columns[items[0]] * kind(powers[0])
            for item, power in zip(items[1:], powers[1:], strict=True):
                codes += columns[item] * kind(power)
            out[i] = np.bincount(codes, minlength=classes)
        return out

    flat = _partials(arrays, shared, n_items, of)
    return flat.select(F.floor(F.col("at") / classes).cast("int").alias("cand"), (F.col("at") % classes).alias("class"), "n")


def weights_by_chunks(arrays: DataFrame, itemsets: Sequence[Itemset], n_items: int) -> DataFrame:
    """(cand, weight, n) from dense blocks: every tuple is looked at for every candidate, which is what makes the scheme slow."""
    k = len(itemsets[0])
    return _classes_by_chunks(arrays, itemsets, n_items, k + 1, [1] * k).withColumnRenamed("class", "weight")


def patterns_by_chunks(arrays: DataFrame, itemsets: Sequence[Itemset], n_items: int) -> DataFrame:
    """(cand, pattern, n) from dense blocks, as ``pattern_counts`` gives but for patterns that no tuple has: a task keeps 2**k counters a candidate and shuffles nothing else."""
    k = len(itemsets[0])
    return _classes_by_chunks(arrays, itemsets, n_items, 1 << k, [1 << i for i in range(k)]).withColumnRenamed("class", "pattern")


def expected_largest_class(s0: float, p: float, q: float, k: int) -> int:
    """The weight class that most tuples are expected in; its counter need not be kept, ``dbsize`` gives it."""
    from math import comb

    one = s0 * p + (1 - s0) * (1 - q)
    return max(range(k + 1), key=lambda w: comb(k, w) * one**w * (1 - one) ** (k - w))


def counters(k: int, strategy: str) -> int:
    """Counters per candidate of k items."""
    return {"pattern": 2**k, "weight": k + 1, "weight_explicit": k, "ones": 1}[strategy]


def count(baskets_arrays: DataFrame, itemsets: Sequence[Itemset], n_items: int, physical: str = "chunks") -> dict[Itemset, int]:
    """All-ones counts of candidates of one length, on the driver: as many numbers as candidates, within the budget."""
    if not itemsets:
        return {}
    long = lambda: baskets_arrays.select("tid", F.explode("items").alias("item"))
    ways = {
        "chunks": lambda: count_chunks(baskets_arrays, itemsets, n_items), "relational": lambda: count_relational(long(), itemsets),
        "bitmaps": lambda: count_bitmaps(column_bits(long()), itemsets), "gram": lambda: count_gram(baskets_arrays, itemsets, n_items),
        "trie": lambda: count_trie(baskets_arrays, itemsets),
    }
    if physical not in ways:
        raise ValueError(f"unknown physical strategy {physical}; there are {sorted(ways)}")
    found = dict.fromkeys(itemsets, 0)
    for row in ways[physical]().collect():
        found[itemsets[row.cand]] = row.n
    return found
