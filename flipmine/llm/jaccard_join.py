"""N-gram Jaccard join by T-occurrence search (DivideSkip), and the components that its links form.

Work that grows with the square of a group of near copies is cut in three ways: equal sets become
one class at once; only classes that share one of their rarest shingles meet; and a class is not
compared with one that it is already connected to. A group that is too large for one task is cut into
chunks, and each pair of chunks is a task's work.
"""

from __future__ import annotations

import heapq
from bisect import bisect_left
from collections.abc import Callable, Iterator
from math import ceil, log2

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from .common import mix64, slices, stored, words_hashed

#: A shingle that more classes have in their prefix than this is put last in the order of rarity, by its number, ...
FREQUENT = 1
#: ... and so many such shingles at most are broadcast (16 bytes each); if there are more, FREQUENT is doubled until they fit.
MOST_FREQUENT = 1 << 20
#: Classes of a chunk: at least SMALL, at most LARGE; between these a group has CHUNKS chunks.
SMALL, LARGE, CHUNKS = 64, 4096, 32
#: So many classes of groups at most (24 bytes each) are broadcast to the texts; more are joined by a shuffle.
MOST_MEMBERS = 1_000_000
#: Prefixes are this much longer when frequent shingles are looked for.
WIDER = 1.5
#: Linked sets share so many shingles of their prefixes (or all, if fewer are needed to be linked at all).
SHARED = 3
#: Classes that meet in a list of so many at most are counted pair by pair; those of a longer list become one group.
PAIRED = 32
#: DivideSkip's weight of a probe against a step of the merge.
MU = 0.0085

#: So many postings of a task are combined before they are shuffled (20 bytes each).
COMBINED = 1 << 21
#: Classes without a doc_id are numbered from here on, by their fingerprint, so that named ones come first.
NAMELESS = 1 << 62

SKETCH = T.StructType([
    T.StructField("doc_id", T.LongType()), T.StructField("n_shingles", T.LongType()), T.StructField("h1", T.LongType()),
    T.StructField("h2", T.LongType()), T.StructField("prefix", T.ArrayType(T.LongType())),
])


def shingle_sets(texts: pa.Array, size: int) -> Iterator[tuple[np.ndarray, np.ndarray]]:
    """Per text its distinct shingles as sorted 64-bit hashes, and the length in bytes of each.

    A text of fewer than ``size`` words, but not none, is one shingle. Long shingles are rare ones, by
    and large; the lengths serve for an order that needs no statistics.
    """
    for a, b in slices(texts):
        words, lengths, bounds = words_hashed(texts.slice(a, b - a))
        with np.errstate(over="ignore"):
            hashes, chars = np.zeros_like(words), np.zeros_like(lengths)
            for k in range(size):
                hashes[: len(words) - k] = hashes[: len(words) - k] * np.uint64(0x9E3779B97F4A7C55) + words[k:] + np.uint64(k + 1)
                chars[: len(words) - k] += lengths[k:]
            hashes = mix64(hashes)
            for lo, hi in zip(bounds[:-1].tolist(), bounds[1:].tolist(), strict=True):
                if lo == hi:
                    yield hashes[:0].view(np.int64), chars[:0]
                elif hi - lo < size:
                    whole = np.uint64(hi - lo)
                    for word in words[lo:hi]:
                        whole = whole * np.uint64(0x9E3779B97F4A7C55) + word
                    yield mix64(np.array([whole ^ np.uint64(0x5555)], np.uint64)).view(np.int64), lengths[lo:hi].sum(keepdims=True)
                else:
                    own, at = np.unique(hashes[lo : hi - size + 1].view(np.int64), return_index=True)
                    yield own, chars[lo:hi][at]


def least_overlap(n: int, percent: int) -> int:
    """Shingles that a set of ``n`` has in common, at the very least, with any set it is linked to."""
    return -(-percent * n // 100)


def least_shared(n: int, percent: int) -> int:
    """Shingles of its prefix that a set of ``n`` shares with the prefix of any set it is linked to."""
    return min(SHARED, least_overlap(n, percent))


def pair_overlap(n: int, m: int, percent: int) -> int:
    """Shingles that sets of ``n`` and ``m`` must share to be linked."""
    return -(-percent * (n + m) // (100 + percent))


def prefix(own: np.ndarray, chars: np.ndarray, percent: int, frequent: tuple[np.ndarray, np.ndarray], wider: float = 1.0) -> np.ndarray:
    """The shingles of a set that come first in the common order: frequent ones last, else long ones first.

    Two linked sets share as many of these as the one that needs fewer asks for (``least_shared``); that
    holds for any order that all sets use.
    """
    n = len(own)
    take = min(n, ceil((n - least_overlap(n, percent) + least_shared(n, percent)) * wider))
    known, weight = frequent
    at = np.minimum(np.searchsorted(known, own), max(len(known) - 1, 0))
    often = np.where(known[at] == own, weight[at], 0) if len(known) else np.zeros(n, np.int64)
    return own[np.lexsort((own, -chars, often))[:take]]


def fingerprint(own: np.ndarray) -> tuple[int, int]:
    """128 bits that stand for a set; the first 64 are its class's number in the search for candidates.

    Of n classes some two have equal numbers with a chance below n * n / 2**65.
    """
    bits = own.view(np.uint64)
    with np.errstate(over="ignore"):
        return int(mix64(bits).sum(dtype=np.uint64).astype(np.int64)), int(mix64(bits ^ np.uint64(0xA5A5A5A5A5A5A5A5)).sum(dtype=np.uint64).astype(np.int64))


def texts_of(documents: DataFrame) -> DataFrame:
    return documents.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text"))


def sketches(documents: DataFrame, size: int, percent: int) -> DataFrame:
    """Per row: size of the set, its fingerprint and its prefix by length alone, somewhat longer than needed."""
    none = (np.zeros(0, np.int64), np.zeros(0, np.int64))

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            n, prints, rare = [], [], []
            for own, chars in shingle_sets(batch.column(1), size):
                n.append(len(own))
                prints.append(fingerprint(own))
                rare.append(prefix(own, chars, percent, none, WIDER))
            ends = np.concatenate(([0], np.cumsum([len(x) for x in rare]))).astype(np.int32)
            flat = pa.array(np.concatenate(rare) if rare else np.zeros(0, np.int64), pa.int64())
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(n, pa.int64()), *(pa.array([x[k] for x in prints], pa.int64()) for k in (0, 1)), pa.ListArray.from_arrays(pa.array(ends), flat)], SKETCH.names)

    return texts_of(documents).mapInArrow(work, SKETCH)


def frequent_shingles(rows: DataFrame) -> tuple[np.ndarray, np.ndarray]:
    """Shingles that stand in the prefixes of several classes, sorted, with the number of rows as weight; a bounded list.

    Any list gives an order that is right, so eight bits tell classes apart well enough here.
    """
    tokens = rows.select(F.explode("prefix").alias("token"), (F.col("h1") % 256).cast("short").alias("kind"))
    counts = tokens.groupBy("token").agg(F.count(F.lit(1)).alias("count"), F.min("kind").alias("least"), F.max("kind").alias("most"))
    counts = stored(counts.where((F.col("count") > FREQUENT) & (F.col("least") < F.col("most"))).select("token", "count"), "shingle-counts")
    least = FREQUENT
    while counts.where(F.col("count") > least).count() > MOST_FREQUENT:
        least *= 2
    found = counts.where(F.col("count") > least).toArrow()
    token, count = found["token"].to_numpy(), found["count"].to_numpy()
    order = np.argsort(token)
    return token[order], count[order]


def distinct_postings(token: np.ndarray, node: np.ndarray, need: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """Postings sorted by token and node without repeats; where each token's list begins and how long it is."""
    order = np.lexsort((need, node, token))
    token, node, need = token[order], node[order], need[order]
    new = np.concatenate(([True], (token[1:] != token[:-1]) | (node[1:] != node[:-1]))) if len(token) else np.zeros(0, bool)
    token, node, need = token[new], node[new], need[new]
    heads = np.flatnonzero(np.concatenate(([True], token[1:] != token[:-1]))) if len(token) else np.zeros(0, np.int64)
    return token, node, need, heads, np.diff(np.append(heads, len(token)))


def pairs_once(a: np.ndarray, b: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """The distinct pairs (a, b) of different nodes."""
    order = np.lexsort((b, a))
    a, b = a[order], b[order]
    new = (np.concatenate(([True], (a[1:] != a[:-1]) | (b[1:] != b[:-1]))) if len(a) else np.zeros(0, bool)) & (a != b)
    return a[new], b[new]


def postings(documents: DataFrame, size: int, percent: int, frequent: tuple[np.ndarray, np.ndarray]) -> DataFrame:
    """(token, node, need): a shingle of a class's prefix, the class, and how many shingles it has to share.

    A list that is long within a task already becomes a star there: each of its classes is tied to the
    smallest (rows with need -1: token and node are the two ends), which alone goes on, with need 0. So a shingle of a third
    of all classes costs a few rows per task, and so does a text that a third of all rows have.
    """
    shared, paired, most = documents.sparkSession.sparkContext.broadcast(frequent), PAIRED, COMBINED
    schema = pa.schema([("token", pa.int64()), ("node", pa.int64()), ("need", pa.int32())])

    def combined(held: list[tuple[np.ndarray, int, int]]) -> Iterator[pa.RecordBatch]:
        lengths = [len(x[0]) for x in held]
        token, node, need, heads, sizes = distinct_postings(np.concatenate([x[0] for x in held]), np.repeat([x[1] for x in held], lengths), np.repeat(np.array([x[2] for x in held], np.int32), lengths))
        long = np.repeat(sizes > paired, sizes)
        far, least = pairs_once(node[long], np.repeat(node[heads], sizes)[long])
        first = heads[sizes > paired]
        out = [np.concatenate(x) for x in ((token[~long], token[first], far), (node[~long], node[first], least), (need[~long], np.zeros(len(first), np.int32), np.full(len(far), -1, np.int32)))]
        yield from pa.Table.from_arrays([pa.array(x) for x in out], schema=schema).to_batches(max_chunksize=100_000)

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held, total = [], 0
        for batch in batches:
            for own, chars in shingle_sets(batch.column(0), size):
                if len(own):
                    rare = prefix(own, chars, percent, shared.value)
                    held.append((rare, fingerprint(own)[0], least_shared(len(own), percent)))
                    total += len(rare)
                    if total >= most:
                        yield from combined(held)
                        held, total = [], 0
        if held:
            yield from combined(held)

    return documents.select(F.col("text").cast("string").alias("text")).mapInArrow(work, "token long, node long, need int")


def meetings(found: DataFrame) -> DataFrame:
    """Edges (a, b) that bring all classes which may be linked into one component.

    In short lists pairs are counted, and those that share too few shingles are left out, so that chance
    meetings do not chain texts together; a long list becomes a star around its smallest member. Postings are shuffled
    once; lists stream by in order, so that none has to be held as a whole.
    """

    paired = PAIRED

    def edges(token: np.ndarray, node: np.ndarray, need: np.ndarray) -> tuple[np.ndarray, ...]:
        token, node, need, heads, sizes = distinct_postings(token, node, need)
        star = (sizes > paired) | (np.minimum.reduceat(need, heads) == 0) if len(heads) else np.zeros(0, bool)
        star = np.repeat(star, sizes)
        far, least = pairs_once(node[star], np.repeat(node[heads], sizes)[star])
        token, node, need = token[~star], node[~star], need[~star]
        a, b, asked = [far], [least], [np.zeros(len(far), np.int32)]
        for k in range(1, paired):
            both = np.flatnonzero(token[k:] == token[:-k])
            if not len(both):
                break
            a.append(node[both + k])
            b.append(node[both])
            asked.append(np.minimum(need[both], need[both + k]))
        return np.concatenate(a), np.concatenate(b), np.concatenate(asked)

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        rest = [np.zeros(0, np.int64), np.zeros(0, np.int64), np.zeros(0, np.int32)]
        for batch in batches:
            columns = [batch.column(k).to_numpy() for k in range(3)]
            tie = columns[2] < 0
            yield pa.RecordBatch.from_arrays([pa.array(columns[0][tie]), pa.array(columns[1][tie]), pa.array(np.zeros(int(tie.sum()), np.int32))], ["a", "b", "need"])
            held = [np.concatenate((x, y[~tie])) for x, y in zip(rest, columns, strict=True)]
            cut = int(np.searchsorted(held[0], held[0][-1])) if len(held[0]) else 0
            a, b, need = edges(*(x[:cut] for x in held))
            rest = [x[cut:] for x in held]
            if len(rest[0]) > 4 * paired:  # a long list: its smallest member stands for it from here on
                far, least = pairs_once(rest[1], np.full(len(rest[1]), rest[1][0]))
                a, b, need = np.append(a, far), np.append(b, least), np.append(need, np.zeros(len(far), np.int32))
                rest = [rest[0][:1], rest[1][:1], np.zeros(1, np.int32)]
            yield pa.RecordBatch.from_arrays([pa.array(a), pa.array(b), pa.array(need)], ["a", "b", "need"])
        yield pa.RecordBatch.from_arrays([pa.array(x) for x in edges(*rest)], ["a", "b", "need"])

    met = found.repartition("token").sortWithinPartitions("token", "node").mapInArrow(work, "a long, b long, need int")
    return met.groupBy("a", "b").agg(F.count(F.lit(1)).alias("n"), F.min("need").alias("need")).where("need = 0 OR n >= need").select("a", "b")


def stars(a: np.ndarray, b: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Every node of the edges (a, b) but the smallest of each component, with that smallest one."""
    nodes, at = np.unique(np.concatenate((a, b)), return_inverse=True)
    u, v, root = at[: len(a)], at[len(a) :], np.arange(len(nodes))
    while len(u):
        x, y = root[u], root[v]
        if (x == y).all():
            break
        np.minimum.at(root, np.maximum(x, y), np.minimum(x, y))
        while not (root[root] == root).all():
            root = root[root]
    far = root != np.arange(len(nodes))
    return nodes[far], nodes[root[far]]


def contracted(edges: DataFrame) -> DataFrame:
    """Edges of the same components: those of each task's edges, at most ``COMBINED`` at once, become stars."""
    most = COMBINED

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held, total = [], 0
        for batch in batches:
            held.append((batch.column(0).to_numpy(), batch.column(1).to_numpy()))
            total += batch.num_rows
            if total >= most:
                yield pa.RecordBatch.from_arrays([pa.array(x) for x in stars(*(np.concatenate(x) for x in zip(*held, strict=True)))], ["a", "b"])
                held, total = [], 0
        if held:
            yield pa.RecordBatch.from_arrays([pa.array(x) for x in stars(*(np.concatenate(x) for x in zip(*held, strict=True)))], ["a", "b"])

    return edges.select("a", "b").mapInArrow(work, "a long, b long")


def components(edges: DataFrame) -> DataFrame:
    """(node, component) for the nodes of ``edges`` (a, b): the smallest node that can be reached.

    Alternating large-star and small-star steps until every node hangs on one that hangs on none; before each, the edges of a
    task are contracted, so that few steps are left. Minima are combined before
    they are shuffled; they are stored so that a node with very many neighbours is a skewed join, which
    adaptive execution splits, and not one task.
    """
    tidy = lambda found: stored(contracted(stored(found.distinct(), "edges")), "edges")
    edges = tidy(edges.where("a <> b").select(F.greatest("a", "b").alias("a"), F.least("a", "b").alias("b")))
    while True:
        up, down = edges.select(F.col("a").alias("node"), F.lit(1).alias("up"), F.lit(0).alias("down")), edges.select("b", F.lit(0), F.lit(1))
        roles = up.union(down).groupBy("node").agg(F.sum("up").alias("up"), F.sum("down").alias("down"))
        if roles.where("up > 1 OR (up > 0 AND down > 0)").isEmpty():
            return edges.select(F.col("a").alias("node"), F.col("b").alias("component")).union(edges.select("b", "b").distinct())
        both = edges.union(edges.select("b", "a"))
        low = stored(both.groupBy("a").agg(F.least(F.min("b"), F.col("a")).alias("low")), "lows")
        large = both.join(low, "a").where("b > a").select(F.col("b").alias("a"), F.col("low").alias("b"))
        large = stored(large.where("a <> b").distinct(), "edges")
        low = stored(large.groupBy("a").agg(F.min("b").alias("low")), "lows")
        small = large.join(low, "a").where("b <> low").select(F.col("b").alias("a"), F.col("low").alias("b"))
        edges = tidy(small.union(low.select("a", "low")))


class Forest:
    def __init__(self, n: int):
        self.up = list(range(n))

    def root(self, x: int) -> int:
        while self.up[x] != x:
            self.up[x] = self.up[self.up[x]]
            x = self.up[x]
        return x

    def join(self, x: int, y: int) -> bool:
        x, y = self.root(x), self.root(y)
        self.up[max(x, y)] = min(x, y)
        return x != y


def divide_skip(lists: list[list[int]], least: int) -> Iterator[tuple[int, int, list[list[int]]]]:
    """Entries that ``least`` or more of the sorted ``lists`` may hold: (entry, lists met, lists left to probe).

    The longest lists are set aside. The short ones are merged by a heap that skips entries which too few
    lists can still hold; whatever passes is left to be looked up in the long ones.
    """
    lists = sorted(lists, key=len)
    if len(lists) < least:
        return
    aside = min(least - 1, int(least / (MU * log2(max(len(lists[-1]), 2)) + 1)))
    short, long = lists[: len(lists) - aside], lists[len(lists) - aside :]
    need = least - aside
    place = [0] * len(short)
    heap = [(x[0], i) for i, x in enumerate(short)]
    heapq.heapify(heap)
    while len(heap) >= need:
        entry, met = heap[0][0], []
        while heap and heap[0][0] == entry:
            met.append(heapq.heappop(heap)[1])
        if len(met) >= need:
            yield entry, len(met), long
            after = entry + 1
            for i in met:
                place[i] += 1
        else:  # fewer than ``need`` lists lie before the next entry that can pass: skip to it
            while heap and len(met) < need - 1:
                met.append(heapq.heappop(heap)[1])
            if not heap:
                return
            after = heap[0][0]
            for i in met:
                place[i] = bisect_left(short[i], after, place[i])
        for i in met:
            if place[i] < len(short[i]):
                heapq.heappush(heap, (short[i][place[i]], i))


def linked(sets: list[np.ndarray], first: int, percent: int) -> list[tuple[int, int]]:
    """Links among ``sets`` that connect what was not yet connected.

    With ``first`` = 0 each set is a query against those before it; else the first ``first`` sets are queries
    against the others.
    """
    sets = [s.tolist() for s in sets]
    sizes, forest, found = [len(s) for s in sets], Forest(len(sets)), []
    index: dict[int, list[int]] = {}

    def enter(i: int) -> None:
        for token in sets[i]:
            if token in index:
                index[token].append(i)
            else:
                index[token] = [i]

    for i in range(first, len(sets)) if first else ():
        enter(i)
    for query in range(first or len(sets)):
        n = sizes[query]
        lists = [index[t] for t in sets[query] if t in index]
        for other, met, rest in divide_skip(lists, least_overlap(n, percent)):
            if forest.root(query) == forest.root(other):
                continue
            need = pair_overlap(n, sizes[other], percent)
            for k, entries in enumerate(rest):
                if met >= need or met + len(rest) - k < need:
                    break
                at = bisect_left(entries, other)
                met += at < len(entries) and entries[at] == other
            if met >= need and forest.join(query, other):
                found.append((query, other))
        if not first:
            enter(query)
    return found


def links(documents: DataFrame, members: DataFrame, size: int, percent: int) -> DataFrame:
    """Links (a, b) between classes, enough of them to connect whatever is connected.

    ``members`` (rid, h1, component) has the classes that may be linked: those with equal component. A class's set
    comes from the document whose doc_id is its rid, or, for classes without a name, from any with its fingerprint.
    """
    counts = members.groupBy("component").agg(F.count(F.lit(1)).alias("n"))
    chunk = F.least(F.greatest(F.ceil(F.col("n") / CHUNKS), F.lit(SMALL)), F.lit(LARGE))
    counts = stored(counts.select("component", F.ceil(F.col("n") / chunk).cast("int").alias("chunks")), "group-chunks")
    members = stored(members.join(counts, "component").select("rid", "named", "h1", "component", "chunks"), "group-members")
    named, nameless = members.where("named").select(F.col("rid").alias("doc_id"), "h1", "component", "chunks"), members.where("NOT named")
    if members.count() <= MOST_MEMBERS:
        named = F.broadcast(named)
    texts = texts_of(documents).join(named, "doc_id")

    def sets(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            own = [s for s, _ in shingle_sets(batch.column("text"), size)]
            mine = pa.array([fingerprint(s)[0] == h for s, h in zip(own, batch.column("h1").to_pylist(), strict=True)], pa.bool_())
            columns = [batch.column(name) for name in ("doc_id", "h1", "component", "chunks")]
            yield pa.RecordBatch.from_arrays([*columns, pa.array([s.tobytes() for s in own], pa.binary())], ["rid", "h1", "component", "chunks", "own"]).filter(mine)

    def own_sets(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            own = [s for s, _ in shingle_sets(batch.column(0), size)]
            yield pa.RecordBatch.from_arrays([pa.array([fingerprint(s)[0] for s in own], pa.int64()), pa.array([s.tobytes() for s in own], pa.binary())], ["h1", "own"])

    rows = texts.mapInArrow(sets, "rid long, h1 long, component long, chunks int, own binary")
    if not nameless.isEmpty():
        other = documents.where("doc_id IS NULL").select(F.col("text").cast("string").alias("text")).mapInArrow(own_sets, "h1 long, own binary")
        rows = rows.unionByName(other.join(nameless.select("h1", "rid", "component", "chunks"), "h1").dropDuplicates(["h1"]))
    rows = rows.withColumn("chunk", F.pmod(F.xxhash64("h1"), F.col("chunks")).cast("int")).withColumn("other", F.explode(F.sequence(F.lit(0), F.col("chunks") - 1)))
    rows = rows.select("rid", "h1", "own", "component", "chunk", F.least("chunk", "other").alias("i"), F.greatest("chunk", "other").alias("j"))
    rows = rows.repartition("component", "i", "j").sortWithinPartitions("component", "i", "j", "chunk", "h1")

    def search(cell: tuple, ids: list[int], prints: list[int], chunks: list[int], own: list[bytes]) -> list[tuple[int, int]]:
        seen = {h: k for k, h in reversed(list(enumerate(prints)))}  # rows that repeat a class are one
        keep = sorted(seen.values())
        first = sum(chunks[k] == cell[1] for k in keep) if cell[1] != cell[2] else 0
        if cell[1] != cell[2] and first in (0, len(keep)):
            return []
        return [(ids[keep[a]], ids[keep[b]]) for a, b in linked([np.frombuffer(own[k], np.int64) for k in keep], first, percent)]

    def cells(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        cell, held = None, ([], [], [], [])
        out: list[tuple[int, int]] = []
        for batch in batches:
            columns = batch.to_pydict()
            for rid, h1, own, chunk, *key in zip(*(columns[name] for name in ("rid", "h1", "own", "chunk", "component", "i", "j")), strict=True):
                if tuple(key) != cell:
                    if cell and len(held[0]) > 1:
                        out += search(cell, *held)
                    cell, held = tuple(key), ([], [], [], [])
                for column, value in zip(held, (rid, h1, chunk, own), strict=True):
                    column.append(value)
            if out:
                yield pa.RecordBatch.from_arrays([pa.array([x[0] for x in out], pa.int64()), pa.array([x[1] for x in out], pa.int64())], ["a", "b"])
                out = []
        if cell and len(held[0]) > 1 and (out := search(cell, *held)):
            yield pa.RecordBatch.from_arrays([pa.array([x[0] for x in out], pa.int64()), pa.array([x[1] for x in out], pa.int64())], ["a", "b"])

    return rows.mapInArrow(cells, "a long, b long")


def grouped(documents: DataFrame, size: int = 5, percent: int = 80) -> DataFrame:
    """Per row doc_id, n_shingles, h1, h2 (its set's fingerprint), first and named.

    ``first`` is the number of the smallest class of the row's component: the smallest doc_id, ``named`` then, or a
    number that only says which rows without doc_id belong together. Texts without shingles have their own
    doc_id there.
    """
    rows = stored(sketches(documents, size, percent), "sketches")
    classes = rows.where("n_shingles > 0").groupBy("h1", "h2").agg(F.min("doc_id").alias("least"))
    number = F.coalesce("least", F.lit(NAMELESS) + F.col("h1").bitwiseAND(F.lit(NAMELESS - 1)))
    classes = stored(classes.select("h1", "h2", number.alias("rid"), F.col("least").isNotNull().alias("named")), "classes")
    groups = stored(components(meetings(postings(documents, size, percent, frequent_shingles(rows)))), "groups")
    members = classes.join(groups.withColumnRenamed("node", "h1"), "h1")
    found = components(links(documents, members.select("rid", "named", "h1", "component"), size, percent))
    first = F.coalesce("component", "rid")
    named = classes.join(found.withColumnRenamed("node", "rid"), "rid", "left").select("h1", "h2", first.alias("first"), ((first < NAMELESS) | F.col("named")).alias("named"))
    named = stored(named, "named")
    own = F.col("n_shingles") > 0
    return rows.drop("prefix").join(named, ["h1", "h2"], "left").select(
        "doc_id", "n_shingles", "h1", "h2", F.when(own, F.col("first")).otherwise(F.col("doc_id")).alias("first"), F.when(own, F.col("named")).otherwise(F.col("doc_id").isNotNull()).alias("named")
    )


def joined(documents: DataFrame, size: int = 5, percent: int = 80) -> DataFrame:
    """Per row of ``documents`` (doc_id, text): doc_id, n_shingles and component_id.

    Two documents are linked if the shingles they share are ``percent`` % or more of those either has;
    the component is the smallest doc_id that links reach. A null or empty text, or one of white space,
    has no shingles and is its own component. Rows with equal doc_id count as one document; a null
    doc_id links through its text but is never the component's name, unless there is no other, and then
    it is null (doc_ids are below 2**62 where null ones occur). Other columns are ignored.
    """
    return grouped(documents, size, percent).select("doc_id", "n_shingles", F.when(F.col("named"), F.col("first")).alias("component_id"))


def one_of_each(documents: DataFrame, columns: list[str], size: int = 5, percent: int = 80) -> DataFrame:
    """One row of each component of ``documents``, with its ``columns`` (doc_id and text among them): that of the smallest doc_id.

    Of rows that repeat a doc_id the smallest stays, of a component without doc_ids the smallest row of its
    first class, and every row without shingles and doc_id. Only ids and fingerprints are shuffled, but for
    rows that repeat an id or have none: ids that go are broadcast up to ``MOST_MEMBERS``, beyond it they are joined.
    """
    rows = stored(grouped(documents, size, percent).drop("n_shingles", "h2"), "grouped")
    ids = rows.where("doc_id IS NOT NULL").groupBy("doc_id").agg(F.max(F.col("doc_id") == F.col("first")).alias("stays"), F.count(F.lit(1)).alias("n"))
    ids = stored(ids.where("n > 1 OR NOT stays"), "grouped-ids")
    gone, again = ids.where("NOT stays").select("doc_id"), ids.where("stays").select("doc_id")
    if gone.count() <= MOST_MEMBERS:
        gone = F.broadcast(gone)
    least = lambda df, *keys: df.groupBy(*keys).agg(F.min(F.struct(*columns)).alias("row")).select("row.*").select(*columns)
    out = documents.where("doc_id IS NOT NULL").select(*columns).join(gone, "doc_id", "left_anti").select(*columns)
    if not again.isEmpty():
        out = out.join(again, "doc_id", "left_anti").select(*columns).unionByName(least(out.join(again, "doc_id", "left_semi"), "doc_id"))
    nameless = rows.where("doc_id IS NULL AND NOT named")
    if not rows.where("doc_id IS NULL").isEmpty():
        own = documents.where("doc_id IS NULL").select(*columns).withColumn("print", _prints(size)(F.col("text").cast("string")))
        firsts = nameless.where((F.lit(NAMELESS) + F.col("h1").bitwiseAND(F.lit(NAMELESS - 1))) == F.col("first")).select(F.col("h1").alias("print")).distinct()
        out = out.unionByName(own.where("print IS NULL").select(*columns)).unionByName(least(own.join(firsts, "print", "left_semi"), "print"))
    return out


def _prints(size: int) -> Callable[[Column], Column]:
    """A function of texts: the first half of the fingerprint, null where there are no shingles."""

    def work(batches: Iterator[pa.Array]) -> Iterator[pa.Array]:
        for texts in batches:
            yield pa.array([fingerprint(own)[0] if len(own) else None for own, _ in shingle_sets(texts, size)], pa.int64())

    return F.arrow_udf(work, T.LongType())
