"""Byte-level BPE by merge replay: the distinct pieces of a portion of texts (4 million characters, the unit
of the inverted index) are merged together, rank by rank.
"""

from __future__ import annotations

import base64
import functools
import heapq
import re
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import regex
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

#: Chunks that a task remembers from earlier batches; beyond it the memory is emptied, results do not change.
MEMORY = 300_000
#: The rank of a pair that does not join.
NONE = np.int32(2**31 - 1)

#: White space other than the blank and the line feed (Unicode's White_Space property).
_RARE_SPACE = re.compile("[\t\x0b-\r\x85\xa0\u1680\u2000-\u200a\u2028\u2029\u202f\u205f\u3000]")
_RUNS = ("  ", " \n", "\n ", "\n\n")


def read_ranks(text: str) -> dict[bytes, int]:
    """Ranks of a vocabulary file: a token in base64 and its rank on each line."""
    return {base64.b64decode(token): int(rank) for token, rank in (line.split() for line in text.splitlines() if line.strip())}


class Merges:
    """Which two neighbouring tokens join, and to which rank: every split of a token into two tokens."""

    def __init__(self, ranks: dict[bytes, int]):
        self.ranks, self.base = ranks, max(ranks.values()) + 1
        keys, joined = [], []
        for token, rank in ranks.items():
            for cut in range(1, len(token)):
                left, right = ranks.get(token[:cut]), ranks.get(token[cut:])
                if left is not None and right is not None:
                    keys.append(left * self.base + right)
                    joined.append(rank)
        order = np.argsort(np.array(keys, np.int64))
        self.keys, self.joined = np.array(keys, np.int64)[order], np.array(joined, np.int32)[order]
        self.byte = np.array([ranks[bytes([b])] for b in range(256)], np.int32)

    def of(self, left: np.ndarray, right: np.ndarray) -> np.ndarray:
        wanted = left.astype(np.int64) * self.base + right
        at = np.minimum(np.searchsorted(self.keys, wanted), len(self.keys) - 1)
        return np.where(self.keys[at] == wanted, self.joined[at], NONE)


def replay(pieces: list[bytes], merges: Merges) -> tuple[np.ndarray, np.ndarray]:
    """Token ids of all pieces, and where each piece's ids begin (one entry more than pieces).

    All pieces lie in one array of linked positions. ``places`` is the inverted index: from the rank of a
    pair to the positions where that pair stands. Ranks are applied in order, each at all its
    positions at once (of overlapping ones every second, from the left), and only the pairs beside a
    merge are looked up anew and entered. Should a merge make a pair of a lower rank than its own,
    the pieces concerned are merged one by one.
    """
    text = np.frombuffer(b"".join(pieces), np.uint8)
    size, lengths = len(text), np.array([len(p) for p in pieces], np.int64)
    starts = np.concatenate(([0], np.cumsum(lengths)))
    token = merges.byte[text]
    after, before = np.arange(1, size + 1, dtype=np.int32), np.arange(-1, size - 1, dtype=np.int32)
    held = starts[:-1][lengths > 0]
    before[held] = -1
    after[np.concatenate((held[1:], [size]))[: len(held)] - 1] = -1
    live = np.ones(size, bool)
    rank = np.full(size, NONE, np.int32)
    inner = np.flatnonzero(after >= 0)
    byte_pairs = merges.of(np.repeat(merges.byte, 256), np.tile(merges.byte, 256))
    rank[inner] = byte_pairs[text[inner].astype(np.int32) * 256 + text[inner + 1]]
    places: dict[int, list[np.ndarray]] = {}
    queue: list[int] = []

    def enter(at: np.ndarray, of: np.ndarray) -> None:
        joins = of != NONE
        at, of = at[joins], of[joins]
        order = np.argsort(of, kind="stable")
        at, of = at[order], of[order]
        cuts = np.flatnonzero(np.diff(of)) + 1
        for value, part in zip(of[np.concatenate(([0], cuts))].tolist() if len(of) else [], np.split(at, cuts), strict=False):
            if value in places:
                places[value].append(part)
            else:
                places[value] = [part]
                heapq.heappush(queue, value)

    enter(inner, rank[inner])
    odd: set[int] = set()
    while queue:
        now = heapq.heappop(queue)
        found = places.pop(now)
        at = found[0] if len(found) == 1 else np.sort(np.concatenate(found))
        at = at[(rank[at] == now) & np.concatenate(([True], at[1:] != at[:-1]))]
        if not len(at):
            continue
        if len(at) > 1 and (chained := after[at[:-1]] == at[1:]).any():
            first = np.concatenate(([True], ~chained))
            run = np.maximum.accumulate(np.where(first, np.arange(len(at)), 0))
            at = at[(np.arange(len(at)) - run) % 2 == 0]
        gone = after[at]
        token[at] = now
        live[gone] = False
        rank[gone] = NONE
        follow = after[gone]
        after[at] = follow
        some = follow >= 0
        before[follow[some]] = at[some]
        rank[at] = NONE
        rank[at[some]] = merges.of(token[at[some]], token[follow[some]])
        left = before[at]
        left = left[left >= 0]
        rank[left] = merges.of(token[left], token[after[left]])
        touched = np.concatenate((at, left))
        fresh = rank[touched]
        if (fresh <= now).any():
            odd.update((np.searchsorted(starts, touched[fresh <= now], side="right") - 1).tolist())
            touched, fresh = touched[fresh > now], fresh[fresh > now]
        enter(touched, fresh)
    bounds = np.concatenate(([0], np.cumsum(live)))[starts]
    ids = token[live]
    if odd:
        parts = [np.array(one_by_one(p, merges.ranks), np.int32) if i in odd else ids[bounds[i] : bounds[i + 1]] for i, p in enumerate(pieces)]
        ids, bounds = np.concatenate(parts), np.concatenate(([0], np.cumsum([len(p) for p in parts])))
    return ids, bounds


def one_by_one(piece: bytes, ranks: dict[bytes, int]) -> list[int]:
    """A single piece with a queue of (rank, place): lowest rank first, of equal ranks the leftmost."""
    end = list(range(1, len(piece) + 1))
    before = list(range(-1, len(piece) - 1))
    queue: list[tuple[int, int, int, int]] = []

    def note(at: int) -> None:
        middle = end[at]
        if middle < len(piece) and (rank := ranks.get(piece[at : end[middle]])) is not None:
            heapq.heappush(queue, (rank, at, middle, end[middle]))

    for at in range(len(piece)):
        note(at)
    while queue:
        _, at, middle, last = heapq.heappop(queue)
        if end[at] != middle or end[middle] != last:
            continue
        end[at], end[middle] = last, 0
        if last < len(piece):
            before[last] = at
        note(at)
        if before[at] >= 0:
            note(before[at])
    ids, at = [], 0
    while at < len(piece):
        ids.append(ranks[piece[at : end[at]]])
        at = end[at]
    return ids


class Codec:
    """Encodes and decodes with a rank file; remembers chunks (runs of pieces) between calls."""

    def __init__(self, ranks: dict[bytes, int], pattern: str):
        self.merges, self.split = Merges(ranks), regex.compile(pattern).findall
        self.token = {rank: token for token, rank in ranks.items()}
        self.known: dict[str, bytes] = {}

    def learn(self, chunks: set[str]) -> None:
        new = [c for c in chunks if c not in self.known]
        if len(self.known) + len(new) > MEMORY:
            self.known, new = {}, list(chunks)
        if not new:
            return
        cut = [self.split(c) for c in new]
        pieces = list(set().union(*cut))
        place = {p: i for i, p in enumerate(pieces)}
        ids, bounds = replay([p.encode() for p in pieces], self.merges)
        raw, bounds = ids.astype("<u4").tobytes(), (bounds * 4).tolist()
        of = {p: raw[bounds[i] : bounds[i + 1]] for p, i in place.items()}
        for chunk, parts in zip(new, cut, strict=True):
            self.known[chunk] = b"".join(map(of.__getitem__, parts))

    def chunks(self, text: str) -> list[str]:
        """Parts that the pattern splits alike alone and in the text.

        Where no two white-space characters stand side by side, a text may be cut before each blank: the
        pattern lets a piece begin with one blank and never contain another. Other texts stay pieces.
        """
        if any(run in text for run in _RUNS) or _RARE_SPACE.search(text):
            return self.split(text)
        first, *rest = text.split(" ")
        return [first, *[" " + part for part in rest]]

    def encode(self, texts: list[str]) -> list[bytes]:
        """Ids of each text as little-endian unsigned 32-bit integers."""
        cut = [self.chunks(t) for t in texts]
        self.learn(set().union(*cut))
        return [b"".join(map(self.known.__getitem__, chunks)) for chunks in cut]

    def decode(self, ids: bytes) -> bytes:
        return b"".join(map(self.token.__getitem__, np.frombuffer(ids, "<u4").tolist()))


@functools.lru_cache(maxsize=2)
def codec(file: str, pattern: str) -> Codec:
    """Kept by a worker between its tasks, but for the chunks it remembers."""
    return Codec(read_ranks(file), pattern)


def portions(texts: list[str], most_chars: int = 4_000_000) -> Iterator[tuple[int, int]]:
    """Ranges of texts that are encoded together: one text at least, whole texts always."""
    at, held = 0, 0
    for i, text in enumerate(texts):
        held += len(text)
        if held >= most_chars:
            yield at, i + 1
            at, held = i + 1, 0
    if at < len(texts):
        yield at, len(texts)


def encoded(documents: DataFrame, ranks_path: str, pattern: str, keep: tuple[str, ...] = ("doc_id",)) -> DataFrame:
    """The ``keep`` columns with ``ids`` (binary, 4 bytes a token) and ``decoded`` (binary, from the ids).

    A null text counts as empty and has no tokens; repeated rows are encoded each; other columns of
    ``documents`` are ignored. The rank file is broadcast: its size is that of a vocabulary, whatever
    the corpus. Narrow: a lost task is simply run again.
    """
    with open(ranks_path, encoding="ascii") as handle:
        file = documents.sparkSession.sparkContext.broadcast(handle.read())
    rows = documents.select(*keep, F.coalesce("text", F.lit("")).alias("text"))
    schema = T.StructType([*rows.select(*keep).schema.fields, T.StructField("ids", T.BinaryType()), T.StructField("decoded", T.BinaryType())])

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        own = codec(file.value, pattern)
        for batch in batches:
            texts = batch.column(len(keep)).to_pylist()
            for a, b in portions(texts):
                ids = own.encode(texts[a:b])
                columns = [batch.column(i).slice(a, b - a) for i in range(len(keep))]
                yield pa.RecordBatch.from_arrays([*columns, pa.array(ids, pa.binary()), pa.array([own.decode(x) for x in ids], pa.binary())], [*keep, "ids", "decoded"])
        own.known = {}

    return rows.mapInArrow(work, schema)


def digests(documents: DataFrame, ranks_path: str, pattern: str) -> DataFrame:
    """Per document the number of tokens and the SHA-256 of its ids and of the bytes decoded from them."""
    return encoded(documents.select(F.col("doc_id").cast("long").alias("doc_id"), "text"), ranks_path, pattern).select(
        "doc_id",
        F.expr("octet_length(ids) div 4").cast("long").alias("n_tokens"),
        F.sha2("ids", 256).alias("ids_sha256"),
        F.sha2("decoded", 256).alias("decoded_sha256"),
    )
