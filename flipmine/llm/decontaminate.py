"""Benchmark decontamination: one Aho-Corasick automaton over windows of test items, each text scanned once."""

from __future__ import annotations

import hashlib
import uuid
from collections.abc import Callable, Iterator
from dataclasses import dataclass

import ahocorasick
import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

WINDOW = 10
#: The automaton has a node per word of a window (some 50 bytes each) in every worker; a benchmark that could have more is refused, not cut.
MOST_NODES = 8_000_000

#: ASCII characters other than digits and letters separate words; A-Z become a-z.
_TABLE = {c: " " for c in range(128) if not chr(c).isalnum()} | {c: chr(c + 32) for c in range(65, 91)}

SCHEMA = T.StructType([
    T.StructField("doc_id", T.LongType()), T.StructField("n_words", T.LongType()), T.StructField("n_hit", T.LongType()),
    T.StructField("n_items", T.LongType()), T.StructField("items_sha256", T.StringType()), T.StructField("contaminated", T.BooleanType()),
    T.StructField("spans", T.ArrayType(T.StructType([T.StructField("begin", T.LongType()), T.StructField("end", T.LongType())]))),
])


def normalised(text: str | None) -> list[str]:
    return [w for w in (text or "").translate(_TABLE).split(" ") if w]


@dataclass
class Index:
    """The automaton over numbered words; value of a window: (number of words, ids of the items that have it)."""

    words: dict[str, int]
    built: ahocorasick.Automaton

    def numbers(self, words: list[str]) -> tuple[int, ...]:
        """Words of no test item are all number 0."""
        known = self.words.get
        return tuple([known(w, 0) for w in words])


def automaton(items: list[tuple[int | None, str | None]], size: int = WINDOW) -> Index:
    """Each run of ``size`` words of an item, or all of a shorter item, is a window; equal ones are one."""
    words: dict[str, int] = {}
    owners: dict[tuple[int, ...], set] = {}
    for item, text in items:
        own = tuple(words.setdefault(w, len(words) + 1) for w in normalised(text))
        for i in range(max(1, len(own) - size + 1) if own else 0):
            owners.setdefault(own[i : i + size], set()).add(item)
    built = ahocorasick.Automaton(ahocorasick.STORE_ANY, ahocorasick.KEY_SEQUENCE)
    for window, ids in owners.items():
        built.add_word(window, (len(window), frozenset(ids)))
    if owners:
        built.make_automaton()
    return Index(words, built)


def original_spans(text: str, hit: np.ndarray) -> list[dict]:
    """Character ranges of the original text that hold runs of hit words."""
    apart = np.array([c == " " for c in text.translate(_TABLE)] + [True])
    starts = np.flatnonzero(~apart & np.concatenate(([True], apart[:-1])))
    ends = np.flatnonzero(apart & ~np.concatenate(([True], apart[:-1])))
    edges = np.diff(np.concatenate(([0], hit.astype(np.int8), [0])))
    return [{"begin": int(starts[a]), "end": int(ends[b - 1])} for a, b in zip(np.flatnonzero(edges == 1), np.flatnonzero(edges == -1), strict=True)]


def scan(text: str | None, index: Index) -> tuple[int, int, set, list[dict]]:
    words = normalised(text)
    if not words or not len(index.built):
        return len(words), 0, set(), []
    found = list(index.built.iter(index.numbers(words)))
    if not found:
        return len(words), 0, set(), []
    last = np.array([end for end, _ in found])
    marks = np.zeros(len(words) + 1, np.int64)
    np.add.at(marks, last + 1, -1)
    np.add.at(marks, last + 1 - np.array([n for _, (n, _) in found]), 1)
    hit = np.cumsum(marks)[:-1] > 0
    return len(words), int(hit.sum()), set().union(*(ids for _, (_, ids) in found)), original_spans(text, hit)


_KEPT: dict[str, Index] = {}


def shared_index(documents: DataFrame, benchmark: DataFrame, size: int) -> Callable[[], Index]:
    """A function that gives the automaton in a worker, which builds it once for all of its tasks.

    Its nodes are bounded before any text comes to the driver.
    """
    n = F.regexp_count(F.coalesce(F.col("text").cast("string"), F.lit("")), F.lit("[^\\x00-\\x2F\\x3A-\\x60\\x7B-\\x7F]+")).cast("long")
    nodes = benchmark.agg(F.sum(F.greatest(n - size + 1, F.lit(1)) * F.least(n, F.lit(size)))).first()[0] or 0
    if nodes > MOST_NODES:
        raise ValueError(f"the benchmark's windows have {nodes} words; at most {MOST_NODES} nodes are held")
    items, name = documents.sparkSession.sparkContext.broadcast([(r.item_id, r.text) for r in benchmark.select("item_id", F.col("text").cast("string").alias("text")).collect()]), uuid.uuid4().hex

    def index() -> Index:
        if name not in _KEPT:
            _KEPT.clear()
            _KEPT[name] = automaton(items.value, size)
        return _KEPT[name]

    return index


def decontaminate(documents: DataFrame, benchmark: DataFrame, size: int = WINDOW) -> DataFrame:
    """Per document: its words, how many lie inside a window of a test item, the items, and original spans.

    ``documents`` has doc_id and text, ``benchmark`` item_id and text; other columns are ignored. A null
    or empty text has no words and no hits; repeated rows give repeated results; equal items share
    their windows and each counts; an empty benchmark hits nothing. The benchmark is the only thing
    broadcast, after its size is checked against ``MOST_NODES``. Item ids that are null mark
    hits but are no items.
    """
    index = shared_index(documents, benchmark, size)

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        built = index()
        for batch in batches:
            rows = []
            for doc, text in zip(batch.column(0).to_pylist(), batch.column(1), strict=True):
                n, n_hit, ids, spans = scan(text.as_py(), built)
                named = sorted(str(i) for i in ids if i is not None)
                rows.append((doc, n, n_hit, len(named), hashlib.sha256(",".join(named).encode()).hexdigest(), n_hit > 0, spans))
            yield pa.RecordBatch.from_pylist([dict(zip(SCHEMA.names, r, strict=True)) for r in rows], schema=ARROW)

    return documents.select(F.col("doc_id").cast("long"), F.col("text").cast("string").alias("text")).mapInArrow(work, SCHEMA)


def clean(documents: DataFrame, benchmark: DataFrame, size: int = WINDOW) -> DataFrame:
    """The rows of ``documents``, with all their columns, in whose own text no window of a test item occurs.

    Each row is judged by itself, whatever its doc_id; a null or empty text is clean. Only texts go to
    the workers; nothing is shuffled.
    """
    index = shared_index(documents, benchmark, size)

    def work(batches: Iterator[pa.Array]) -> Iterator[pa.Array]:
        built = index()
        for texts in batches:
            yield pa.array([next(built.built.iter(built.numbers(normalised(t.as_py()))), None) is not None if len(built.built) else False for t in texts], pa.bool_())

    return documents.where(~F.arrow_udf(work, T.BooleanType())(F.col("text").cast("string")))


ARROW = pa.schema([
    ("doc_id", pa.int64()), ("n_words", pa.int64()), ("n_hit", pa.int64()), ("n_items", pa.int64()), ("items_sha256", pa.string()),
    ("contaminated", pa.bool_()), ("spans", pa.list_(pa.struct([("begin", pa.int64()), ("end", pa.int64())]))),
])
