"""Toxicity classifier with a counterfactual penalty: swapping identity terms must not move a score."""

from __future__ import annotations

import functools
import re
import zlib
from collections import Counter
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from .common import mix64

#: The classifier is fitted on so many labelled rows at most: those whose hashed doc_id is smallest.
SAMPLE = 5000
#: Words of the model at most, those that tell the classes apart best; chance that any word is taken without reason.
WORDS, CHANCE = 4000, 0.05
#: Of so many least hashes of its words a row must share fewer than the second number with each earlier row, else it is a near copy.
HASHES, ALIKE = 8, 4
#: Lengths of stems in letters, and the shares of a text's words from which a stem counts as used often.
STEMS, SHARES = (3, 4, 5, 6, 7), (0.005, 0.01, 0.015, 0.02, 0.03)
#: Weights of the absolute-value and the counterfactual penalties, steps of the fit, and the decision's cutoff.
SPARSITY, FAIRNESS, STEPS, CUTOFF = 0.1, 1.0, 2000, 0.7

#: Identity terms by group; a term is swapped for each other of its group.
IDENTITY_TERMS = (
    ("women", "men"), ("woman", "man"), ("girls", "boys"), ("girl", "boy"), ("female", "male"), ("mothers", "fathers"),
    ("black", "white", "asian", "latino", "african", "european"), ("muslim", "christian", "jewish", "hindu", "buddhist", "atheist"),
    ("muslims", "christians", "jews", "hindus", "buddhists", "atheists"), ("gay", "straight", "lesbian", "bisexual", "transgender"),
    ("immigrants", "refugees", "natives", "foreigners"), ("disabled", "deaf", "blind", "autistic"), ("old", "young", "elderly"),
    ("femmes", "hommes"), ("frauen", "männer"), ("mujeres", "hombres"), ("musulmans", "chrétiens", "juifs"), ("muslime", "christen", "juden"),
)

_WORD = re.compile(r"[^\W\d_]+")
_PLACE = {term: (group, i) for group in IDENTITY_TERMS for i, term in enumerate(group)}


def counted(text: str | None) -> Counter[str]:
    """Words in lower case (runs of letters, so marks stuck to a word do not hide it) with their numbers."""
    return Counter(_WORD.findall((text or "").lower()))


def features(found: Counter[str], stems: dict[int, frozenset[str]] | None = None) -> set[str]:
    """Distinct words of a text, and stems used often.

    A stem is the beginning of words; ``stem~2`` says that it begins two words or more and at least the
    third share of ``SHARES`` of all words. With ``stems``, by length, only those are looked for.
    """
    out, total = set(found), sum(found.values())
    for size in STEMS:
        wanted = None if stems is None else stems.get(size)
        if stems is not None and not wanted:
            continue
        begun: dict[str, int] = {}
        for word, n in found.items():
            stem = word[:size]
            if (wanted is None or stem in wanted) and len(stem) == size:
                begun[stem] = begun.get(stem, 0) + n
        out.update(f"{stem}~{level}" for stem, n in begun.items() if n > 1 for level, share in enumerate(SHARES) if n >= share * total)
    return out


def counterfactuals(found: Counter[str]) -> list[Counter[str]]:
    """The words of the same text without its identity terms, and with each swapped for every other of its group in turn.

    A text without any gets a group named in it, twice and in two hundredths of its words at least, so that the
    stems of the name are used often too.
    """
    terms = [w for w in found if w in _PLACE]
    if not terms:
        pick = zlib.crc32(" ".join(sorted(found)).encode())
        return [found + Counter({sorted(_PLACE)[pick % len(_PLACE)]: max(2, -(-sum(found.values()) // 50))})]
    out = [Counter({w: n for w, n in found.items() if w not in _PLACE})]
    for turn in range(max(len(_PLACE[w][0]) for w in terms) - 1):
        swapped = out[0].copy()
        for w in terms:
            group, i = _PLACE[w]
            swapped[group[(i + 1 + turn % (len(group) - 1)) % len(group)]] += found[w]
        out.append(swapped)
    return out


def example(text: str | None) -> tuple[list[str], list[list[str]]]:
    """The features of a text, and for each counterfactual those it lacks (after ``-``) or has besides (after ``+``)."""
    found = counted(text)
    own = features(found)
    others = [features(other) for other in counterfactuals(found)]
    return sorted(own), [sorted([f"-{w}" for w in own - other] + [f"+{w}" for w in other - own]) for other in others]


@dataclass
class Model:
    weights: dict[str, float]
    bias: float

    @functools.cached_property
    def stems(self) -> dict[int, frozenset[str]]:
        known = {w.partition("~")[0] for w in self.weights if "~" in w}
        return {size: frozenset(w for w in known if len(w) == size) for size in STEMS}

    def score(self, text: str | None) -> float:
        # whatever order a set has, the sum is taken in one order
        logit = self.bias + sum(self.weights[w] for w in sorted(features(counted(text), self.stems) & self.weights.keys()))
        return float(1 / (1 + np.exp(-np.clip(logit, -500, 500))))


Row = tuple[list[str], int, list[list[str]]]


def without_copies(rows: list[Row]) -> list[Row]:
    """One row of each set of equal or nearly equal rows of a class, by least hashes."""
    salts = np.random.default_rng(5).integers(1, 2**63, HASHES, dtype=np.uint64)
    seen: dict[tuple[int, int, int], list[int]] = {}
    out: list[Row] = []
    last = None
    for row in sorted(rows, key=lambda r: (r[0], r[1])):
        own, label, _ = row
        if last == (own, label):
            continue
        last = (own, label)
        hashes = np.array([zlib.crc32(w.encode()) for w in own if "~" not in w] or [0], np.uint64) + np.uint64(1)
        with np.errstate(over="ignore"):
            least = mix64(hashes[:, None] * salts[None, :]).min(0).tolist()
        met: dict[int, int] = {}
        for k, x in enumerate(least):
            for at in seen.get((label, k, x), ()):
                met[at] = met.get(at, 0) + 1
        if max(met.values(), default=0) >= ALIKE:
            continue
        for k, x in enumerate(least):
            seen.setdefault((label, k, x), []).append(len(out))
        out.append(row)
    return out


def fit(rows: list[Row], sparsity: float = SPARSITY, fairness: float = FAIRNESS) -> Model:
    """Logistic regression on the presence of features, by accelerated proximal steps.

    A row has its features, its label, and the changes that its counterfactuals make (``example``). Copies count
    once, so that they do not make a word look significant. Features enter whose share of toxic rows
    differs from that of all rows by more than chance, by a Chernoff bound over all. The penalty is
    ``fairness`` times the summed squared change of the logit between a row and its counterfactuals, their mean for each row.
    """
    rows = without_copies(rows)
    labels = np.array([r[1] for r in rows], float)
    if not rows or labels.min() == labels.max():
        return Model({}, 500.0 if rows and labels[0] else -500.0)
    counts: dict[str, list[int]] = {}
    for own, label, _ in rows:
        for w in own:
            counts.setdefault(w, [0, 0])[label] += 1
    share = labels.mean()
    part = lambda k, n, p: k * np.log(k / (n * p)) if k else 0.0
    signal = {w: part(k[1], sum(k), share) + part(k[0], sum(k), 1 - share) for w, k in counts.items()}
    chosen = sorted((w for w in counts if signal[w] > np.log(len(counts) / CHANCE)), key=lambda w: (-signal[w], w))[:WORDS]
    chosen += sorted(_PLACE.keys() - set(chosen))
    place = {w: i for i, w in enumerate(chosen)}
    at = [[place[w] for w in own if w in place] for own, _, _ in rows]
    row, col = np.repeat(np.arange(len(at)), [len(x) for x in at]), np.array([i for x in at for i in x], int)
    moves = [(others, len(variants) ** -0.5) for _, _, variants in rows for others in variants]
    moved = [(i, place[w[1:]], weight if w[0] == "+" else -weight) for i, (others, weight) in enumerate(moves) for w in others if w[1:] in place]
    row2, col2, by = (np.array(x, kind) for x, kind in zip(zip(*moved, strict=True) if moved else ((), (), ()), (int, int, float), strict=True))
    n, m = len(rows), len(chosen)
    times = lambda r, c, w: np.bincount(r, w[c], n)
    back = lambda r, c, x: np.bincount(c, x[r], m)
    # of the penalty half its slope: the changes of the logits, taken back to the weights
    unfair = lambda w: np.bincount(col2, by * np.bincount(row2, by * w[col2], max(len(moves), 1))[row2], m)
    probe = np.ones(m + 1)
    for _ in range(20):
        y = times(row, col, probe[:m]) + probe[m]
        probe = np.append(0.25 * back(row, col, y) + 2 * fairness * unfair(probe[:m]), 0.25 * y.sum())
        size = np.linalg.norm(probe)
        probe /= size
    w, look, pace = np.zeros(m + 1), np.zeros(m + 1), 1.0
    for _ in range(STEPS):
        off = 1 / (1 + np.exp(-(times(row, col, look[:m]) + look[m]))) - labels
        slope = np.append(back(row, col, off) + 2 * fairness * unfair(look[:m]), off.sum())
        new = look - slope / (1.1 * size)
        new[:m] = np.sign(new[:m]) * np.maximum(np.abs(new[:m]) - sparsity / (1.1 * size), 0)
        faster = (1 + np.sqrt(1 + 4 * pace * pace)) / 2
        look, w, pace = new + (pace - 1) / faster * (new - w), new, faster
    return Model({x: float(w[i]) for x, i in place.items() if w[i]}, float(w[m]))


def remainder(divisor: int) -> Column:
    """crc32 of the doc_id as text, modulo ``divisor``; a null doc_id counts as an empty text."""
    return F.crc32(F.coalesce(F.col("doc_id").cast("string"), F.lit(""))) % divisor


def train(documents: DataFrame, labels: DataFrame, sample: int = SAMPLE) -> Model:
    """Fits on labelled documents that are not held out, ``sample`` of them at most; only their words come to the driver."""
    known = labels.where(F.col("toxic").isin(0, 1) & F.col("doc_id").isNotNull()).select(F.col("doc_id").cast("long").alias("doc_id"), "toxic")
    known = known.where(remainder(3) != 1).groupBy("doc_id").agg(F.max("toxic").alias("toxic"))
    some = known.orderBy(F.xxhash64("doc_id"), "doc_id").limit(sample)
    texts = documents.select(F.col("doc_id").cast("long").alias("doc_id"), "text").join(F.broadcast(some), "doc_id").select("text", "toxic")

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            rows = [example(t) for t in batch.column(0).to_pylist()]
            yield pa.RecordBatch.from_arrays([pa.array([r[0] for r in rows], pa.list_(pa.string())), batch.column(1).cast(pa.int32()), pa.array([r[1] for r in rows], pa.list_(pa.list_(pa.string())))], ["words", "toxic", "others"])

    pool: dict[str, str] = {}  # a word is held once, however many rows have it
    one = lambda words: [pool.setdefault(w, w) for w in words]
    return fit([(one(r.words), r.toxic, [one(x) for x in r.others]) for r in texts.mapInArrow(work, "words array<string>, toxic int, others array<array<string>>").toLocalIterator()])


def scored(documents: DataFrame, model: Model, keep: tuple[str, ...] = ("doc_id",)) -> DataFrame:
    """The ``keep`` columns, score and predicted for each row, from its whole text alone.

    A null text is an empty one and gets the score of no words at all; other columns are ignored. Only
    texts go to the Python workers and only scores come back. The model, at most ``WORDS`` words, is broadcast.
    """
    shared = documents.sparkSession.sparkContext.broadcast(model)

    def score(batches: Iterator[pa.Array]) -> Iterator[pa.Array]:
        for texts in batches:
            yield pa.array([shared.value.score(t.as_py()) for t in texts], pa.float64())

    rows = documents.withColumn("score", F.arrow_udf(score, T.DoubleType())(F.col("text").cast("string")))
    return rows.select(*(c for c in keep), "score", (F.col("score") >= CUTOFF).cast("int").alias("predicted"))


def classified(documents: DataFrame, labels: DataFrame) -> DataFrame:
    """doc_id, held_out, score and predicted for every row of ``documents``; without labels nothing is toxic."""
    ids = documents.select(F.col("doc_id").cast("long").alias("doc_id"), "text")
    return scored(ids, train(documents, labels)).select("doc_id", (remainder(3) == 1).alias("held_out"), "score", "predicted")
