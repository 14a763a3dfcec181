"""Language-model scores from a gated recurrent network with a class-factored softmax.

The network foretells the class of the next word and, for the most frequent words, the word within its class;
both factors see the state. Rarer words share a few classes by frequency, in which counts over the whole
training corpus say how likely a word is. The weights are fitted on all training documents, each in one round
of parallel descent; a task descends on the documents of its split, so weights depend on how the input is split.
"""

from __future__ import annotations

import heapq
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from .common import slices, stored, words_hashed

#: The most frequent words that occur twice or more are broadcast, this many at most; others, the tail, are joined by hash.
HEAD = 131_072
#: The most frequent words make NEAR classes of SLOTS words, foretold one by one; other words of the head make REST - 1 classes, the tail the last.
NEAR, SLOTS, REST = 64, 64, 16
#: Width of the state; lanes and window of truncated backpropagation; longer documents are cut into segments for it (not for scores).
HIDDEN, LANES, WINDOW, SEGMENT = 24, 256, 16, 512
#: Rounds of parallel descent, which deal out the training documents; tasks of a round at most; step size at first, which falls to a tenth.
ROUNDS, TASKS, RATE = 2, 4096, 0.02
#: Tokens of a window of scoring.
AHEAD = 8192
#: Bits of a hash that say where to look for it.
PREFIX = 17
#: Bytes of text that are cut into words at once.
BLOCK = 500_000
#: The hash that stands for the end of a document.
END = np.int64(0x454E44)
LN10 = np.log(10.0)
KINDS, ROWS = NEAR + REST, NEAR * SLOTS + REST

Params = dict[str, np.ndarray]


@dataclass(frozen=True)
class Words:
    """What is known of the head: sorted hashes with count, class, input row, and log10 share of the class's count."""

    keys: np.ndarray
    count: np.ndarray
    kind: np.ndarray
    row: np.ndarray
    inside: np.ndarray
    prior: np.ndarray  # log probability of each class
    slots: np.ndarray  # log probability of each slot in its near class; empty ones have next to none

    def look(self, hashes: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Place in the head, and whether it is there at all."""
        if not len(self.keys):
            return np.zeros(len(hashes), int), np.zeros(len(hashes), bool)
        at = np.minimum(searched(self.keys, hashes), len(self.keys) - 1)
        return at, self.keys[at] == hashes

    def codes(self, hashes: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """Input row of each token (of a near word its class and slot at once), place and membership."""
        at, there = self.look(hashes)
        row = self.row[at] if len(self.keys) else np.where(hashes == END, 0, ROWS - 1)
        return np.where(there, row, np.where(hashes == END, 0, ROWS - 1)).astype(np.int16), at, there


def searched(keys: np.ndarray, hashes: np.ndarray) -> np.ndarray:
    """``np.searchsorted``; many hashes begin at the first key with their highest bits, and few keys share these."""
    if len(hashes) < 1 << PREFIX:
        return np.searchsorted(keys, hashes)
    first = np.searchsorted(keys, np.arange(-(1 << PREFIX - 1), 1 << PREFIX - 1) << 64 - PREFIX)
    at = first[(hashes >> 64 - PREFIX) + (1 << PREFIX - 1)]
    for _ in range(int(np.diff(first, append=len(keys)).max())):
        at += keys[np.minimum(at, len(keys) - 1)] < hashes
    return np.minimum(at, len(keys))


def kinds_of(rows: np.ndarray) -> np.ndarray:
    """Class by input row: a near word's row holds its class and slot, other classes have one row each."""
    return np.where(rows < NEAR * SLOTS, rows // SLOTS, rows - NEAR * SLOTS + NEAR)


def classes(keys: np.ndarray, count: np.ndarray, tail: int) -> Words:
    """Near classes by rank, then classes of about equal weight; the end is the first word, the last class is all beyond the head."""
    is_end = keys == END
    order = np.lexsort((keys, -count, ~is_end))
    keys, count = keys[order], count[order]
    near = min(len(keys), NEAR * SLOTS)
    row = np.arange(len(keys))
    rest = count[near:]
    if len(rest):
        row[near:] = NEAR * SLOTS + np.minimum((np.cumsum(rest) - rest / 2) * (REST - 1) // rest.sum(), REST - 2)
    kind = kinds_of(row)
    weight = np.bincount(kind, count, KINDS).astype(float)
    inside = np.log10(count / weight[kind]) if len(keys) else np.zeros(0)
    slots = np.full(NEAR * SLOTS, -60.0)
    slots[:near] = inside[:near] * LN10
    weight[-1] = tail
    prior = np.log((weight + 1) / (weight + 1).sum())
    order = np.argsort(keys)
    return Words(keys[order], count[order], kind[order], row[order], inside[order], prior, slots.reshape(NEAR, SLOTS))


def fresh(words: Words) -> Params:
    """Where descent begins: both factors are those of the counts, whatever the state."""
    rng = np.random.default_rng(11)
    small = lambda *shape: rng.normal(0, 0.1, shape).astype(np.float32)
    return {
        "inputs": small(ROWS, 3 * HIDDEN), "state": small(HIDDEN, 3 * HIDDEN), "out": np.zeros((HIDDEN, KINDS), np.float32), "bias": words.prior.astype(np.float32),
        "inner": np.zeros((NEAR, HIDDEN, SLOTS), np.float32), "slots": words.slots.astype(np.float32),
    }


def forward(p: Params, x: np.ndarray, begin: np.ndarray, h: np.ndarray, keep: bool = True) -> tuple[np.ndarray, list]:
    """States after each step of a window and, if asked for, what ``backward`` needs; ``begin`` marks steps that start a document, where the state is zero.

    Each gate has its own columns. Their signs are turned where they are added up, and the candidate's are doubled: exp takes them as they are.
    """
    steps, n = x.shape
    kind = p["state"].dtype
    out, kept, goes_on = np.empty((steps, n, HIDDEN), kind), [], ~begin
    state = by_gate(p["state"]) * np.array([-1, -1, -2], kind)[:, None, None]
    rows, at = p["inputs"].reshape(-1, HIDDEN), x[:, None, :].astype(np.intp) * 3 + np.arange(3)[:, None]
    one, two = kind.type(1), kind.type(2)
    with np.errstate(over="ignore"):
        for t in range(steps):
            if not goes_on[t].all():
                h = h * goes_on[t][:, None]
            given, gates = rows.take(at[t], 0), np.matmul(h, state)
            both = gates[:2]
            both -= given[:2]
            np.exp(both, out=both)
            both += one
            np.reciprocal(both, out=both)
            r, z, b = gates
            new = r * b
            new -= given[2]
            new -= given[2]
            np.exp(new, out=new)
            new += one
            np.divide(two, new, out=new)
            new -= one
            ahead = h - new
            if keep:
                kept.append((h, r, z, new, b, ahead))
            h = np.multiply(z, ahead, out=out[t])
            h += new
    return out, kept


def by_gate(v: np.ndarray) -> np.ndarray:
    """(3, HIDDEN, HIDDEN): the weights of each gate."""
    return np.ascontiguousarray(v.reshape(HIDDEN, 3, HIDDEN).transpose(1, 0, 2))


#: Logits stay within this; beyond it a probability is next to 0 or 1 anyway. So many rows of them stay in a core's cache.
CLIP, CACHED = 60.0, 512


def slopes(logits: np.ndarray, own: np.ndarray, share: np.ndarray) -> np.ndarray:
    """In place of the logits: the softmax less 1 at each row's ``own`` column, times the row's ``share``."""
    for a in range(0, len(logits), CACHED):
        d, part = logits[a : a + CACHED], share[a : a + CACHED]
        np.minimum(d, CLIP, out=d)
        np.exp(d, out=d)
        total = d @ np.ones(d.shape[1], d.dtype)
        total += 1e-30
        d *= (part / total)[:, None]
    logits[np.arange(len(logits)), own] -= share
    return logits


def with_one(states: np.ndarray) -> np.ndarray:
    """States and a column of ones, which meets the biases."""
    out = np.ones((len(states), HIDDEN + 1), states.dtype)
    out[:, :HIDDEN] = states
    return out


def log_total(logits: np.ndarray) -> np.ndarray:
    """The log of the softmax's divisor alone; the logits are used up."""
    total = np.empty(len(logits), logits.dtype)
    for a in range(0, len(logits), CACHED):
        d = logits[a : a + CACHED]
        np.minimum(d, CLIP, out=d)
        np.matmul(np.exp(d, out=d), np.ones(d.shape[1], d.dtype), out=total[a : a + CACHED])
    total += 1e-30
    return np.log(total, out=total)


def near_groups(rows: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Places of the near words in order of their class, and where each class begins among them."""
    near = np.flatnonzero(rows < NEAR * SLOTS)
    kind = (rows[near] // SLOTS).astype(np.int16)
    order = np.argsort(kind, kind="stable")
    return near[order], np.searchsorted(kind[order], np.arange(NEAR + 1))


def slot_weights(p: Params) -> np.ndarray:
    """(NEAR, HIDDEN + 1, SLOTS): weights within the near classes, biases last."""
    return np.concatenate((p["inner"], p["slots"][:, None]), axis=1)


def groups_of(bounds: np.ndarray) -> list[tuple[int, int, int]]:
    """(class, first, end) of the near classes that are met."""
    ends = bounds.tolist()
    return [(c, a, b) for c, (a, b) in enumerate(zip(ends, ends[1:])) if a < b]


def slot_logits(weights: np.ndarray, states: np.ndarray, groups: list[tuple[int, int, int]]) -> np.ndarray:
    """Of states with a one, in order of their classes."""
    out = np.empty((len(states), SLOTS), states.dtype)
    for c, a, b in groups:
        np.matmul(states[a:b], weights[c], out=out[a:b])
    return out


def log_likelihood(p: Params, states: np.ndarray, rows: np.ndarray) -> np.ndarray:
    """Natural log probability of each token's class and, for near words, of the word in it."""
    at, states = np.arange(len(rows)), with_one(states)
    logits = states @ np.concatenate((p["out"], p["bias"][None]))
    got = np.minimum(logits[at, kinds_of(rows)], CLIP)
    got -= log_total(logits)
    places, bounds = near_groups(rows)
    inner = slot_logits(slot_weights(p), states.take(places, 0), groups_of(bounds))
    own = np.minimum(inner[at[: len(places)], rows[places] % SLOTS], CLIP)
    got[places] += own - log_total(inner)
    return got


def backward(p: Params, x: np.ndarray, y: np.ndarray, begin: np.ndarray, live: np.ndarray, states: np.ndarray, kept: list) -> tuple[Params, np.ndarray]:
    """Gradient of the mean loss over a window, nothing flowing beyond its first step; for ``inputs`` only of the rows in the second result."""
    flat, rows = with_one(states.reshape(-1, HIDDEN)), y.ravel()
    kind, share = flat.dtype, (live.ravel() / max(live.sum(), 1)).astype(flat.dtype)
    d = slopes(flat @ np.concatenate((p["out"], p["bias"][None])), kinds_of(rows), share)
    outer, back = flat.T @ d, d @ p["out"].T
    places, bounds = near_groups(rows)
    groups, weights, own = groups_of(bounds), slot_weights(p), flat.take(places, 0)
    d = slopes(slot_logits(weights, own, groups), rows[places] % SLOTS, share[places])
    within, turned, inner = np.zeros_like(weights), np.ascontiguousarray(p["inner"].transpose(0, 2, 1)), np.empty((len(own), HIDDEN), kind)
    for c, a, b in groups:
        mine = d[a:b]
        np.matmul(own[a:b].T, mine, out=within[c])
        np.matmul(mine, turned[c], out=inner[a:b])
    back[places] += inner
    back = back.reshape(states.shape)
    dh, one, half = np.zeros_like(states[0]), kind.type(1), kind.type(-0.5)
    # slopes of the candidate, of both gates, and of what the candidate has of the state
    slope, keep, turned = np.empty((4, *states.shape), kind), ~begin, np.ascontiguousarray(by_gate(p["state"]).transpose(0, 2, 1))
    for t in range(len(x) - 1, -1, -1):
        h, r, z, new, b, ahead = kept[t]
        dnew, dr, dz, db = slope[:, t]
        dh += back[t]
        through = dh * z
        np.subtract(dh, through, out=dnew)
        rest = new * new
        np.subtract(one, rest, out=rest)
        dnew *= rest
        np.multiply(dnew, r, out=db)
        np.subtract(one, r, out=rest)
        rest *= db
        rest *= half
        np.multiply(rest, b, out=dr)  # the state's part was doubled and its sign turned
        np.subtract(one, z, out=rest)
        rest *= ahead
        np.multiply(rest, through, out=dz)
        dh = through
        for part in np.matmul(slope[1:, t], turned):
            dh += part
        if not keep[t].all():
            dh *= keep[t][:, None]
    slope = slope.reshape(4, -1, HIDDEN)
    g = {"out": outer[:-1], "bias": outer[-1], "inner": within[:, :-1], "slots": within[:, -1]}
    g["state"] = np.concatenate(np.concatenate([k[0] for k in kept]).T @ slope[1:], axis=1)
    times = np.bincount(x.ravel(), minlength=ROWS)
    seen, place = np.flatnonzero(times), np.cumsum(times > 0) - 1
    cells = (place[x.ravel()] * HIDDEN)[:, None] + np.arange(HIDDEN)
    g["inputs"] = np.concatenate([np.bincount(cells.ravel(), slope[i].ravel()).reshape(-1, HIDDEN) for i in (1, 2, 0)], axis=1, dtype=kind, casting="same_kind")
    return g, seen


class Descent:
    """Adam on the weights; of the input rows only those met in a window move."""

    def __init__(self, start: Params, steps: int):
        self.p = {k: v.copy() for k, v in start.items()}
        self.first, self.second = ({k: np.zeros_like(v) for k, v in start.items()} for _ in range(2))
        self.step, self.steps = 0, max(steps, 1)
        self.met = {"inputs": np.zeros(ROWS), "inner": np.zeros(NEAR), "slots": np.zeros(NEAR)}  # how often a row, or a class, was seen
        self.seen = 0

    def window(self, x: np.ndarray, y: np.ndarray, begin: np.ndarray, live: np.ndarray, h: np.ndarray) -> np.ndarray:
        """One step on a window; the state that it ends with."""
        states, kept = forward(self.p, x, begin, h)
        g, rows = backward(self.p, x, y, begin, live, states, kept)
        self.step += 1
        rate = RATE * max(0.1, 1 - self.step / self.steps)
        for k, d in g.items():
            first, second = self.first[k], self.second[k]
            if k == "inputs":
                first, second = first.take(rows, 0), second.take(rows, 0)
            move = np.subtract(d, first)
            move *= 0.1
            first += move
            np.multiply(d, d, out=move)
            move -= second
            move *= 0.01
            second += move
            if k == "inputs":
                self.first[k][rows], self.second[k][rows] = first, second
            # both moments are brought up to what they are without their start at zero
            spread = np.float32((1 - 0.99**self.step) ** 0.5)
            np.sqrt(second, out=move)
            move += np.float32(1e-6) * spread
            np.divide(first, move, out=move)
            move *= np.float32(rate / (1 - 0.9**self.step)) * spread
            if k == "inputs":
                self.p[k][rows] -= move
            else:
                self.p[k] -= move
        self.met["inputs"] += np.bincount(x[live], minlength=ROWS)
        kinds = np.bincount(kinds_of(y[live]), minlength=KINDS)[:NEAR]
        self.met["inner"] += kinds
        self.met["slots"] += kinds
        self.seen += int(live.sum())
        return states[-1]


def packed(lengths: np.ndarray, lanes: int) -> list[list[int]]:
    """Documents dealt to lanes, longest first and each to the lane that is shortest; longest lane first.

    There are fewer lanes where one document outweighs the rest, so that lanes stay about equal.
    """
    heap = [(0, i, []) for i in range(max(1, min(lanes, -(-int(lengths.sum()) // max(int(lengths.max()), 1)))))]
    for doc in np.argsort(-lengths, kind="stable").tolist():
        held, i, docs = heap[0]
        docs.append(doc)
        heapq.heapreplace(heap, (held + int(lengths[doc]), i, docs))
    return [docs for _, _, docs in sorted(heap, key=lambda x: (-x[0], x[1]))]


def lanes_of(starts: np.ndarray, lanes: list[list[int]], x: np.ndarray, y: np.ndarray) -> tuple[np.ndarray, ...]:
    """Inputs, targets, first-step marks and document numbers by step and lane; -1 where a lane has ended."""
    steps = max(sum(int(starts[d + 1] - starts[d]) for d in docs) for docs in lanes)
    put = lambda fill, kind: np.full((len(lanes), steps), fill, kind)
    xs, ys, begin, docs_at = put(0, np.int16), put(0, np.int16), put(False, bool), put(-1, np.int32)
    for k, docs in enumerate(lanes):
        at = 0
        for d in docs:
            a, b = int(starts[d]), int(starts[d + 1])
            xs[k, at : at + b - a], ys[k, at : at + b - a], docs_at[k, at : at + b - a] = x[a:b], y[a:b], d
            begin[k, at] = True
            at += b - a
    return tuple(np.ascontiguousarray(v.T) for v in (xs, ys, begin, docs_at))


def segments(starts: np.ndarray, most: int = SEGMENT) -> np.ndarray:
    """Where documents begin, and every ``most`` tokens inside them."""
    n = np.diff(starts)
    parts = -(-n // most)
    first = np.repeat(starts[:-1], parts)
    inner = np.arange(len(first)) - np.repeat(np.cumsum(parts) - parts, parts)
    return np.append(first + inner * most, starts[-1])


def tokens(texts: pa.Array) -> tuple[np.ndarray, np.ndarray]:
    """Hashes of all tokens, an end after each text, and where each text's tokens begin; texts are cut into words a few at a time."""
    hashes, counts = [], []
    for a, b in slices(texts, BLOCK):
        words, _, bounds = words_hashed(texts.slice(a, b - a))
        hashes.append(words)
        counts.append(np.diff(bounds))
    counts = np.concatenate(counts) if counts else np.zeros(0, np.int64)
    starts = np.concatenate(([0], np.cumsum(counts + 1)))
    out = np.full(starts[-1], END, np.int64)
    inner = np.ones(len(out), bool)
    inner[starts[1:] - 1] = False
    out[inner] = np.concatenate(hashes).view(np.int64) if hashes else np.zeros(0, np.int64)
    return out, starts


def inputs(rows: np.ndarray, starts: np.ndarray, end_row: int) -> np.ndarray:
    """Each step sees the token before; the first one of a document sees an end."""
    x = np.concatenate(([end_row], rows[:-1])) if len(rows) else rows
    x[starts[:-1]] = end_row
    return x


def counted(documents: DataFrame) -> DataFrame:
    """(word, c): tokens of ``documents`` by hash, combined in the worker before they are shuffled."""

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for a, b in slices(batch.column(0), 12_000_000):
                word, c = np.unique(tokens(batch.column(0).slice(a, b - a))[0], return_counts=True)
                yield pa.RecordBatch.from_arrays([pa.array(word, pa.int64()), pa.array(c, pa.int64())], ["word", "c"])

    return documents.select(F.col("text").cast("string").alias("text")).mapInArrow(work, "word long, c long").groupBy("word").agg(F.sum("c").alias("c"))


def descend(documents: DataFrame, words: Words, params: Params) -> Params:
    """One round: every task descends from ``params`` on its documents; weights are averaged by how often they were used.

    A task sends its weights in blocks; a block of all tasks (at most ``TASKS``) is averaged in one place, in the order of
    the tasks, so that equal splits give equal weights.
    """
    shared = documents.sparkSession.sparkContext.broadcast((words, params))
    names, shapes, block, window = list(params), {k: v.shape for k, v in params.items()}, 1 << 14, WINDOW

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        known, start = shared.value
        run, task = None, 0
        for batch in batches:
            task = task or batch.column(1)[0].as_py() + 1
            for a, b in slices(batch.column(0), 6_000_000):
                hashes, starts = tokens(batch.column(0).slice(a, b - a))
                rows, _, _ = known.codes(hashes)
                x, cuts = inputs(rows, starts, int(known.codes(np.array([END]))[0][0])), segments(starts)
                xs, ys, begin, docs = lanes_of(cuts, packed(np.diff(cuts), LANES), x, rows)
                run = run or Descent(start, 3 * -(-len(xs) // window))
                h = np.zeros((xs.shape[1], HIDDEN), np.float32)
                for t in range(0, len(xs), window):
                    now = slice(t, t + window)
                    h = run.window(xs[now], ys[now], begin[now], docs[now] >= 0, h)
        if run and run.seen:
            times = [np.broadcast_to(run.met[k].reshape(-1, *[1] * (len(shapes[k]) - 1)) if k in run.met else np.float64(run.seen), shapes[k]).ravel() for k in names]
            total, times = np.concatenate([run.p[k].ravel() for k in names]), np.concatenate(times)
            total = total * times
            at = range(0, len(total), block)
            yield pa.RecordBatch.from_arrays([
                pa.array([i // block for i in at], pa.int32()), pa.array([task] * len(at), pa.int64()),
                pa.array([total[i : i + block].astype(np.float32).tobytes() for i in at], pa.binary()), pa.array([times[i : i + block].astype(np.float32).tobytes() for i in at], pa.binary()),
            ], ["part", "task", "total", "times"])

    def mean(key: tuple, rows: pa.Table) -> pa.Table:
        rows = rows.sort_by("task")
        total, times = (sum(np.frombuffer(x.as_py(), np.float32).astype(np.float64) for x in rows[name]) for name in ("total", "times"))
        return pa.table({"part": pa.array([key[0].as_py()], pa.int32()), "v": pa.array([np.where(times > 0, total / np.maximum(times, 1e-9), np.nan).astype(np.float32).tobytes()], pa.binary())})

    rows = documents.select(F.col("text").cast("string").alias("text"), F.spark_partition_id().cast("long").alias("task")).coalesce(TASKS)
    rows = rows.mapInArrow(work, "part int, task long, total binary, times binary").groupBy("part").applyInArrow(mean, "part int, v binary").orderBy("part").toArrow()
    if not rows.num_rows:
        return params
    flat = np.frombuffer(b"".join(rows["v"].to_pylist()), np.float32)
    ends = np.cumsum([v.size for v in params.values()])
    new = {k: flat[e - v.size : e].reshape(v.shape) for (k, v), e in zip(params.items(), ends, strict=True)}
    return {k: np.where(np.isnan(v), params[k], v) for k, v in new.items()}


def scores(p: Params, xs: np.ndarray, ys: np.ndarray, begin: np.ndarray, docs: np.ndarray, n: int) -> np.ndarray:
    """Natural-log probability of each document's classes and near words; the state goes on from window to window until its end."""
    total, h, t = np.zeros(n), np.zeros((xs.shape[1], HIDDEN), np.float32), 0
    while t < len(xs):
        live = int((docs[t] >= 0).sum())  # lanes end from the last on
        now = slice(t, t + max(1, AHEAD // live))
        x, y, d = xs[now, :live], ys[now, :live], docs[now, :live]
        states, _ = forward(p, x, begin[now, :live], h[:live], keep=False)
        h, t = states[-1], now.stop
        there = d >= 0
        total += np.bincount(d[there], log_likelihood(p, states[there], y[there]), n)
    return total


PART = T.StructType([
    T.StructField("doc_id", T.LongType()), T.StructField("held_out", T.BooleanType()), T.StructField("row", T.LongType()), T.StructField("n_tokens", T.LongType()),
    T.StructField("n_head", T.LongType()), T.StructField("head_log", T.DoubleType()), T.StructField("model_log", T.DoubleType()), T.StructField("tail", T.ArrayType(T.LongType())),
])


def parts(documents: DataFrame, words: Words, params: Params) -> DataFrame:
    """Per row what the head and the network say, and the hashes of its other words."""
    shared = documents.sparkSession.sparkContext.broadcast((words, params))

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        known, p = shared.value
        log_count, far = np.log10(known.count + 1.0), np.where(known.row < NEAR * SLOTS, 0.0, known.inside)
        end_row = int(known.codes(np.array([END]))[0][0])
        for batch in batches:
            for a, b in slices(batch.column(3), 24_000_000):
                hashes, starts = tokens(batch.column(3).slice(a, b - a))
                row, at, there = known.codes(hashes)
                doc = np.repeat(np.arange(b - a), np.diff(starts))
                sums = lambda v: np.bincount(doc[there], v, b - a)
                inside = sums(far[at[there]]) if len(known.keys) else np.zeros(b - a)
                head = sums(log_count[at[there]]) if len(known.keys) else np.zeros(b - a)
                model = scores(p, *lanes_of(starts, packed(np.diff(starts), 2 * LANES), inputs(row, starts, end_row), row), b - a) / LN10 + inside
                n_head = np.bincount(doc[there], minlength=b - a)
                ends = np.concatenate(([0], np.cumsum(np.diff(starts) - n_head))).astype(np.int32)
                tail = pa.ListArray.from_arrays(pa.array(ends), pa.array(hashes[~there], pa.int64()))
                yield pa.RecordBatch.from_arrays([
                    *(batch.column(i).slice(a, b - a) for i in range(3)), pa.array(np.diff(starts), pa.int64()), pa.array(n_head, pa.int64()), pa.array(head), pa.array(model), tail,
                ], PART.names)

    return documents.select("doc_id", "held_out", "row", "text").mapInArrow(work, PART)


def scored(documents: DataFrame, divisor: int = 7, held: int = 2) -> DataFrame:
    """doc_id, held_out, n_tokens, n_known, train_tokens, base_score and score for every row of ``documents``.

    Documents whose crc32(doc_id as text) modulo ``divisor`` is ``held`` are held out of all learning (a
    null doc_id counts as an empty text). A null or empty text has one token, its end. Repeated rows are
    scored each and, if not held out, counted each; other columns are ignored. An empty training
    set leaves all words unknown. A word beyond the head counts by its 64-bit hash; such words are joined
    to their counts, none is frequent, so no key is hot. In the class of those words, the tail, a word
    that was seen c times has weight c, and the event of an unseen word as much as there are words in the tail:
    most of these were met once, so new ones are about as likely as they (Good and Turing's estimate).
    """
    crc = F.crc32(F.coalesce(F.col("doc_id").cast("string"), F.lit("")))
    rows = documents.select(F.col("doc_id").cast("long").alias("doc_id"), (crc % divisor == held).alias("held_out"), F.monotonically_increasing_id().alias("row"), F.coalesce(F.col("text").cast("string"), F.lit("")).alias("text"))
    learn = rows.where(~F.col("held_out"))
    counts = stored(counted(learn), "lm-counts")
    n, v = counts.agg(F.coalesce(F.sum("c"), F.lit(0)), F.count(F.lit(1))).first()
    top = counts.where((F.col("c") > 1) | (F.col("word") == F.lit(int(END)))).orderBy((F.col("word") == F.lit(int(END))).desc(), F.desc("c"), "word").limit(HEAD).toArrow()
    keys, count = top["word"].to_numpy().astype(np.int64), top["c"].to_numpy().astype(np.int64)
    n_tail, v_tail = n - int(count.sum()), v - len(keys)
    words = classes(keys, count, n_tail)
    params = fresh(words)
    deal = F.crc32(F.concat(F.lit("round"), F.coalesce(F.col("doc_id").cast("string"), F.lit(""))))
    for i in range(ROUNDS):
        params = descend(learn.where(deal % ROUNDS == i), words, params)
    first = stored(parts(rows, words, params), "lm-parts")
    tails = first.select("row", F.explode("tail").alias("word")).join(counts, "word", "left").groupBy("row")
    tails = tails.agg(F.sum(F.log10(F.coalesce("c", F.lit(0)) + 1)).alias("tail_log"), F.sum(F.log10("c")).alias("seen_log"), F.count("c").alias("known"))
    both = first.join(tails, "row", "left")
    tail_log, n_rest, known = F.coalesce("tail_log", F.lit(0.0)), F.size("tail"), F.coalesce("known", F.lit(0))
    unseen = max(v_tail, 1)
    within = F.coalesce("seen_log", F.lit(0.0)) + (n_rest - known) * float(np.log10(unseen)) - n_rest * float(np.log10(n_tail + unseen))
    return both.select(
        "doc_id", "held_out", "n_tokens", (F.col("n_head") + known).alias("n_known"), F.lit(int(n)).cast("long").alias("train_tokens"),
        (F.col("head_log") + tail_log - F.col("n_tokens") * float(np.log10(n + v + 1))).alias("base_score"),
        (F.col("model_log") + within).alias("score"),
    )
