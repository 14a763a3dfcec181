"""Distortion of baskets at the source: every cell is flipped on its own, by a coin that a private seed fixes.

Coins are keyed by (seed, tuple, item), not drawn from a generator's state: a task that runs again, or
another partitioning, gives the same table, and nobody can average over repeated draws. The seed belongs
to the owner of the data; the miner gets p and q only.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator, Sequence
from itertools import chain

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..config import FlipParams
from ..functions import native
from ..functions.coins import below as tossed_below
from ..sources.baskets import Baskets
from ..sources.shared import spread

#: Bytes of a dense block of tuples and items in a task.
BLOCK_BYTES = 64_000_000


def coin(tid: Column, item: Column, seed: int) -> Column:
    """52 bits as a long: the first 13 hexadecimal digits of a digest of seed, tuple and item."""
    text = F.concat_ws("|", F.lit(str(seed)), tid.cast("string"), item.cast("string"))
    return F.conv(F.substring(F.md5(text), 1, 13), 16, 10).cast("long")


def flip_rule(present: Column, u: Column, params: FlipParams) -> Column:
    """Whether the cell is seen as 1."""
    keep, absent = params.thresholds
    return F.when(present, u < keep).otherwise(u >= absent)


def _lists(seen: np.ndarray, names: np.ndarray | None = None) -> pa.Array:
    """The rows of a dense block as lists of items, called by ``names`` where they are given."""
    rows, items = np.nonzero(seen)
    offsets = np.concatenate(([0], np.cumsum(np.bincount(rows, minlength=len(seen)))))
    flat = items if names is None else names[items]
    return pa.ListArray.from_arrays(pa.array(offsets, pa.int32()), pa.array(flat.astype(np.int32), pa.int32()))


def _span(places: np.ndarray) -> np.ndarray | slice:
    """Ascending places, as a slice if there is no gap."""
    return slice(places[0], places[-1] + 1) if places[-1] - places[0] + 1 == len(places) else places


def _block(rows: np.ndarray, columns: np.ndarray) -> tuple:
    """Index of a block of a table: a view if there is no gap."""
    spans = _span(rows), _span(columns)
    return spans if isinstance(spans[0], slice) or isinstance(spans[1], slice) else np.ix_(rows, columns)


def _steps(batches: Iterator[pa.RecordBatch], n_items: int) -> Iterator[pa.RecordBatch]:
    """Batches cut so that a dense block of tuples and items stays within bounds."""
    step = max(1, BLOCK_BYTES // max(n_items, 1))
    for batch in batches:
        for at in range(0, batch.num_rows, step):
            yield batch.slice(at, step)


def flip_arrays(arrays: DataFrame, n_items: int, params: FlipParams, seed: int, only: Sequence[int] | None = None) -> DataFrame:
    """(tid, items) distorted, from (tid, items); works on streams as well. Narrow: no cell leaves its tuple's row.

    With ``only`` the cells of these items alone, in ascending order, and items are called by their places there.
    """
    bars = params.thresholds
    names = np.arange(n_items) if only is None else np.array(only, int)

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in _steps(batches, n_items):
            held = _by_item(batch.column(1), n_items)
            held = held if only is None else held[names]
            for rows, columns, (kept, low) in tossed_below(seed, batch.column(0).to_pylist(), names, bars):
                at = _block(rows, columns)
                held[at] = np.where(held[at], kept, ~low)
            yield pa.RecordBatch.from_arrays([batch.column(0), _lists(np.ascontiguousarray(held.T))], ["tid", "items"])

    return arrays.select("tid", "items").mapInArrow(work, "tid long, items array<int>")


def flip_counts(arrays: DataFrame, n_items: int, settings: Sequence[FlipParams], seed: int) -> list[np.ndarray]:
    """How often each item is seen under each of ``settings``: a coin is tossed once for all of them, and no distorted table is made or kept.

    Counts are added up within a task and then over tasks; where there are many cells, a process in Java tosses their coins (``functions.native``).
    """
    bars, code = [s.thresholds for s in settings], native.compiled(arrays.sparkSession)

    def totals(batches: Iterator[pa.RecordBatch]) -> np.ndarray | None:
        first = next(batches, None)
        if first is None:
            return None
        batches = chain([first], batches)
        found = native.flipped(code, seed, n_items, bars, batches) if first.num_rows * n_items >= native.WORTH else None
        return (tossed(batches) if found is None else found).ravel()

    def tossed(batches: Iterator[pa.RecordBatch]) -> np.ndarray:
        total = np.zeros((len(settings), n_items), np.int64)
        for batch in _steps(batches, n_items):
            held = _by_item(batch.column(1), n_items)
            for rows, columns, under in tossed_below(seed, batch.column(0).to_pylist(), np.arange(n_items), [bar for pair in bars for bar in pair]):
                true, rows = held[_block(rows, columns)], _span(rows)
                for i, (kept, low) in enumerate(zip(under[::2], under[1::2], strict=True)):
                    total[i, rows] += np.count_nonzero(np.where(true, kept, ~low), axis=1)
        return total

    out = added(spread(arrays.select("tid", "items")), totals, len(settings) * n_items)
    return list(out.reshape(len(settings), n_items))


def flip_cells(baskets: Baskets, params: FlipParams, seed: int) -> Baskets:
    """Distorted baskets in long form; theta(tuples * items) coins, one shuffle by tid to bring a tuple's items together."""
    long = flip_arrays(baskets.arrays(), baskets.n_items, params, seed).select("tid", F.explode("items").alias("item"))
    return Baskets(long, baskets.tids, baskets.items, baskets.n_items)


def flip_symmetric(baskets: Baskets, p: float, seed: int) -> Baskets:
    """The scheme with one keep-probability for both symbols."""
    return flip_cells(baskets, FlipParams(p, p, allow_negative=True), seed)


def flip_tuple(items: list[int], n_items: int, params: FlipParams, seed: int, tid: int) -> list[int]:
    """One tuple on its owner's machine; the same coins as ``flip_arrays``."""
    from hashlib import md5

    keep, absent = params.thresholds
    held = set(items)
    draw = lambda i: int(md5(f"{seed}|{tid}|{i}".encode()).hexdigest()[:13], 16)
    return [i for i in range(n_items) if (draw(i) < keep if i in held else draw(i) >= absent)]


def to_bits(arrays: DataFrame, n_items: int) -> DataFrame:
    """(tid, bits): row-oriented bit vectors, most significant bit first."""

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array([np.packbits(row).tobytes() for row in _dense(batch.column(1), n_items)], pa.binary())], ["tid", "bits"])

    return arrays.select("tid", "items").mapInArrow(work, "tid long, bits binary")


def from_bits(bits: DataFrame, n_items: int) -> DataFrame:
    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            rows = [np.flatnonzero(np.unpackbits(np.frombuffer(b.as_py(), np.uint8), count=n_items)).astype(np.int32) for b in batch.column(1)]
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(rows, pa.list_(pa.int32()))], ["tid", "items"])

    return bits.select("tid", "bits").mapInArrow(work, "tid long, items array<int>")


def _dense(lists: pa.ListArray, n_items: int) -> np.ndarray:
    out = np.zeros((len(lists), n_items), bool)
    flat = lists.flatten().to_numpy(zero_copy_only=False)
    out[np.repeat(np.arange(len(lists)), np.diff(lists.offsets.to_numpy())), flat] = True
    return out


def _by_item(lists: pa.ListArray, n_items: int) -> np.ndarray:
    """A dense block with a row for each item."""
    out = np.zeros((n_items, len(lists)), bool)
    flat = lists.flatten().to_numpy(zero_copy_only=False)
    out[flat, np.repeat(np.arange(len(lists)), np.diff(lists.offsets.to_numpy()))] = True
    return out


def flipped_bits(raw: bytes, tid: int, n_items: int, params: FlipParams, seed: int) -> bytes:
    """One bit vector, by a counter-based generator keyed by (seed, tid)."""
    u = np.random.Generator(np.random.Philox(key=[seed, tid])).random(n_items)
    held = np.unpackbits(np.frombuffer(raw, np.uint8), count=n_items).astype(bool)
    return np.packbits(np.where(held, u < params.p, u >= params.q)).tobytes()


def flip_bitvectors(bits: DataFrame, n_items: int, params: FlipParams, seed: int) -> DataFrame:
    """Bit vectors in, bit vectors out, with a counter-based generator keyed by (seed, tid)."""

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            out = [flipped_bits(raw.as_py(), tid, n_items, params, seed) for tid, raw in zip(batch.column(0).to_pylist(), batch.column(1), strict=True)]
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(out, pa.binary())], ["tid", "bits"])

    return bits.select("tid", "bits").mapInArrow(work, "tid long, bits binary")


#: Draws of a block of tuples: their columns stay in a core's cache.
DRAWS = 65_536
#: Bits of a draw that say how its coin compares with the settings' bars; the others make the gap to the next false item.
LEVEL_BITS = 24


def _mix(z: np.ndarray, spare: np.ndarray | None = None) -> np.ndarray:
    """Bits of 64-bit words scrambled, in place; ``spare`` is room for as many."""
    spare = np.empty_like(z) if spare is None else spare
    for shift, by in ((30, 0xBF58476D1CE4E5B9), (27, 0x94D049BB133111EB)):
        z ^= np.right_shift(z, np.uint64(shift), out=spare)
        z *= np.uint64(by)
    z ^= np.right_shift(z, np.uint64(31), out=spare)
    return z


def _levels_of(settings: Sequence[FlipParams]) -> tuple[float, list[int], list[int]]:
    """The lowest q, and what a draw's level and a held item's coin (32 bits) are compared with for each setting."""
    low = min(s.q for s in settings)
    bars = [round((s.q - low) / (1 - low) * (1 << LEVEL_BITS)) if low < 1 else 0 for s in settings]
    return low, bars, [round(s.p * (1 << 32)) for s in settings]


def _draws(tids: np.ndarray, lists: pa.ListArray, n_items: int, low: float, seed: int) -> Iterator[tuple[np.ndarray, ...]]:
    """(first tuple, cells, levels, held cells, coins of these) in blocks of tuples.

    A cell is tuple * n_items + item, ascending and counted from the block's first tuple. Cells are those of absent items
    whose coins reach ``low``, by geometric gaps; a level says how far beyond. Draws are keyed by (seed, tid) and their number.
    """
    key = _mix(_mix(np.full(1, seed % (1 << 64), np.uint64) + np.uint64(0x9E3779B97F4A7C15)) + tids.astype(np.int64).view(np.uint64))
    step = _mix(key + np.uint64(0xD1B54A32D192ED03)) | np.uint64(1)  # streams of two tuples never run in step
    other = _mix(key ^ np.uint64(0x8CB92BA72F3D8DD7))
    offsets, flat = lists.offsets.to_numpy(), lists.flatten().to_numpy(zero_copy_only=False).astype(np.int64)
    offsets = offsets - offsets[0]
    mean = n_items * (1 - low)
    wide = int(mean + 2 * mean**0.5) + 3
    kind = np.float32 if 1 - low > 0.001 else np.float64  # fine enough for gaps of these lengths
    with np.errstate(divide="ignore"):
        scale = 1 / np.log1p(-(1 - low)) if low < 1 else 0.0
    most = 30 * -scale + 1  # a gap is no longer than this, 29 being above -log of the least draw
    high = max(1, min(DRAWS // wide, len(tids)))
    whole = np.int32 if high * n_items + wide * (min(most, n_items) + 1) < 1 << 31 else np.int64
    room = [np.empty(high * wide, t) for t in (np.uint64, np.uint64, kind, whole, np.int32)]
    for at in range(0, len(tids), high):
        here = slice(at, at + high)
        rows = np.arange(len(tids[here]))
        mine, coins_of = flat[offsets[at] : offsets[min(at + high, len(tids))]], np.diff(offsets[at : min(at + high, len(tids)) + 1])
        owner = np.repeat(rows, coins_of)
        toss = _mix(other[here][owner] + (mine.view(np.uint64) + np.uint64(1)) * step[here][owner]) >> np.uint64(32)
        held = owner * n_items + mine
        cells, levels, begin, first = [], [], np.full(len(rows), -1, np.int64), 1
        while low < 1 and len(rows):
            z, spare, u, place, level = (x[: len(rows) * wide].reshape(len(rows), wide) for x in room)
            np.multiply(np.arange(first, first + wide, dtype=np.uint64)[None, :], step[here][rows][:, None], out=z)
            z += key[here][rows][:, None]
            _mix(z, spare)
            np.copyto(u, np.right_shift(z, np.uint64(LEVEL_BITS), out=spare).view(np.int64), casting="same_kind")
            u += kind(0.5)
            u *= kind(2.0 ** (LEVEL_BITS - 64))
            np.log(u, out=u)
            u *= kind(scale)
            if most > n_items:
                np.minimum(u, kind(n_items), out=u)
            np.copyto(place, u, casting="unsafe")
            place += whole(1)
            place[:, 0] += begin.astype(whole)
            np.cumsum(place, axis=1, out=place)
            last = place[:, -1].astype(np.int64)
            good = np.flatnonzero(place < n_items)
            place += (rows * n_items).astype(whole)[:, None]
            cells.append(place.ravel().take(good))
            np.copyto(level, z, casting="unsafe")
            level &= np.int32((1 << LEVEL_BITS) - 1)
            levels.append(level.ravel().take(good))
            more = last < n_items
            rows, begin, first = rows[more], last[more], first + wide
        cell, level = (cells[0], levels[0]) if len(cells) == 1 else (np.concatenate(x) if x else np.zeros(0, t) for x, t in ((cells, whole), (levels, np.int32)))
        if len(cells) > 1:
            order = np.argsort(cell, kind="stable")
            cell, level = cell[order], level[order]
        yield at, cell, level, held, toss


def _met(cells: np.ndarray, held: np.ndarray) -> np.ndarray:
    """Places among the ascending ``cells`` of those that are held."""
    if not len(cells):
        return np.zeros(0, int)
    at = np.minimum(np.searchsorted(cells, held), len(cells) - 1)
    return at[cells[at] == held]


def _classes(levels: np.ndarray, above: np.ndarray) -> np.ndarray:
    """How many of the ascending bars but the first, which is 0, each level reaches."""
    if len(above) > 127:
        return np.searchsorted(above[1:], levels, side="right")
    out = np.zeros(len(levels), np.int8)
    for bar in above[1:]:
        out += (levels >= bar).view(np.int8)
    return out.astype(np.int64)


def _shown(above: np.ndarray, below: np.ndarray, bars: Sequence[int], keeps: Sequence[int]) -> list[np.ndarray]:
    """For each setting, whether a draw of each class, and after these a held item whose coin reaches so many of ``below``, is seen; last what never is."""
    return [np.concatenate((np.arange(len(above)) >= np.searchsorted(above, b), np.arange(len(below) + 1) <= np.searchsorted(below, k), [False])) for b, k in zip(bars, keeps, strict=True)]


def packed(sizes: np.ndarray, flat: np.ndarray, n_items: int) -> pa.BinaryArray:
    """Lists of ``sizes`` items as bytes, which Spark hands on without a look at each item."""
    kind = kind_of(n_items)
    ends = np.concatenate(([0], np.cumsum(sizes))) * kind.itemsize
    return pa.BinaryArray.from_buffers(pa.binary(), len(sizes), [None, pa.py_buffer(ends.astype(np.int32)), pa.py_buffer(np.ascontiguousarray(flat.astype(kind)))])


def kind_of(n_items: int) -> np.dtype:
    """The numbers that ``packed`` writes."""
    return np.dtype("<u2" if n_items <= 1 << 16 else "<i4")


def unpacked(lists: pa.ListArray | pa.BinaryArray, n_items: int) -> tuple[np.ndarray, np.ndarray]:
    """Where each list begins and ends, from 0 on, and the items of all, of lists or of what ``packed`` made."""
    if isinstance(lists, pa.ListArray):
        offsets = lists.offsets.to_numpy()
        return offsets - offsets[0], lists.flatten().to_numpy(zero_copy_only=False)
    kind, (_, ends, data) = kind_of(n_items), lists.buffers()
    offsets = np.frombuffer(ends, np.int32)[lists.offset : lists.offset + len(lists) + 1] if len(lists) else np.zeros(1, np.int32)
    flat = np.frombuffer(data, np.uint8)[offsets[0] : offsets[-1]] if data is not None else np.zeros(0, np.uint8)
    return (offsets - offsets[0]) // kind.itemsize, flat.view(kind) if flat.ctypes.data % kind.itemsize == 0 else flat.copy().view(kind)


def flip_sparse(arrays: DataFrame, n_items: int, params: FlipParams, seed: int) -> DataFrame:
    """The same distribution in O(length + false items) per tuple: kept items by coin, false ones by geometric gaps.

    For wide universes this is the form to use: with 20,000 items and q = 0.99 it draws 200 numbers for a
    tuple instead of 20,000. Draws are keyed by (seed, tid), so retries repeat them; a block of tuples is drawn at once.
    """
    return flip_lists(arrays, n_items, [params], seed, sparse=True).select("tid", F.col("s0").alias("items"))


def flip_lists(arrays: DataFrame, n_items: int, settings: Sequence[FlipParams], seed: int, sparse: bool = False, as_bytes: bool = False) -> DataFrame:
    """(tid, items, s0, s1, ...): true lists, and the lists seen under each of ``settings``, a coin being tossed once for all of them.

    ``sparse`` draws false items by the sampler; with ``as_bytes`` lists are ``packed``, to be kept and counted.
    """
    names = [f"s{i}" for i in range(len(settings))]
    low, bars, keeps = _levels_of(settings)
    dense_bars = [bar for s in settings for bar in s.thresholds]

    above, below = (np.unique(x) for x in (bars, keeps))
    tables = _shown(above, below, bars, keeps)

    def drawn(batch: pa.RecordBatch) -> list[pa.Array]:
        items, sizes = [[np.zeros(0, np.int32)] for _ in settings], np.zeros((len(settings), len(batch)), np.int64)
        for at, cells, levels, held, toss in _draws(batch.column(0).to_numpy(), batch.column(1), n_items, low, seed):
            code = _classes(levels, above)
            code[_met(cells, held)] = -1  # seen or not by its own coin, beside it
            if (np.diff(held) < 0).any():
                order = np.argsort(held, kind="stable")
                held, toss = held[order], toss[order]
            place = np.searchsorted(cells, held) + np.arange(len(held))
            drawn_ = np.ones(len(cells) + len(held), bool)
            drawn_[place] = False
            all_, codes = np.empty(len(drawn_), cells.dtype), np.empty(len(drawn_), np.int64)
            all_[drawn_], all_[place] = cells, held
            codes[drawn_], codes[place] = code, len(above) + np.searchsorted(below, toss.astype(np.int64), side="right")
            wide = all_.dtype.type(n_items)
            own = (all_ - all_ // wide * wide).astype(np.int32)
            rows = int(all_[-1] // wide) + 1 if len(all_) else 0
            bounds = np.searchsorted(all_, np.arange(rows + 1) * n_items)
            for i, table in enumerate(tables):
                kept = np.flatnonzero(table.take(codes))
                items[i].append(own.take(kept))
                sizes[i, at : at + rows] = np.diff(np.searchsorted(kept, bounds))
        joined = ((n, np.concatenate(x)) for n, x in zip(sizes, items, strict=True))
        return [packed(n, x, n_items) if as_bytes else pa.ListArray.from_arrays(pa.array(np.concatenate(([0], np.cumsum(n))), pa.int32()), pa.array(x, pa.int32())) for n, x in joined]

    def tossed(batch: pa.RecordBatch) -> list[pa.Array]:
        held = _by_item(batch.column(1), n_items)
        seen = [np.empty_like(held) for _ in settings]
        for rows, columns, under in tossed_below(seed, batch.column(0).to_pylist(), np.arange(n_items), dense_bars):
            at = _block(rows, columns)
            true = held[at]
            for one, kept, low in zip(seen, under[::2], under[1::2], strict=True):
                one[at] = np.where(true, kept, ~low)
        return [bytes_of(_lists(np.ascontiguousarray(one.T))) for one in seen]

    def bytes_of(lists: pa.ListArray) -> pa.Array:
        if not as_bytes:
            return lists
        offsets, flat = unpacked(lists, n_items)
        return packed(np.diff(offsets), flat, n_items)

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches if sparse else _steps(batches, n_items * (1 + len(settings))):
            yield pa.RecordBatch.from_arrays([batch.column(0), bytes_of(batch.column(1)), *(drawn if sparse else tossed)(batch)], ["tid", "items", *names])

    kind = "binary" if as_bytes else "array<int>"
    return arrays.select("tid", "items").mapInArrow(work, ", ".join(["tid long", *(f"{n} {kind}" for n in ("items", *names))]))


#: Numbers of a block that ``added`` brings to one place, and draws that are counted at once.
BLOCK, TALLY = 1 << 14, 4_000_000


def added(df: DataFrame, totals: Callable[[Iterator[pa.RecordBatch]], np.ndarray | None], size: int) -> np.ndarray:
    """The sum over tasks of the arrays of ``size`` numbers that ``totals`` makes of their batches; they are shuffled as blocks, not as rows."""
    block = BLOCK

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        total = totals(batches)
        for at in range(0, 0 if total is None else size, block):
            if total[at : at + block].any():
                yield pa.RecordBatch.from_arrays([pa.array([at // block], pa.int32()), pa.array([total[at : at + block].astype(np.int64).tobytes()], pa.binary())], ["part", "n"])

    def plus(key: tuple, rows: pa.Table) -> pa.Table:
        n = sum(np.frombuffer(x.as_py(), np.int64) for x in rows["n"])
        return pa.table({"part": pa.array([key[0].as_py()], pa.int32()), "n": pa.array([n.tobytes()], pa.binary())})

    out = np.zeros(size, np.int64)
    found = df.mapInArrow(work, "part int, n binary").groupBy("part").applyInArrow(plus, "part int, n binary").toArrow()
    for part, n in zip(found["part"].to_pylist(), found["n"].to_pylist(), strict=True):
        out[part * block : (part + 1) * block] = np.frombuffer(n, np.int64)
    return out


def flip_sparse_counts(arrays: DataFrame, n_items: int, settings: Sequence[FlipParams], seed: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(true, seen, kept): each item's count in the true lists, and by setting how often ``flip_lists`` shows it at all and where it is true.

    Every tuple's false items are drawn, once for all settings; no distorted table is made or kept.
    """
    low, bars, keeps = _levels_of(settings)
    # draws and coins fall between ascending bars; a setting's count is the sum of the classes beyond, or before, its own
    above, below = (np.unique(x) for x in (bars, keeps))
    parts = len(above) + len(below) + 1

    def totals(batches: Iterator[pa.RecordBatch]) -> np.ndarray:
        out, room, filled = np.zeros(parts * n_items, np.int64), np.empty(max(TALLY, n_items), np.int64), 0

        def count(keys: np.ndarray) -> None:
            found = np.bincount(keys)
            out[: len(found)] += found

        for batch in batches:
            for _, cells, levels, held, toss in _draws(batch.column(0).to_numpy(), batch.column(1), n_items, low, seed):
                wide, kinds = cells.dtype.type(n_items), _classes(levels, above)
                kinds *= n_items
                if filled + len(cells) > len(room):
                    count(room[:filled])
                    filled = 0
                key = room[filled : filled + len(cells)] if len(cells) <= len(room) else np.empty(len(cells), np.int64)
                np.add(kinds, cells - cells // wide * wide, out=key)
                np.subtract.at(out, key[_met(cells, held)], 1)
                if len(cells) <= len(room):
                    filled += len(cells)
                else:
                    count(key)
                np.add.at(out, held % n_items + (len(above) + np.searchsorted(below, toss.astype(np.int64), side="right")) * n_items, 1)
        count(room[:filled])
        return out

    found = added(arrays.select("tid", "items"), totals, parts * n_items).reshape(parts, n_items)
    false, coins_ = found[: len(above)], found[len(above) :]
    kept = np.array([coins_[: np.searchsorted(below, k) + 1].sum(0) for k in keeps])
    return coins_.sum(0), np.array([false[np.searchsorted(above, bar) :].sum(0) for bar in bars]) + kept, kept


def expected_length(length: float, n_items: int, p: float, q: float) -> float:
    """Mean length of a tuple after distortion."""
    return length * p + (n_items - length) * (1 - q)


def choose_layout(length: float, n_items: int, p: float, q: float) -> str:
    """``lists`` or ``bits``, whichever is expected to take fewer bytes for the distorted table."""
    return "lists" if 4 * expected_length(length, n_items, p, q) < n_items / 8 else "bits"
