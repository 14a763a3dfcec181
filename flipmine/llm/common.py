"""Pieces that several operators of this subpackage share: shared-folder tables and vectorised words."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc

from ..sources.shared import shared_dir, stored

__all__ = ["mix64", "shared_dir", "slices", "stored", "words_hashed"]

#: The bytes that separate words, and the odd multipliers of the word and shingle hashes.
SPACE_BYTES = (0x20, 0x09, 0x0A, 0x0B, 0x0C, 0x0D)
WORD_MULTIPLIER = np.uint64(0x9E3779B97F4A7C15)
MIX_A = np.uint64(0xBF58476D1CE4E5B9)
MIX_B = np.uint64(0x94D049BB133111EB)

_LOWER = np.arange(256, dtype=np.uint8)
_LOWER[65:91] += 32
_IN_WORD = np.ones(256, dtype=bool)
_IN_WORD[list(SPACE_BYTES)] = False


def mix64(x: np.ndarray) -> np.ndarray:
    """A bijective finaliser on 64-bit values (wraps around on purpose)."""
    x = (x ^ (x >> np.uint64(30))) * MIX_A
    x = (x ^ (x >> np.uint64(27))) * MIX_B
    return x ^ (x >> np.uint64(31))


def words_hashed(texts: pa.Array) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Words (runs of bytes other than white space, A-Z lower-cased) of all texts at once.

    Returns 64-bit hashes of the words in order, their lengths in bytes, and for text ``i`` the
    range ``bounds[i]:bounds[i + 1]`` of its words. Null texts have no words.
    """
    texts = texts.cast(pa.large_string()).fill_null("")
    offsets = np.frombuffer(texts.buffers()[1], dtype=np.int64)[texts.offset : texts.offset + len(texts) + 1]
    if len(texts) == 0 or offsets[-1] == offsets[0]:
        return np.zeros(0, np.uint64), np.zeros(0, np.int64), np.zeros(len(texts) + 1, np.int64)
    raw = np.frombuffer(texts.buffers()[2], dtype=np.uint8)[offsets[0] : offsets[-1]]
    cuts = offsets - offsets[0]
    inside = np.concatenate(([False], _IN_WORD[raw], [False]))
    first, last = inside[1:-1] & ~inside[:-2], inside[1:-1] & ~inside[2:]
    edges = cuts[(cuts > 0) & (cuts < len(raw))]
    first[edges] |= inside[1:-1][edges]
    last[edges - 1] |= inside[1:-1][edges - 1]
    starts, ends = np.flatnonzero(first), np.flatnonzero(last) + 1
    lengths = ends - starts
    bounds = np.searchsorted(starts, cuts)
    if len(starts) == 0:
        return np.zeros(0, np.uint64), lengths, bounds
    letters = _LOWER[raw[inside[1:-1]]].astype(np.uint64)
    letters += np.uint64(1)
    heads = np.concatenate(([0], np.cumsum(lengths)[:-1]))
    place = np.arange(len(letters)) - np.repeat(heads, lengths)
    with np.errstate(over="ignore"):
        powers = np.cumprod(np.full(int(lengths.max()), WORD_MULTIPLIER, dtype=np.uint64))
        sums = np.add.reduceat(letters * powers[place], heads)
        return mix64(sums ^ lengths.astype(np.uint64)), lengths, bounds


def slices(texts: pa.Array, most_bytes: int = 1_000_000) -> Iterator[tuple[int, int]]:
    """Ranges of rows that hold about ``most_bytes`` of text each, so that buffers stay small; every row is in one."""
    sizes = np.cumsum(np.asarray(pc.binary_length(texts.cast(pa.large_string())).fill_null(0), dtype=np.int64) + 1)
    at = 0
    while at < len(texts):
        before = sizes[at - 1] if at else 0
        to = max(at + 1, int(np.searchsorted(sizes, before + most_bytes)))
        yield at, min(to, len(texts))
        at = to
