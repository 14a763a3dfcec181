"""The portable coin for blocks of tuples and items at once: MD5 over columns of 32-bit words.

A coin is the first 52 bits of the digest of ``seed|tid|item`` (``seed|item`` where the tid is null). The texts of a block
differ in a few words only: what comes before the item's digits is worked out once for a tuple, and all else is
arithmetic on columns, a quarter of a digest's cost one by one.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator, Sequence
from functools import partial
from hashlib import md5
from math import sin

import numpy as np

#: Cells of a block: its columns stay in cache, and are long enough for a call to each operation.
CELLS = 65_536
#: A text that fills one block of the digest; longer ones are digested one by one.
LONGEST = 55

_U = [np.array(i, np.uint32) for i in range(33)]
_SINES = np.array([int(abs(sin(i + 1)) * 2**32) for i in range(64)], np.uint32)
_TURNS = [7, 12, 17, 22] * 4 + [5, 9, 14, 20] * 4 + [4, 11, 16, 23] * 4 + [6, 10, 15, 21] * 4
_WORD = [i if i < 16 else (5 * i + 1) % 16 if i < 32 else (3 * i + 5) % 16 if i < 48 else 7 * i % 16 for i in range(64)]
_START = np.array([0x67452301, 0xEFCDAB89, 0x98BADCFE, 0x10325476], np.uint32)


def _by_length(texts: list[bytes]) -> Iterator[tuple[np.ndarray, np.ndarray]]:
    """(places, characters) of the texts of each length."""
    lengths = np.fromiter(map(len, texts), np.int64, len(texts))
    for n in np.unique(lengths):
        at = np.flatnonzero(lengths == n)
        yield at, np.frombuffer(b"".join(texts[i] for i in at), np.uint8).reshape(len(at), n)


def _mixed(i: int, b: np.ndarray, c: np.ndarray, d: np.ndarray, f: np.ndarray, e: np.ndarray) -> None:
    """What step ``i`` of the digest makes of three words, in ``f``; ``e`` goes from one step to the next."""
    if i < 16:
        np.bitwise_xor(c, d, out=f)
        np.bitwise_and(f, b, out=f)
        np.bitwise_xor(f, d, out=f)
    elif i < 32:
        np.bitwise_xor(b, c, out=f)
        np.bitwise_and(f, d, out=f)
        np.bitwise_xor(f, c, out=f)
    elif i < 48:
        if i % 2:
            np.bitwise_xor(e, b, out=f)  # the two words of the step before are c and d now
        else:
            np.bitwise_xor(b, c, out=e)
            np.bitwise_xor(e, d, out=f)
    else:
        np.bitwise_not(d, out=f)
        np.bitwise_or(f, b, out=f)
        np.bitwise_xor(f, c, out=f)


def _words(chars: np.ndarray, at: int, end: bool) -> np.ndarray:
    """(16, rows): characters from place ``at`` on as the digest's words, with the mark of the end and the length if asked for."""
    rows = np.zeros((len(chars), 64), np.uint8)
    stop = at + chars.shape[1]
    rows[:, at:stop] = chars
    if end:
        rows[:, stop] = 0x80
        rows[:, 56:] = np.frombuffer((8 * stop).to_bytes(8, "little"), np.uint8)
    return np.ascontiguousarray(rows.view("<u4").T).astype(np.uint32)


def coins(seed: int, tids: Sequence[int | None], items: np.ndarray) -> Iterator[tuple[np.ndarray, np.ndarray, np.ndarray]]:
    """(rows, columns, u) in blocks: coin ``u[i, j]`` (64 bits unsigned) of the item ``items[rows[i]]`` and the tuple ``tids[columns[j]]``."""
    for rows, columns, _, digests in _blocks(seed, tids, items):
        yield rows, columns, digests(True)


def below(seed: int, tids: Sequence[int | None], items: np.ndarray, bars: Sequence[int]) -> Iterator[tuple[np.ndarray, np.ndarray, list[np.ndarray]]]:
    """(rows, columns, under) in blocks: whether each coin is below each of ``bars``.

    The first 32 bits of a coin say so, unless they are the bar's own: these coins are tossed one by one, to their last bit.
    """
    for rows, columns, coin, digests in _blocks(seed, tids, items):
        top, under = digests(False), []
        for bar in bars:
            high, low = divmod(bar, 1 << 20)
            if high >> 32:
                under.append(np.ones(top.shape, bool))
                continue
            one = top < np.uint32(high)
            if low:
                tie = top == np.uint32(high)
                if tie.any():
                    for i, j in np.argwhere(tie):
                        one[i, j] = coin(rows[i], columns[j]) < bar
            under.append(one)
        yield rows, columns, under


def _blocks(seed: int, tids: Sequence[int | None], items: np.ndarray) -> Iterator[tuple[np.ndarray, np.ndarray, Callable, Callable]]:
    """(rows, columns, coin, digests) by block: the coin of one cell, and the coins of all or (False) their first 32 bits."""
    heads = [f"{seed}|{t}|".encode() if t is not None else f"{seed}|".encode() for t in tids]
    texts = [str(i).encode() for i in items.tolist()]
    tails = list(_by_length(texts))
    coin = lambda i, j: int(md5(heads[j] + texts[i]).hexdigest()[:13], 16)
    for columns, head in _by_length(heads):
        for rows, tail in tails:
            at, n = head.shape[1], tail.shape[1]
            if at + n > LONGEST:
                u = np.array([[coin(i, j) for j in columns] for i in rows], np.uint64)
                yield rows, columns, coin, lambda whole, u=u: u if whole else (u >> np.uint64(20)).astype(np.uint32)
                continue
            before, after = _words(head, 0, False), _words(tail, at, True)
            wide = min(len(columns), max(4096, CELLS // len(rows)))
            high = max(1, CELLS // wide)
            for x in range(0, len(columns), wide):
                for y in range(0, len(rows), high):
                    yield rows[y : y + high], columns[x : x + wide], coin, partial(_digests, before[:, x : x + wide], after[:, y : y + high], at, n)


def _digests(before: np.ndarray, after: np.ndarray, at: int, n: int, whole: bool) -> np.ndarray:
    """The first 52 bits, or 32 if not ``whole``, of the digests of each column of ``before`` followed by each of ``after``, whose ``n`` characters begin at ``at``."""
    shape = after.shape[1], before.shape[1]
    own, shared = at // 4, range(at // 4, (at + n) // 4 + 1)
    state = [np.full((1, shape[1]), x, np.uint32) for x in _START]
    e, f, g = (np.empty_like(state[0]) for _ in range(3))
    for i in range(64 if whole else 61):  # the first word is not touched after that
        if i == own:
            state = [np.array(np.broadcast_to(x, shape), order="C") for x in state]
            e, f, g = (np.empty(shape, np.uint32) for _ in range(3))
        a, b, c, d = state
        _mixed(i, b, c, d, f, e)
        np.add(f, a, out=f)
        w, k = _WORD[i], _SINES[i : i + 1]
        if 4 * w < at:
            np.add(f, before[w][None, :] + k, out=f)
            if w in shared:
                np.add(f, after[w][:, None], out=f)
        else:
            np.add(f, after[w][:, None] + k if w in shared else (after[w, :1] + k)[0], out=f)
        np.left_shift(f, _U[_TURNS[i]], out=g)
        np.right_shift(f, _U[32 - _TURNS[i]], out=f)
        np.bitwise_or(f, g, out=f)
        np.add(f, b, out=a)
        state = [d, a, b, c]
    top = (state[0 if whole else 1] + _START[0]).byteswap()
    return (top.astype(np.uint64) << np.uint64(20)) | ((state[1] + _START[1]).byteswap() >> _U[12]) if whole else top
