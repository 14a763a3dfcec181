"""Algebra of the distortion channel: transition matrices, their inverses in closed form, and weights of estimates."""

from __future__ import annotations

from functools import lru_cache
from math import comb

import numpy as np

from ..config import FlipParams, exact


def single(p: float, q: float) -> np.ndarray:
    """Columns: true 1, true 0; rows: seen 1, seen 0."""
    return np.array([[p, 1 - q], [1 - p, q]])


def pattern_matrix(n: int, p: float, q: float) -> np.ndarray:
    """2**n square, Kronecker power of ``single``; pattern codes count down from all ones."""
    out = np.ones((1, 1))
    for _ in range(n):
        out = np.kron(out, single(p, q))
    return out


@lru_cache(maxsize=256)
def weight_matrix(n: int, p: float, q: float) -> np.ndarray:
    """Entry (i, j): a tuple with j of the n items is seen with i of them.

    k of the j kept, the other j - k lost, i - k of the absent ones made up. Every column sums to 1.
    """
    out = np.zeros((n + 1, n + 1))
    for i in range(n + 1):
        for j in range(n + 1):
            out[i, j] = sum(comb(j, k) * p**k * (1 - p) ** (j - k) * comb(n - j, i - k) * (1 - q) ** (i - k) * q ** (n - j - i + k) for k in range(max(0, i + j - n), min(i, j) + 1))
    return out


def support_row(n: int, p: float, q: float) -> list[float]:
    """Weights of the seen weight classes 0..n in the estimate of the all-ones count: the last row of the inverse, in closed form."""
    d = p + q - 1
    return [(q / d) ** w * (-(1 - q) / d) ** (n - w) for w in range(n + 1)]


def condition(n: int, p: float, q: float, norm: int = 2) -> float:
    """How much the inversion magnifies relative errors, in a norm; it grows steeply with n and as p falls."""
    return float(np.linalg.cond(weight_matrix(n, p, q), norm))


def solve_patterns(counts: np.ndarray, p: float, q: float) -> np.ndarray:
    """True pattern counts from seen ones (axis of length 2**n last), item by item: n 2x2 solves instead of a 2**n inverse."""
    counts = np.asarray(counts, float)
    n = counts.shape[-1].bit_length() - 1
    if counts.shape[-1] != 1 << n:
        raise ValueError("the number of patterns is no power of two")
    inverse = np.linalg.inv(single(p, q))
    out = counts.reshape(*counts.shape[:-1], *([2] * n))
    for axis in range(counts.ndim - 1, counts.ndim - 1 + n):
        out = np.moveaxis(np.tensordot(inverse, out, axes=(1, axis)), 0, axis)
    return out.reshape(counts.shape)


def numerator_terms(n: int, params: FlipParams) -> list[int]:
    """Integer weights by subset size 0..n; the estimate of an n-itemset is their sum over ``b ** n``."""
    a, scale, _ = params.integers
    return [(-a) ** (n - s) * scale**s for s in range(n + 1)]


def least_numerator(n: int, params: FlipParams, support: float | str, dbsize: int, strict: bool = False) -> int:
    """The least numerator of an n-itemset that is frequent; exact integers, so engines cannot disagree on ties."""
    share, b = exact(support), params.integers[2]
    bound = share.numerator * dbsize * b**n
    at = -(-bound // share.denominator)
    return at + 1 if strict and at * share.denominator == bound else at


def variance(classes: list[float], p: float, q: float) -> float:
    """Variance of the n-itemset estimate, given the true numbers of tuples with w = 0..n of the items."""
    n, d = len(classes) - 1, p + q - 1
    spread = sum(t * (p * (1 - p) + d * d) ** w * (q * (1 - q)) ** (n - w) for w, t in enumerate(classes))
    return spread / d ** (2 * n) - classes[-1]
