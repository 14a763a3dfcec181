"""Parameters of the distortion channel, presets, and the library's own errors."""

from __future__ import annotations

from dataclasses import dataclass
from fractions import Fraction
from math import floor, gcd


class CandidateBudgetExceeded(RuntimeError):
    """More candidates or items than may be held on the driver or broadcast."""


#: Itemsets of one level, and items of a universe, that may be held on the driver and broadcast.
CANDIDATE_BUDGET = 2_000_000
ITEM_BUDGET = 2_000_000
#: Items of a universe that are broadcast without asking; Spark chooses how to join more.
ITEMS_BROADCAST = 500_000
#: Bits of the portable coin.
COIN_BITS = 52


def exact(x: float | str | Fraction) -> Fraction:
    """The decimal that was written, not the nearest binary number."""
    return x if isinstance(x, Fraction) else Fraction(str(x))


@dataclass(frozen=True)
class FlipParams:
    """A present item is kept with probability ``p``, an absent one with ``q``; known to the miner, unlike the coin's seed.

    ``p + q = 1`` loses all information and is refused; ``p + q < 1`` (the mirror regime) needs ``allow_negative``.
    """

    p: float
    q: float
    allow_negative: bool = False

    def __post_init__(self) -> None:
        for name in ("p", "q"):
            if not 0 <= getattr(self, name) <= 1:
                raise ValueError(f"{name} = {getattr(self, name)} is no probability")
        if self.d == 0:
            raise ValueError("p + q = 1 cannot be inverted")
        if self.d < 0 and not self.allow_negative:
            raise ValueError("p + q < 1; pass allow_negative=True if this is meant")

    @property
    def d(self) -> Fraction:
        return exact(self.p) + exact(self.q) - 1

    @property
    def thresholds(self) -> tuple[int, int]:
        """Coins below the first keep a present item; coins from the second on turn an absent one present."""
        return floor(self.p * 2**COIN_BITS), floor(self.q * 2**COIN_BITS)

    @property
    def integers(self) -> tuple[int, int, int]:
        """(a, Q, b) with 1 - q = a / Q and p + q - 1 = b / Q in lowest terms."""
        miss, d = 1 - exact(self.q), self.d
        scale = miss.denominator * d.denominator // gcd(miss.denominator, d.denominator)
        a, b = int(miss * scale), int(d * scale)
        common = gcd(gcd(a, b), scale)
        return a // common, scale // common, b // common


#: The usual setting of the symmetric scheme, the recommended one, and the candidates of both regimes.
SYM_DEFAULT = FlipParams(0.9, 0.9)
ASYM_DEFAULT = FlipParams(0.4, 0.98)
CANDIDATES_DENSE = ((0.6, 0.96), (0.5, 0.97), (0.4, 0.98), (0.3, 0.99))
CANDIDATES_SPARSE = ((0.3, 0.99), (0.4, 0.99), (0.4, 0.98), (0.5, 0.98), (0.5, 0.97), (0.6, 0.98), (0.6, 0.97), (0.6, 0.96), (0.7, 0.97), (0.7, 0.96), (0.8, 0.96))
