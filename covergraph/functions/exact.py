"""Exact thresholds: the coverage share is a fraction of integers."""

from __future__ import annotations

import math
from dataclasses import dataclass
from fractions import Fraction

import numpy as np

#: Modulus and multipliers of the portable hash; any engine with 64-bit integers gives the same numbers.
PRIME, BY_ID, BY_ROUND, BY_SEED = 2147483647, 48271, 16807, 69621
#: Rounds from which draws take their numbers, so that they share none with the orders.
DRAWS = 1000


@dataclass(frozen=True)
class Share:
    """Coverage share num/den in [0, 1]."""

    num: int
    den: int

    @classmethod
    def of(cls, x: str | float | tuple[int, int] | Share) -> Share:
        if isinstance(x, Share):
            return x
        f = Fraction(*x) if isinstance(x, tuple) else Fraction(str(x))
        if not 0 <= f <= 1:
            raise ValueError("a coverage share lies between 0 and 1")
        return cls(f.numerator, f.denominator)

    def need(self, n: int) -> int:
        """Points that each of n nodes must cover."""
        return -(-self.num * (n - 1) // self.den) if n > 0 else 0

    def clique(self, times: int = 2) -> int:
        """Smallest integer at least times / (1 - share): 2 for exact ownership, 4 for sampled."""
        if self.num == self.den:
            raise ValueError("clique peeling needs a share below 1")
        return -(-times * self.den // (self.den - self.num))

    def sample(self, n: int, delta: float) -> int:
        """Draws that make sampled ownership right for all n points with probability 1 - delta."""
        return math.ceil(16 * math.log(max(n, 2) / delta) * self.den / (self.den - self.num))

    def keeps(self, owned, n: int):
        return owned * self.den <= (self.den - self.num) * n

    def keeps_sampled(self, owned, w: int):
        return 2 * self.den * owned <= (self.den - self.num) * w

    def rounds(self, n: int) -> int:
        return math.ceil(math.log(max(n, 2)) / math.log(4 / 3)) + 1

    def __float__(self) -> float:
        return float(Fraction(self.num, self.den))

    def __str__(self) -> str:
        return str(float(self))


def portable_hash(x, turn: int, seed: int):
    """A number below PRIME for numbers and columns alike. Two squarings with a linear step between them: orders of
    different rounds and seeds are not shifts of each other."""
    z = (x % PRIME * BY_ID + (BY_ROUND * turn + BY_SEED * seed) % PRIME) % PRIME
    z = (z * z % PRIME * BY_ID + 11) % PRIME
    return z * z % PRIME


def draw(i, turn: int, seed: int, n):
    """Draw i of a round's sample: a number below n, with replacement. Two hashes make one, so n may exceed PRIME."""
    return (portable_hash(2 * i, turn + DRAWS, seed) * PRIME + portable_hash(2 * i + 1, turn + DRAWS, seed)) % n
