"""Set similarities as exact ratios, and every bound that follows from them.

A similarity is ``num / den`` of integers made from the overlap ``o`` and the sizes ``nr, ns``. The quotient as a
double is its key: below 2^26 equal ratios have equal keys and different ones differ, so keys group, order
and compare exactly. Cosine's key is its square. All methods take and return Columns, or numbers alike; keys and ratios
take arrays too.
"""

from __future__ import annotations

import math
from dataclasses import dataclass
from fractions import Fraction

import numpy as np
from pyspark.sql import Column, functions as F


def _least(a, b):
    return F.least(a, b) if isinstance(a, Column) or isinstance(b, Column) else np.minimum(a, b) if isinstance(a, np.ndarray) else min(a, b)


def _greatest(a, b):
    return F.greatest(a, b) if isinstance(a, Column) or isinstance(b, Column) else np.maximum(a, b) if isinstance(a, np.ndarray) else max(a, b)


def _quotient(num, den):
    if isinstance(num, Column) or isinstance(den, Column):
        num = num if isinstance(num, Column) else F.lit(num)
        return num.cast("double") / den
    return num / den


def _ceil_ratio(num, den):
    """Least integer of at least ``num / den``, in integers."""
    if isinstance(num, Column) or isinstance(den, Column):
        return F.floor((num + den - 1) / den)
    return -(-num // den)


@dataclass(frozen=True)
class SetSimilarity:
    """One of jaccard, overlap, dice, cosine, tversky; ``alpha`` weighs the size of r, ``1 - alpha`` that of s."""

    name: str
    alpha: Fraction = Fraction(1, 2)

    @property
    def symmetric(self) -> bool:
        return self.name != "tversky" or self.alpha == Fraction(1, 2)

    def ratio(self, o, nr, ns):
        """Numerator and denominator."""
        a, b = self.alpha.numerator, self.alpha.denominator
        return {
            "jaccard": lambda: (o, nr + ns - o),
            "overlap": lambda: (o, _greatest(nr, ns)),
            "dice": lambda: (o * 2, nr + ns),
            "cosine": lambda: (o * o, nr * ns),
            "tversky": lambda: (o * b, nr * a + ns * (b - a)),
        }[self.name]()

    def key(self, o, nr, ns):
        return _quotient(*self.ratio(o, nr, ns))

    def value(self, key):
        """The similarity of a key."""
        if self.name != "cosine":
            return key
        return F.sqrt(key) if isinstance(key, Column) else math.sqrt(key)

    def key_of(self, theta: float | str | Fraction) -> float:
        """The key from which similarities reach a threshold."""
        t = Fraction(str(theta))
        return float(t * t if self.name == "cosine" else t)

    def least(self, seen, nr, ns):
        """Key if nothing more is shared."""
        return self.key(seen, nr, ns)

    def most(self, seen, rest_r, rest_s, nr, ns):
        """Key if all that is left of the shorter rest is shared; rests are those of a merge of both in order."""
        return self.key(seen + _least(rest_r, rest_s), nr, ns)

    def min_overlap(self, theta: float | str | Fraction, n, side: str = "r", bounds: str = "tight"):
        """Shared elements that a set of ``n`` needs, whatever its partner, to reach ``theta`` (> 0)."""
        t = Fraction(str(theta))
        alpha = self.alpha if side == "r" else 1 - self.alpha
        share = {
            "jaccard": t, "overlap": t, "cosine": t * t,
            "dice": t / 2 if bounds == "paper" else t / (2 - t),
            "tversky": t * alpha if bounds == "paper" else (t * alpha / (1 - t * (1 - alpha)) if alpha else Fraction(0)),
        }[self.name]
        return _greatest(_ceil_ratio(n * share.numerator, share.denominator), F.lit(1) if isinstance(n, Column) else 1)

    def prefix_len(self, theta: float | str | Fraction, n, side: str = "r", bounds: str = "tight"):
        """Elements of which one at least is shared with any partner at ``theta``."""
        return n - self.min_overlap(theta, n, side, bounds) + 1

    def cap(self, position, n, side: str = "r", bounds: str = "tight"):
        """Best key of a pair whose first shared element stands at ``position`` (from 1) of a set of ``n``."""
        m = n - position + 1
        a, b = (self.alpha if side == "r" else 1 - self.alpha).as_integer_ratio()
        if self.name in ("jaccard", "overlap", "cosine"):
            return _quotient(m, n)
        if self.name == "dice":
            return _least(_quotient(m * 2, n), F.lit(1.0) if isinstance(n, Column) else 1.0) if bounds == "paper" else _quotient(m * 2, n + m)
        if bounds == "paper":
            if not a:
                return F.lit(1.0) if isinstance(n, Column) else 1.0
            return _least(_quotient(m * b, n * a), F.lit(1.0) if isinstance(n, Column) else 1.0)
        return _quotient(m * b, n * a + m * (b - a))

    def least_share(self, key: float, side: str = "r", bounds: str = "tight") -> float:
        """Share of a set that any partner of this key or more has in common with it."""
        a = float(self.alpha if side == "r" else 1 - self.alpha)
        if self.name == "dice":
            return key / 2 if bounds == "paper" else key / (2 - key)
        if self.name == "tversky":
            return key * a if bounds == "paper" else key * a / (1 - key * (1 - a)) if a else 0.0
        return key

    def needed(self, key: float, nr: np.ndarray, ns: np.ndarray) -> np.ndarray:
        """Shared elements, not rounded, of sets of these sizes at a key."""
        a, key = np.float32(self.alpha), nr.dtype.type(key)
        return {
            "jaccard": lambda: nr * (key / (1 + key)) + ns * (key / (1 + key)), "overlap": lambda: np.maximum(nr, ns) * key,
            "dice": lambda: nr * (key / 2) + ns * (key / 2), "cosine": lambda: np.sqrt(nr * key) * np.sqrt(ns),
            "tversky": lambda: nr * (key * a) + ns * (key * (1 - a)),
        }[self.name]()

    def prefix_at_most(self, key: float, n: Column, side: str = "r", bounds: str = "tight") -> Column:
        """No fewer places than those whose cap reaches ``key``; rounding may add one or two."""
        return F.least(n, n - F.floor(n * F.lit(self.least_share(key, side, bounds) * (1 - 1e-12))) + 2).cast("int")

    def rest_at_most(self, key: float, n: Column, side: str = "r", bounds: str = "tight") -> Column:
        """No fewer elements than there are behind the places whose cap reaches ``key``."""
        return F.least(n, F.ceil(n * F.lit(self.least_share(key, side, bounds) * (1 + 1e-12)))).cast("bigint")

    def size_range(self, theta: float | str | Fraction, nr):
        """Least and greatest size of a partner of r at ``theta``, as doubles; null or infinity where there is no bound."""
        t, a = Fraction(str(theta)), self.alpha
        low, high = {
            "jaccard": lambda: (t, 1 / t), "overlap": lambda: (t, 1 / t), "cosine": lambda: (t * t, 1 / (t * t)),
            "dice": lambda: (t / (2 - t), (2 - t) / t),
            "tversky": lambda: (t * a / (1 - t * (1 - a)) if a else Fraction(0), (1 - t * a) / (t * (1 - a)) if a < 1 else None),
        }[self.name]()
        most = math.inf if high is None else float(high)
        return nr * float(low), nr * most


def jaccard() -> SetSimilarity:
    return SetSimilarity("jaccard")


def overlap() -> SetSimilarity:
    return SetSimilarity("overlap")


def dice() -> SetSimilarity:
    return SetSimilarity("dice")


def cosine() -> SetSimilarity:
    return SetSimilarity("cosine")


def tversky(alpha: float | str | Fraction) -> SetSimilarity:
    return SetSimilarity("tversky", Fraction(str(alpha)))


def edit_similarity(a: Column, b: Column) -> Column:
    """1 - edit distance / longer length; 1 for two empty strings."""
    longest = F.greatest(F.length(a), F.length(b))
    return F.when(longest == 0, F.lit(1.0)).otherwise(1 - F.levenshtein(a, b) / longest)


def dot(a: Column, b: Column) -> Column:
    return F.aggregate(F.zip_with(a, b, lambda x, y: x.cast("double") * y.cast("double")), F.lit(0.0), lambda s, x: s + x)


def vector_cosine(a: Column, b: Column) -> Column:
    return dot(a, b) / F.sqrt(dot(a, a) * dot(b, b))
