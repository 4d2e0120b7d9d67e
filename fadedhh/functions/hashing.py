"""Row hashes of the sketch: one column number per row for each item.

Profiles: ``mod31`` and ``mod61`` are pairwise independent (a x + b modulo a Mersenne prime); mod31 fits long
arithmetic in any engine but folds keys modulo 2**31 - 1, mod61 runs in the numpy kernel. ``xx64`` is the JVM's
seeded 64-bit hash: fast, not formally pairwise independent.
"""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
from pyspark.sql import Column
from pyspark.sql import functions as F

P31 = (1 << 31) - 1
P61 = (1 << 61) - 1


def _draw(seed: int, k: int) -> int:
    """The k-th 64-bit number of a seeded counter generator."""
    x = (seed * 0x9E3779B97F4A7C15 + (k + 1) * 0xD1B54A32D192ED03) & (2**64 - 1)
    for shift, factor in ((30, 0xBF58476D1CE4E5B9), (27, 0x94D049BB133111EB)):
        x = ((x ^ (x >> shift)) * factor) & (2**64 - 1)
    return x ^ (x >> 31)


@dataclass(frozen=True)
class RowHashes:
    d: int
    w: int
    seed: int = 1
    profile: str = "mod31"

    def coefficients(self, prime: int = P31) -> list[tuple[int, int]]:
        return [(1 + _draw(self.seed, 2 * j) % (prime - 1), _draw(self.seed, 2 * j + 1) % prime) for j in range(self.d)]

    def columns(self, item: Column) -> list[Column]:
        """Spark columns (mod31, xx64)."""
        if self.profile == "xx64":
            return [F.pmod(F.xxhash64(item, F.lit(_draw(self.seed, j) >> 1)), F.lit(self.w)).cast("int") for j in range(self.d)]
        if self.profile != "mod31":
            raise ValueError(f"profile {self.profile} has no column form")
        x = F.pmod(item, F.lit(P31))
        return [(((F.lit(a) * x + F.lit(b)) % F.lit(P31)) % F.lit(self.w)).cast("int") for a, b in self.coefficients()]

    def sql(self, item: str = "item") -> list[str]:
        """The mod31 columns as SQL text."""
        return [f"((({a}::BIGINT * ((({item} % {P31}) + {P31}) % {P31}) + {b}::BIGINT) % {P31}) % {self.w})::INTEGER" for a, b in self.coefficients()]

    def arrays(self, item: np.ndarray) -> np.ndarray:
        """Column numbers, one line per sketch row (mod31, mod61)."""
        if self.profile == "mod31":
            x = item % P31
            return np.stack([((a * x + b) % P31) % self.w for a, b in self.coefficients()])
        if self.profile == "mod61":
            x = (item.astype(object) % P61).astype(np.uint64) if len(item) and (item.min() < 0 or item.max() >= P61) else item.astype(np.uint64)
            return np.stack([_affine61(a, x, b) % np.uint64(self.w) for a, b in self.coefficients(P61)]).astype(np.int64)
        raise ValueError(f"profile {self.profile} is computed in the JVM")


def _affine61(a: int, x: np.ndarray, b: int) -> np.ndarray:
    """(a x + b) mod 2**61 - 1 with 64-bit words: halves of 31 bits, folded by 2**61 = 1."""
    u = np.uint64
    low31, low30 = u((1 << 31) - 1), u((1 << 30) - 1)
    ah, al = u(a >> 31), u(a & ((1 << 31) - 1))
    xh, xl = x >> u(31), x & low31
    mid = ah * xl + al * xh
    total = ((ah * xh) << u(1)) + (mid >> u(30)) + ((mid & low30) << u(31))
    part = al * xl
    total = (total & u(P61)) + (total >> u(61)) + (part & u(P61)) + (part >> u(61)) + u(b)
    total = (total & u(P61)) + (total >> u(61))
    return np.where(total >= u(P61), total - u(P61), total)
