"""Sketch parameters and the bounds they imply."""

from __future__ import annotations

import math
from dataclasses import dataclass, field, replace

from pyspark.sql import Column
from pyspark.sql import functions as F

from fadedhh.functions.decay import DecaySpec
from fadedhh.functions.hashing import RowHashes


def dimension(eps: float, delta: float, kind: str = "faded") -> tuple[int, int]:
    """(rows, columns). Plain Count-Min needs twice the columns of the faded sketch for the same error."""
    if not (0 < eps < 1 and 0 < delta < 1):
        raise ValueError("0 < eps < 1 and 0 < delta < 1")
    return math.ceil(math.log(1 / delta)), math.ceil(math.e / (eps if kind == "countmin" else 2 * eps))


def dimension_columns(eps: Column, delta: Column, kind: str = "faded") -> tuple[Column, Column]:
    """``dimension`` of columns, both long."""
    return F.ceil(F.log(F.lit(1.0) / delta)), F.ceil(F.lit(math.e) / (eps if kind == "countmin" else F.lit(2.0) * eps))


def implied(d: int, w: int, kind: str = "faded") -> tuple[float, float]:
    """(eps, delta) that a grid of d rows and w columns attains."""
    return math.e / (w if kind == "countmin" else 2 * w), math.exp(-d)


def miss_bound(phi: float, d: int, w: int) -> float:
    """Bound on the chance that a heavy item is majority candidate in none of its cells."""
    return min(1.0, (1 / (2 * phi * w)) ** d)


def miss_bound_column(phi: Column, d: int, w: int) -> Column:
    """``miss_bound`` of a column, by repeated products: every engine gets the same digits."""
    one = F.lit(1.0) / (F.lit(2.0 * w) * phi)
    power = one
    for _ in range(d - 1):
        power = power * one
    return F.least(F.lit(1.0), power)


@dataclass(frozen=True)
class SketchParams:
    """Everything two sketches must share to be merged."""

    d: int = 4
    w: int = 1360
    landmark: int = 0
    decay: DecaySpec = field(default_factory=DecaySpec.none)
    seed: int = 1
    profile: str = "mod31"

    def __post_init__(self):
        if self.d < 1 or self.w < 1:
            raise ValueError("a sketch has at least one row and one column")

    @property
    def hashes(self) -> RowHashes:
        return RowHashes(self.d, self.w, self.seed, self.profile)

    @property
    def eps(self) -> float:
        return implied(self.d, self.w)[0]

    def check_support(self, phi: float, strict: bool = True) -> bool:
        """Whether phi is within the guarantee (eps < phi < 1); raises unless strict is off."""
        inside = self.eps < phi < 1
        if strict and not inside:
            raise ValueError(f"phi={phi} is outside the guarantee: the grid's error is {self.eps:.5f}")
        return inside

    def with_(self, **changes) -> SketchParams:
        return replace(self, **changes)

    def describe(self) -> dict:
        return {"d": self.d, "w": self.w, "seed": self.seed, "profile": self.profile, "decay": f"{self.decay.kind}:{self.decay.param!r}:{self.decay.unit}", "landmark": self.landmark}
