"""Decay functions as Spark columns.

Forward decay: an occurrence at time ``at`` weighs g(at - L) when stored and is divided by g(t - L) only when
asked at time t, so stored weights never change. Times are longs (microseconds, or any ordinal with unit 1).
"""

from __future__ import annotations

import math
from dataclasses import dataclass
from datetime import timedelta

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

MICROS = 1_000_000


@dataclass(frozen=True)
class DecaySpec:
    """A monotone g. ``unit`` is the number of ticks that make one unit of the argument."""

    kind: str
    param: float = 0.0
    unit: int = MICROS

    @classmethod
    def exp(cls, rate: float, unit: int = MICROS) -> DecaySpec:
        """g(a) = exp(rate a)."""
        return cls("exp", float(rate), unit)

    @classmethod
    def half_life(cls, life: timedelta) -> DecaySpec:
        """Exponential decay that halves a weight every ``life``."""
        return cls.exp(rate_from_half_life(life))

    @classmethod
    def poly(cls, beta: float, unit: int = MICROS) -> DecaySpec:
        """g(a) = a ** beta."""
        return cls("poly", float(beta), unit)

    @classmethod
    def dyadic(cls, step: int) -> DecaySpec:
        """g(a) = 2 ** floor(a / step) for a step in ticks: sums are exact in doubles, in any order."""
        return cls("dyadic", float(step), 1)

    @classmethod
    def none(cls) -> DecaySpec:
        """g = 1: plain frequencies."""
        return cls("none")

    @property
    def landmark_free(self) -> bool:
        """Whether normalised weights do not depend on the landmark, so that a sketch may be moved to another."""
        return self.kind in ("exp", "none")

    def g(self, age: int) -> float:
        if self.kind == "exp":
            return math.exp(self.param * age / self.unit)
        if self.kind == "poly":
            return (age / self.unit) ** self.param
        if self.kind == "dyadic":
            return 2.0 ** (age // int(self.param))
        return 1.0

    def column(self, age: Column) -> Column:
        """g of an age column in ticks."""
        if self.kind == "exp":
            return F.exp(F.lit(self.param) * (age.cast("double") / F.lit(float(self.unit))))
        if self.kind == "poly":
            return F.pow(age.cast("double") / F.lit(float(self.unit)), F.lit(self.param))
        if self.kind == "dyadic":
            return F.pow(F.lit(2.0), F.floor(age / F.lit(int(self.param))).cast("double"))
        return F.lit(1.0)

    def check_span(self, span: int) -> None:
        """Refuses spans whose raw weights would leave the range of doubles."""
        log2 = {"exp": self.param * span / self.unit / math.log(2), "poly": self.param * math.log2(max(2, span / self.unit)), "dyadic": span / max(self.param, 1)}.get(self.kind, 0)
        if log2 > 900:
            raise OverflowError("raw weights overflow: move the landmark nearer to the data")


def rate_from_half_life(life: timedelta) -> float:
    """Rate per second."""
    return math.log(2) / life.total_seconds()


def forward_raw(at: Column, landmark: int, spec: DecaySpec) -> Column:
    return spec.column(at - F.lit(landmark))


def forward_weight(at: Column, now: int, landmark: int, spec: DecaySpec) -> Column:
    """Normalised forward weight at time ``now``."""
    return forward_raw(at, landmark, spec) / F.lit(spec.g(now - landmark))


def backward_weight(at: Column, now: int, spec: DecaySpec) -> Column:
    """h(age) / h(0) with h = 1/g shifted to h(0) = 1: for exp the usual exp(-rate age); for poly (1 + age) ** -beta."""
    age = F.lit(now) - at
    if spec.kind == "poly":
        return F.pow(F.lit(1.0) + age.cast("double") / F.lit(float(spec.unit)), F.lit(-spec.param))
    return F.lit(1.0) / spec.column(age)


def check_contract(stream: DataFrame, spec: DecaySpec, landmark: int, nows: list[int]) -> DataFrame:
    """One row per query time: rows seen, weights outside 0..1, weights that grew since the time before, and weights
    other than 1 at age 0. All but the first must be 0."""
    out = None
    for k, now in enumerate(nows):
        w = forward_weight(F.col("tick"), now, landmark, spec)
        before = forward_weight(F.col("tick"), nows[k - 1], landmark, spec) if k else w
        seen = stream.where((F.col("tick") > landmark) & (F.col("tick") <= (nows[k - 1] if k else now)))
        one = seen.agg(
            F.lit(k).alias("step"), F.count("*").alias("n"),
            F.count_if((w < 0) | (w > 1)).alias("out_of_range"), F.count_if(w > before).alias("grew"),
            F.count_if((F.col("tick") == now) & (w != 1)).alias("not_one_at_zero"),
        )
        out = one if out is None else out.union(one)
    return out
