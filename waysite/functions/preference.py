"""Preferences: how much a path values a site by its detour. All are 0 beyond tau unless said."""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass

from pyspark.sql import Column
from pyspark.sql import functions as F

#: Scores are whole millionths, so sums don't depend on row order.
MICRO = 1_000_000


@dataclass(frozen=True)
class Preference:
    name: str
    tau: float | None
    of: Callable[[Column], Column]

    def score(self, metres: Column) -> Column:
        value = F.round(self.of(metres.cast("double")) * MICRO).cast("long")
        return value if self.tau is None else F.when(metres <= self.tau, value).otherwise(F.lit(0).cast("long"))


def binary(tau: float) -> Preference:
    return Preference("binary", tau, lambda d: F.lit(1.0))


def linear(tau: float) -> Preference:
    return Preference("linear", tau, lambda d: 1 - d / F.lit(float(tau)))


def convex(tau: float, power: float = 2) -> Preference:
    return Preference("convex", tau, lambda d: F.pow(1 - d / F.lit(float(tau)), F.lit(float(power))))


def exponential(tau: float, rate: float = 3) -> Preference:
    return Preference("exponential", tau, lambda d: F.exp(-rate * d / F.lit(float(tau))))


def inconvenience() -> Preference:
    """The negated detour, without a threshold."""
    return Preference("inconvenience", None, lambda d: -d / MICRO)


def custom(tau: float, of: Callable[[Column], Column]) -> Preference:
    return Preference("custom", tau, of)


def is_non_increasing(preference: Preference, spark, steps: int = 100) -> bool:
    """Whether the score never rises with the detour, on evenly spaced detours up to tau and a little beyond."""
    top = (preference.tau or 1000) * 1.1
    rows = spark.range(steps + 1).select((F.col("id") * top / steps).alias("d")).select("d", preference.score(F.col("d")).alias("s")).orderBy("d").collect()
    return all(a["s"] >= b["s"] for a, b in zip(rows, rows[1:], strict=False))
