"""Functions of a frequency, as columns with the properties that the methods ask for."""

from __future__ import annotations

from collections.abc import Callable, Sequence
from dataclasses import dataclass

from pyspark.sql import Column, DataFrame, functions as F


@dataclass(frozen=True)
class FrequencyFunction:
    """A non-negative function of a positive frequency, ``column(w)``.

    exponent: p if it is the p-th power. monotone: never falls as w grows.
    concave: concave and sublinear, so that a concave multi-objective sample serves it.
    """

    name: str
    column: Callable[[Column], Column]
    monotone: bool = True
    concave: bool = False
    exponent: float | None = None

    def __call__(self, w: Column | str) -> Column:
        return self.column(F.col(w) if isinstance(w, str) else w)


def power(w: Column, p: float) -> Column:
    """w to the power p; small whole powers as products, which are exact longer."""
    if p == 0:
        return F.lit(1.0)
    if p == int(p) and 0 < p <= 4:
        out = w.cast("double")
        for _ in range(int(p) - 1):
            out = out * w.cast("double")
        return out
    return F.pow(w.cast("double"), F.lit(float(p)))


def moment(p: float) -> FrequencyFunction:
    if p < 0:
        raise ValueError("moments have p of 0 or more")
    return FrequencyFunction(f"moment_{p:g}", lambda w: power(w, p), True, p <= 1, float(p))


def distinct() -> FrequencyFunction:
    return FrequencyFunction("distinct", lambda w: F.when(w > 0, 1.0).otherwise(0.0), True, True, 0.0)


def threshold(t: float, strict: bool = True) -> FrequencyFunction:
    return FrequencyFunction(f"threshold_{t:g}", lambda w: (w > t if strict else w >= t).cast("double"))


def threshold_weight(t: float) -> FrequencyFunction:
    return FrequencyFunction(f"threshold_weight_{t:g}", lambda w: F.when(w > t, w.cast("double")).otherwise(0.0))


def cap(t: float) -> FrequencyFunction:
    return FrequencyFunction(f"cap_{t:g}", lambda w: F.least(w.cast("double"), F.lit(float(t))), True, True)


def log1p() -> FrequencyFunction:
    return FrequencyFunction("log1p", lambda w: F.log1p(w.cast("double")), True, True)


def soft_cap(t: float) -> FrequencyFunction:
    return FrequencyFunction(f"soft_cap_{t:g}", lambda w: F.lit(1.0) - F.exp(-w.cast("double") / t), True, True)


def combination(parts: Sequence[tuple[float, FrequencyFunction]]) -> FrequencyFunction:
    """A non-negative combination: families that a sample serves are closed under it."""
    if not parts or any(a < 0 for a, _ in parts):
        raise ValueError("weights must be 0 or more")

    def column(w: Column) -> Column:
        out = F.lit(0.0)
        for a, f in parts:
            out = out + F.lit(float(a)) * f(w)
        return out

    return FrequencyFunction("+".join(f"{a:g}*{f.name}" for a, f in parts), column, all(f.monotone for _, f in parts), all(f.concave for _, f in parts))


def custom(name: str, column: Callable[[Column], Column], monotone: bool = True) -> FrequencyFunction:
    return FrequencyFunction(name, column, monotone)


def is_monotone_on(f: FrequencyFunction, histogram: DataFrame) -> bool:
    """Whether f never falls from one frequency of ``histogram`` (w, m) to the next larger one."""
    from pyspark.sql import Window as W

    steps = histogram.select(f("w").alias("y"), F.lag(f("w")).over(W.orderBy("w")).alias("x"))
    return steps.where("x is not null and y < x").limit(1).count() == 0
