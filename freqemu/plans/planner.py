"""Choices made when a plan is built: which scheme, and which way to a sketch."""

from __future__ import annotations

from collections.abc import Sequence

from pyspark.sql import DataFrame, functions as F

from ..functions.frequency import FrequencyFunction
from ..functions.seeds import draw
from ..operators import advice as A
from ..operators.exact import frequencies
from ..operators.overhead import family_overhead
from .lineage import cut

#: Keys of advice that may be broadcast once they passed the bars.
FEW_PASSING = 500_000
#: Keys up to which the aggregation of all keys is the plain way.
FEW_KEYS = 20_000_000


def choose_scheme(hist: DataFrame, functions: Sequence[FrequencyFunction], epsilon: float, schemes: Sequence = (1.0, 2.0, "concave")) -> dict:
    """The scheme of least overhead for all ``functions``, and the sample size that keeps the error within ``epsilon``."""
    found = [(family_overhead(hist, functions, s).first()["emulation"], str(s), s) for s in schemes]
    h, _, scheme = min(found, key=lambda x: x[:2])
    return {"scheme": scheme, "overhead": h, "size": -int(-(h / epsilon**2) // 1)}


def bars(part: DataFrame, f: FrequencyFunction, kh: int, kp: int, ku: int, scheme: str = "ppswor", salt: str = "s") -> tuple[float | None, float | None, float | None]:
    """(least advice, largest r, largest h) that a key of the sketch can have, from some of the elements.

    The k_h-th largest advice of a subset is no larger than that of all; and the subset
    without the top keys competes in the whole, so its order statistics k_h places further
    are no smaller than the thresholds. None: no bar.
    """
    rows = A.seeded(part.select("key", "advice").distinct().withColumn("w", F.lit(0.0)), f, scheme, salt)

    def last(frame, col, n):
        kept = frame.limit(n).agg(F.count("*").alias("c"), (F.min if col == "advice" else F.max)(col).alias("x")).first()
        return kept.x if n and kept.c == n else None

    a = last(rows.orderBy(F.col("advice").desc()), "advice", kh)
    r = last(rows.where("r is not null").orderBy("r"), "r", kp + kh) if kp else -1.0
    h = last(rows.orderBy("h"), "h", ku + kh) if ku else -1.0
    return a, r, h


def prefiltered_sketch(elements: DataFrame, part: DataFrame, advice: DataFrame, f: FrequencyFunction, kh: int, kp: int, ku: int, scheme: str = "ppswor", salt: str = "s") -> DataFrame:
    """The sketch of ``elements`` (key, value) after a filter that drops keys which cannot enter.

    ``part`` is any subset of the elements (a few files), ``advice`` (key, advice) the
    predictions. The bars come from the part; keys of advice that pass them are few and are
    broadcast if their number allows it. All other keys can only enter by their own draw,
    which is a plain column of the scan: no element is shuffled before the filter.
    """
    seen = part.select("key").distinct().join(advice, "key", "left").select("key", F.coalesce("advice", F.lit(0.0)).alias("advice"))
    a, r, h = bars(cut(seen), f, kh, kp, ku, scheme, salt)
    draw_ = draw(F.col("key"), salt, scheme)
    fa = F.when(F.col("advice") > 0, f("advice")).otherwise(0.0)
    by_advice = F.lit(False)
    if kh:
        by_advice = by_advice | (F.lit(True) if a is None else F.col("advice") >= a)
    if kp:
        by_advice = by_advice | ((fa > 0) & (F.lit(True) if r is None else draw_ <= fa * (r * (1 + 1e-12))))
    if ku:
        by_advice = by_advice | (F.lit(True) if h is None else draw_ <= h * (1 + 1e-12))
    passing = cut(advice.where(by_advice).select("key", F.col("advice").alias("_advice")))
    side = F.broadcast(passing) if passing.limit(FEW_PASSING + 1).count() <= FEW_PASSING else passing
    rows = elements.join(side, "key", "left")
    keep = F.col("_advice").isNotNull()
    if kh and (a is None or a <= 0):
        keep = F.lit(True)
    elif ku:
        keep = keep | (F.lit(True) if h is None else draw_ <= h * (1 + 1e-12))
    # a key with advice whose draw is under the bar passes too, so kept keys outside ``passing`` have no advice
    found = rows.where(keep).groupBy("key").agg(F.sum("value").alias("w"), F.coalesce(F.max("_advice"), F.lit(0.0)).alias("advice"))
    return A.cut_sketch(A.seeded(found, f, scheme, salt), kh, kp, ku)


def sketch_plan(elements: DataFrame, sampled_share: float = 0.01) -> str:
    """'relational' or 'kernel', from an estimate of the number of keys on a share of the elements."""
    n = elements.sample(sampled_share, seed=7).agg(F.approx_count_distinct("key")).first()[0]
    return "relational" if n / max(sampled_share, 1e-9) <= FEW_KEYS else "kernel"


def ground_truth(elements: DataFrame) -> DataFrame:
    return frequencies(elements)
