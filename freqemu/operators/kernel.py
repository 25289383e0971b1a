"""A bounded sketch in each task: sampling by advice without a shuffle of all keys.

Each task keeps a table of keys with their exact sums, cuts it down to the sketch of what
it has seen whenever it is full, and emits at most k_h + k_p + k_u rows. Cutting is safe
because a key outside the sketch of what a task has seen stays outside: later rows only
bring rivals, and its own seed and advice do not change. Partial sketches are summed by key,
which deals them over tasks again, and cut once more. Advice that is too large to broadcast is
joined to the elements' sums by key, whose rows then go through the same tasks.
"""

from __future__ import annotations

import hashlib
import math
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame, functions as F

from ..functions.frequency import FrequencyFunction
from ..plans.lineage import cut
from .advice import attach, cut_sketch
from .exact import frequencies

#: Rows of advice that may be broadcast to the tasks.
MOST_ADVICE = 2_000_000
#: Elements that a task sums at once, and bytes of them: each such block looks all its keys up in the advice.
BLOCK_ROWS, BLOCK_BYTES = 1 << 18, 1 << 24
SCHEMA = "key string, w double, advice double, h double, fa double, r double"


def unit_seed_of(key: str, salt: str) -> float:
    return (int(hashlib.md5(f"{salt}|{key}".encode()).hexdigest()[:13], 16) + 0.5) / float(1 << 52)


class PartialSketch:
    """The state of one task, as columns; keys come in batches that hold each key once. ``f`` maps advice to its weight."""

    def __init__(self, kh: int, kp: int, ku: int, f, scheme: str, salt: str, slack: int = 65536):
        self.kh, self.kp, self.ku, self.f, self.scheme, self.salt = kh, kp, ku, f, scheme, salt
        self.full = 2 * (kh + kp + ku) + slack
        self.rows = pa.table({"key": pa.array([], pa.string()), **{c: pa.array([], pa.float64()) for c in ("w", "advice", "u")}})
        self.bars = (math.inf, math.inf, -math.inf)

    def add(self, keys: pa.Array, values: np.ndarray, advice: np.ndarray) -> None:
        u = np.fromiter((unit_seed_of(x, self.salt) for x in keys.to_pylist()), float, len(keys))
        h, _, r = self._ranks(advice, u)
        bar_h, bar_r, bar_a = self.bars  # beaten in all three parts already: never in the sketch
        on = (h <= bar_h) | (r <= bar_r) | (advice >= bar_a)
        new = pa.table({"key": keys.cast(pa.string()), "w": values, "advice": advice, "u": u}).filter(pa.array(on))
        self.rows = pa.concat_tables([self.rows, new])
        if len(self.rows) >= self.full:
            self.cut()

    def _ranks(self, advice: np.ndarray, u: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        h = -np.log1p(-u) if self.scheme == "ppswor" else u
        fa = np.where(advice > 0, self.f(np.where(advice > 0, advice, 1.0)), 0.0)
        return h, fa, np.where(fa > 0, h / np.where(fa > 0, fa, 1.0), math.inf)

    def cut(self) -> tuple[pa.Table, np.ndarray, np.ndarray, np.ndarray]:
        """Sums the rows by key and keeps the sketch of what the task has seen: (rows, h, fa, r)."""
        t = self.rows.group_by("key").aggregate([("w", "sum"), ("advice", "max"), ("u", "min")]).rename_columns(["key", "w", "advice", "u"]).sort_by("key")
        advice, u = t.column("advice").to_numpy(), t.column("u").to_numpy()
        h, fa, r = self._ranks(advice, u)
        order = np.lexsort((h, -advice))  # rows are in order of keys, and the sort is stable
        top, rest = order[: self.kh], np.sort(order[self.kh :])
        by_h = rest[np.argsort(h[rest], kind="stable")[: self.ku]]
        some = rest[r[rest] < math.inf]
        by_r = some[np.argsort(r[some], kind="stable")[: self.kp]]
        self.bars = (
            (h[by_h[-1]] if self.ku else -math.inf) if len(by_h) == self.ku else math.inf,
            (r[by_r[-1]] if self.kp else -math.inf) if len(by_r) == self.kp else math.inf,
            (advice[top[-1]] if len(top) == self.kh else -math.inf) if self.kh else math.inf,
        )
        kept = np.unique(np.concatenate([top, by_h, by_r]))
        self.rows = t.take(pa.array(kept))
        return self.rows, h[kept], fa[kept], r[kept]


def blocks(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.Table]:
    """The batches, joined up to a block's size; none if there are none."""
    held, rows, size = [], 0, 0
    for b in batches:
        held.append(b)
        rows, size = rows + b.num_rows, size + b.nbytes
        if rows >= BLOCK_ROWS or size >= BLOCK_BYTES:
            yield pa.Table.from_batches(held)
            held, rows, size = [], 0, 0
    if held:
        yield pa.Table.from_batches(held)


def partial_sketches(elements: DataFrame, f: FrequencyFunction, kh: int, kp: int, ku: int, scheme: str = "ppswor", salt: str = "s", advice: DataFrame | None = None) -> DataFrame:
    """At most k_h + k_p + k_u rows for each partition of ``elements`` (key, value, advice). f must be a moment.

    With ``advice`` (key, advice), elements have none of their own, and keys outside it have
    advice 0. Up to ``MOST_ADVICE`` rows of it are broadcast to the tasks; more are joined to
    the elements' sums by key.
    """
    p = f.exponent
    if p is None:
        raise ValueError("the kernel computes moments only")
    held = None
    if advice is not None:
        advice = cut(advice.select("key", F.col("advice").cast("double").alias("advice")))
        if advice.limit(MOST_ADVICE + 1).count() > MOST_ADVICE:
            elements = attach(frequencies(elements), advice).withColumnRenamed("w", "value")
        else:
            table = advice.toArrow()
            held = elements.sparkSession.sparkContext.broadcast((table.column("key").combine_chunks(), table.column("advice").to_numpy()))

    def weight(a: np.ndarray) -> np.ndarray:
        return np.prod([a] * int(p), axis=0) if p in (1, 2, 3, 4) else a**p

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        state = PartialSketch(kh, kp, ku, weight, scheme, salt)
        for b in blocks(batches):
            # elements of one block are summed by key first, in Arrow
            t = b.group_by("key").aggregate([("value", "sum"), ("advice", "max")])
            keys, given = t.column("key").combine_chunks(), t.column("advice_max").to_numpy()
            if held is not None:
                known, values = held.value
                at = pc.index_in(keys, value_set=known)
                given = np.where(at.is_valid().to_numpy(zero_copy_only=False), np.append(values, 0.0)[pc.fill_null(at, len(values)).to_numpy()], 0.0)
            state.add(keys, t.column("value_sum").to_numpy(), given)
        rows, h, fa, r = state.cut()
        cols = [rows.column(c).combine_chunks() for c in ("key", "w", "advice")]
        yield pa.RecordBatch.from_arrays([*cols, pa.array(h), pa.array(fa), pa.array(r, mask=np.isinf(r))], names=["key", "w", "advice", "h", "fa", "r"])

    own = F.lit(0.0) if held is not None else F.col("advice").cast("double")
    return elements.select("key", F.col("value").cast("double").alias("value"), own.alias("advice")).mapInArrow(run, SCHEMA)


def kernel_sketch(elements: DataFrame, f: FrequencyFunction, kh: int, kp: int, ku: int, scheme: str = "ppswor", salt: str = "s", advice: DataFrame | None = None) -> DataFrame:
    """As ``advice.advice_sketch``: elements carry their advice, or ``advice`` is a table of any size."""
    parts = partial_sketches(elements, f, kh, kp, ku, scheme, salt, advice)
    merged = parts.groupBy("key").agg(F.sum("w").alias("w"), *[F.first(c).alias(c) for c in ("advice", "h", "fa", "r")])
    return cut_sketch(merged, kh, kp, ku)
