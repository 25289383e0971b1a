"""Quality by a sparse rule ensemble.

Shallow boosted trees over text statistics are taken apart into rules (every path from
the root, a conjunction of thresholds); a logistic model with an l1 penalty keeps few of
them; the kept rules become one Spark column expression over the statistics.

Training reads at most about TRAINING labelled documents, chosen by a hash of the id.

Edge cases: null and empty texts have all statistics 0 and are scored like others; with
no labelled rows every score is 0.5; with labels of one kind it is the smoothed share of
that kind; labels other than 0 and 1, null labels and null ids are not learnt from.
"""

from __future__ import annotations

import numpy as np
from pyspark.sql import Column, DataFrame, functions as F, types as T

from .common import SPACED, annotate, free_names, held_out, learnable

TRAINING = 6000
THRESHOLD = 0.7
TREES, DEPTH, CUTS, LEAST = 24, 3, 24, 20
PENALTY = 0.002

STATISTICS = (
    "q_words", "q_word_length", "q_distinct", "q_top", "q_runs", "q_upper", "q_digits", "q_symbols", "q_bars", "q_shouts", "q_stops", "q_lines", "q_same_lines", "q_longest", "q_foreign",
)

_UPPER = np.zeros(256, bool)
_UPPER[65:91] = True
_DIGIT = np.zeros(256, bool)
_DIGIT[48:58] = True
_LETTER = np.zeros(256, bool)
_LETTER[65:91] = _LETTER[97:123] = _LETTER[128:] = True
_PLAIN = _LETTER | _DIGIT
for _c in b" \t\n\r\x0b\x0c.,;:'\"-!?()|":
    _PLAIN[_c] = True


def statistics(text: bytes | None) -> list[float]:
    """The STATISTICS of one whole text."""
    if not text:
        return [0.0] * len(STATISTICS)
    count = np.bincount(np.frombuffer(text, np.uint8), minlength=256)
    w = text.translate(SPACED).split()
    n, size = len(w), len(text)
    letters = max(1, int(count[_LETTER].sum()))
    seen: dict[bytes, int] = {}
    for x in w:
        seen[x] = seen.get(x, 0) + 1
    runs = sum(map(bytes.__eq__, w, w[1:]))
    lines = [x for x in text.split(b"\n") if x.strip()]
    per = max(1, n)
    return [
        float(n), sum(map(len, w)) / per, len(seen) / per, max(seen.values(), default=0) / per, runs / per,
        count[_UPPER].sum() / letters, count[_DIGIT].sum() / size, 1 - count[_PLAIN].sum() / size, count[124] / per, count[33] / per,
        count[46] / per, len(lines) / per, 1 - len(set(lines)) / max(1, len(lines)), max(map(len, w), default=0) / 1.0, count[128:].sum() / size,
    ]


def with_statistics(docs: DataFrame, text: str = "text", keep=None) -> DataFrame:
    """Rows of ``docs`` with one double for each of STATISTICS."""

    def start():
        return lambda texts: list(zip(*[statistics(t) for t in texts]))

    return annotate(docs, [text], [(s, T.DoubleType()) for s in STATISTICS], start, keep)


def _tree(x: np.ndarray, bins: np.ndarray, cuts: list[np.ndarray], g: np.ndarray, h: np.ndarray, rows: np.ndarray, path: tuple, depth: int, rules: set, out: np.ndarray) -> None:
    """Grows one regression tree on gradients; adds its paths to ``rules`` and its step to ``out``."""
    best = (1e-6, None, None)
    G, H = g[rows].sum(), h[rows].sum() + 1.0
    if depth and len(rows) >= 2 * LEAST:
        for f in range(x.shape[1]):
            m = len(cuts[f])
            if not m:
                continue
            b = bins[rows, f]
            gs = np.cumsum(np.bincount(b, g[rows], m + 1))[:-1]
            hs = np.cumsum(np.bincount(b, h[rows], m + 1))[:-1]
            ns = np.cumsum(np.bincount(b, minlength=m + 1))[:-1]
            gain = gs**2 / (hs + 1) + (G - gs) ** 2 / (H - hs) - G**2 / H
            gain[(ns < LEAST) | (len(rows) - ns < LEAST)] = -1
            k = int(gain.argmax())
            if gain[k] > best[0]:
                best = (gain[k], f, k)
    if best[1] is None:
        out[rows] = -G / H
        return
    _, f, k = best
    left = bins[rows, f] <= k
    for side, part in ((True, rows[left]), (False, rows[~left])):
        step = (f, float(cuts[f][k]), side)
        rules.add(tuple(sorted({*path, step})))
        _tree(x, bins, cuts, g, h, part, (*path, step), depth - 1, rules, out)


def holds(x: np.ndarray, rule: tuple) -> np.ndarray:
    ok = np.ones(len(x), bool)
    for f, cut_at, low in rule:
        ok &= (x[:, f] <= cut_at) == low
    return ok


def fit_rules(x: np.ndarray, y: np.ndarray, penalty: float = PENALTY) -> tuple[float, list[tuple[tuple, float]]]:
    """Intercept and the rules that the lasso keeps, with their weights."""
    share = (y.sum() + 1) / (len(y) + 2)
    prior = float(np.log(share / (1 - share)))
    if len(y) == 0 or y.min() == y.max():
        return (0.0 if len(y) == 0 else prior), []
    cuts = [np.unique(np.quantile(x[:, f], np.linspace(0, 1, CUTS + 2)[1:-1])) for f in range(x.shape[1])]
    bins = np.stack([np.searchsorted(c, x[:, f], side="left") for f, c in enumerate(cuts)], axis=1)
    z, rules = np.full(len(y), prior), set()
    for _ in range(TREES):
        p = 1 / (1 + np.exp(-z))
        step = np.zeros(len(y))
        _tree(x, bins, cuts, p - y, p * (1 - p) + 1e-9, np.arange(len(y)), (), DEPTH, rules, step)
        z += 0.3 * step
    order = sorted(rules)
    a = np.stack([holds(x, r) for r in order], axis=1).astype(np.float64)
    _, first = np.unique(a, axis=1, return_index=True)
    order = [order[i] for i in sorted(first)]
    a = a[:, sorted(first)]
    # proximal gradient with momentum; l1 on the rules, none on the intercept
    n, m = a.shape
    rate = 4.0 / (np.linalg.norm(a, 2) ** 2 / n + 1)
    w, b, vw, vb, t = np.zeros(m), prior, np.zeros(m), prior, 1.0
    for _ in range(600):
        r = 1 / (1 + np.exp(-(a @ vw + vb))) - y
        new = vw - rate * (a.T @ r) / n
        new = np.sign(new) * np.maximum(np.abs(new) - rate * penalty, 0)
        nb = vb - rate * r.mean()
        nt = (1 + np.sqrt(1 + 4 * t * t)) / 2
        vw, vb = new + (t - 1) / nt * (new - w), nb + (t - 1) / nt * (nb - b)
        w, b, t = new, nb, nt
    return float(b), [(rule, float(v)) for rule, v in zip(order, w) if abs(v) > 1e-6]


def compiled(model: tuple[float, list[tuple[tuple, float]]], names=STATISTICS) -> Column:
    """The model as a column over the statistics: the chance of label 1."""
    intercept, rules = model
    total = F.lit(intercept)
    for rule, weight in rules:
        hold = F.lit(True)
        for f, cut_at, low in rule:
            hold = hold & (F.col(names[f]) <= cut_at if low else F.col(names[f]) > cut_at)
        total = total + F.when(hold, F.lit(weight)).otherwise(F.lit(0.0))
    return F.lit(1.0) / (F.lit(1.0) + F.exp(-total))


def train(docs: DataFrame, labels: DataFrame, id_col: str = "doc_id", label: str = "quality", training: int = TRAINING, text: str = "text"):
    """The model, from texts of documents whose id's hash leaves them to learning; rows that repeat count as often."""
    known = labels.select(F.col(id_col).alias("_id"), F.col(label).cast("int").alias("_y")).where(learnable(F.col("_id"), 4, 2) & F.col("_y").isin(0, 1))
    n = known.count()
    u = F.pmod(F.xxhash64("_id", F.lit("quality")), F.lit(1 << 20))
    chosen = known.where(u < int((1 << 20) * min(1.0, training / max(1, n)))).distinct()
    rows = docs.select(F.col(id_col).alias("_id"), F.col(text).alias("_text")).join(F.broadcast(chosen), "_id")
    rows = with_statistics(rows, "_text", keep=["_id", "_y"])
    data = rows.toArrow().to_pandas().sort_values(["_id", "_y", *STATISTICS], kind="stable")
    return fit_rules(data[list(STATISTICS)].to_numpy(float), data["_y"].to_numpy(float))


def classify(docs: DataFrame, labels: DataFrame, id_col: str = "doc_id", text: str = "text", keep=None) -> DataFrame:
    """Rows of ``docs`` with score and predicted (1 from THRESHOLD on).

    Only the bounded sample of labelled documents is measured for training; then every text once.
    """
    kept = list(docs.columns) if keep is None else list(keep)
    model = train(docs, labels, id_col, text=text)
    rows = with_statistics(docs, text, keep=kept)
    names = rows.columns[len(kept):]
    out = rows.withColumn(names[0], compiled(model, names))
    score, predicted = free_names(["score", "predicted"], kept)
    return out.select(*[F.col(f"`{c}`") for c in kept], F.col(f"`{names[0]}`").alias(score), (F.col(f"`{names[0]}`") >= THRESHOLD).cast("int").alias(predicted))


def op8_quality(spark, sf_dir):
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet").select("doc_id", "text")
    labels = spark.read.parquet(f"{sf_dir}/labels.parquet").select("doc_id", "quality")
    found = classify(docs, labels, keep=["doc_id"])
    return found.select("doc_id", held_out(F.col("doc_id"), 4, 2).alias("held_out"), "score", "predicted")
