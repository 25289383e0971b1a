"""Language identification by error-correcting output codes.

Every language gets a codeword; one logistic classifier over hashed byte bigrams and
trigrams predicts each bit; decoding sums each bit's logistic loss, weighted by the bit's
accuracy in training, and picks the codeword of least loss. The score is the chosen
language's share when losses are turned into weights, and a result is ambiguous if its
score is under ``AMBIGUOUS``.

Training reads at most about PER_LANGUAGE documents of each language (all of them if
there are fewer), and at most about TRAINING of all languages together, chosen by a hash of
the id; prediction reads whole texts.

Edge cases: null texts and texts without a letter are ``und`` with score 0; with no
training rows every document is ``und``; with one language every text with a letter is in
it with score 1. Null languages are never learnt; rows with a null id are predicted but
never learnt from.
"""

from __future__ import annotations

import itertools
import math
import re

import numpy as np
from pyspark.sql import DataFrame, functions as F, types as T

from .common import annotate, held_out, learnable

PER_LANGUAGE, TRAINING = 400, 8000
TRIGRAMS, BIGRAMS = 4096, 1024
AMBIGUOUS = 0.6
UNKNOWN = "und"
_LETTER = re.compile(rb"[A-Za-z]")
_LOWER = bytes(range(256)).lower()


def has_letter(text: bytes | None) -> bool:
    if not text:
        return False
    return bool(_LETTER.search(text)) or any(c.isalpha() for c in text.decode("utf-8", "replace"))


def grams(texts: list[bytes | None]) -> np.ndarray:
    """Rows of unit length: square roots of hashed trigram and bigram counts of whole texts."""
    out = np.zeros((len(texts), TRIGRAMS + BIGRAMS), np.float32)
    for k, t in enumerate(texts):
        if not t:
            continue
        b = np.frombuffer(b" " + t.translate(_LOWER) + b" ", np.uint8).astype(np.uint32)
        pair = b[:-1] * np.uint32(257) + b[1:]
        tri = (pair[:-1] * np.uint32(2654435761) + b[2:] * np.uint32(40503 * 65537)) >> np.uint32(20)
        bi = (pair * np.uint32(2246822519)) >> np.uint32(22)
        out[k, :TRIGRAMS] = np.bincount(tri, minlength=TRIGRAMS)
        out[k, TRIGRAMS:] = np.bincount(bi, minlength=BIGRAMS)
    np.sqrt(out, out=out)
    norm = np.sqrt((out * out).sum(axis=1, keepdims=True))
    return out / np.maximum(norm, 1e-9)


def codewords(n: int) -> np.ndarray:
    """n rows of -1 and 1: all splits of the languages for up to 5, else the best of some random codes."""
    if n <= 5:
        cols = [(1, *rest) for rest in itertools.product((1, -1), repeat=n - 1) if -1 in rest]
        return np.array(cols, np.float32).reshape(-1, n).T
    bits = max(15, math.ceil(8 * math.log2(n)))
    rng, best, most = np.random.default_rng(7), None, -1
    for _ in range(200):
        code = rng.choice(np.array([-1, 1], np.float32), (n, bits))
        apart = (bits - code @ code.T) / 2 + bits * np.eye(n)
        if np.abs(code.sum(axis=0)).max() < n and apart.min() > most:
            best, most = code, apart.min()
    return best


def fit(x: np.ndarray, label: np.ndarray, code: np.ndarray, rounds: int = 120) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Weights, offsets and bit weights of the binary classifiers (accelerated gradient steps)."""
    target = code[label]
    share = np.bincount(label, minlength=len(code)).astype(np.float32)
    each = (1 / share[label] / np.count_nonzero(share))[:, None]
    w = np.zeros((x.shape[1], code.shape[1]), np.float32)
    b = np.zeros(code.shape[1], np.float32)
    vw, vb = w.copy(), b.copy()
    for k in range(rounds):
        look_w, look_b = w + 0.9 * vw, b + 0.9 * vb
        m = target * (x @ look_w + look_b)
        g = -target * each / (1 + np.exp(np.clip(m, -30, 30)))
        vw = 0.9 * vw - 12.0 * (x.T @ g + 1e-5 * look_w)
        vb = 0.9 * vb - 2.0 * g.sum(axis=0)
        w, b = w + vw, b + vb
    wrong = (each * ((x @ w + b) * target <= 0)).sum(axis=0)
    e = np.clip(wrong, 0.01, 0.49)
    weight = np.log((1 - e) / e)
    return w, b, (weight / weight.mean()).astype(np.float32)


def decode(margin: np.ndarray, code: np.ndarray, weight: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Chosen languages and their scores."""
    loss = np.stack([(np.logaddexp(0, -margin * c) * weight).sum(axis=1) for c in code], axis=1)
    near = np.exp(loss.min(axis=1, keepdims=True) - loss)
    pick = loss.argmin(axis=1)
    return pick, near[np.arange(len(pick)), pick] / near.sum(axis=1)


def train(docs: DataFrame, id_col: str, text: str, lang: str, per_language: int = PER_LANGUAGE) -> dict | None:
    """The model, from documents whose id's hash leaves them to learning."""
    rows = docs.select(F.col(id_col).alias("id"), F.col(lang).alias("lang"), F.col(text).alias("text")).where(
        learnable(F.col("id"), 4, 2) & F.col("lang").isNotNull() & F.col("text").isNotNull()
    )
    counts = sorted((r.lang, r.n) for r in rows.groupBy("lang").agg(F.count("*").alias("n")).collect())
    if not counts:
        return None
    names = [k for k, _ in counts]
    if len(names) == 1:
        return {"names": names}
    each = min(per_language, max(1, TRAINING // len(names)))
    part = F.create_map(*[F.lit(v) for k, n in counts for v in (k, min(1.0, each / n))])
    u = F.pmod(F.xxhash64("id", F.lit("language")), F.lit(1 << 20)) / float(1 << 20)

    def start():
        return lambda texts: [[row.astype(np.float16).tobytes() for row in grams(texts)]]

    sample = annotate(rows.where(u < part[F.col("lang")]), ["text"], [("x", T.BinaryType())], start, keep=["id", "lang"]).toArrow().to_pandas()
    sample = sample.sort_values(["id", "lang"], kind="stable")
    at = {k: i for i, k in enumerate(names)}
    label = np.array([at[k] for k in sample["lang"]], np.int64)
    if len(set(label.tolist())) < 2:
        return {"names": [names[label[0]]] if len(label) else names[:1]}
    x = np.stack([np.frombuffer(v, np.float16) for v in sample["x"]]).astype(np.float32)
    code = codewords(len(names))
    w, b, weight = fit(x, label, code)
    return {"names": names, "code": code, "w": w, "b": b, "weight": weight}


def identify(docs: DataFrame, model: dict | None, text: str = "text", keep=None) -> DataFrame:
    """Rows of ``docs`` with lang_pred, score and ambiguous."""
    held = docs.sparkSession.sparkContext.broadcast(model)

    def start():
        m = held.value

        def work(texts):
            usable = [has_letter(t) for t in texts] if m else [False] * len(texts)
            pred, score = [UNKNOWN] * len(texts), [0.0] * len(texts)
            rows = [i for i, ok in enumerate(usable) if ok]
            if rows and "w" not in m:
                for i in rows:
                    pred[i], score[i] = m["names"][0], 1.0
            elif rows:
                pick, s = decode(grams([texts[i] for i in rows]) @ m["w"] + m["b"], m["code"], m["weight"])
                for i, p, v in zip(rows, pick, s):
                    pred[i], score[i] = m["names"][p], float(v)
            return pred, score, [v < AMBIGUOUS for v in score]

        return work

    fields = [("lang_pred", T.StringType()), ("score", T.DoubleType()), ("ambiguous", T.BooleanType())]
    return annotate(docs, [text], fields, start, keep)


def op3_language(spark, sf_dir):
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet").select("doc_id", "lang", "text")
    found = identify(docs, train(docs, "doc_id", "text", "lang"), keep=["doc_id"])
    return found.select("doc_id", held_out(F.col("doc_id"), 4, 2).alias("held_out"), "lang_pred", "score", "ambiguous")
