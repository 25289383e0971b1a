"""The flagship: one l_1 sample of words, the third moment estimated from it, its truth, and a certificate."""

from __future__ import annotations

from pyspark.sql import functions as F

from ..functions.frequency import moment
from ..operators import bottomk as B
from ..operators.combos import certify
from ..plans.registry import query
from .sql import f_sql, freq, s, sample_sql, sig

K = 64
_S = sample_sql(f_sql("doc_words"), "w", K)


@query(
    "flagship",
    f"""SELECT CAST(count(*) AS BIGINT) AS keys, {s('sum(w*w*w / p_incl)')} AS estimate, {s(f"(SELECT sum(w*w*w) FROM {f_sql('doc_words')} a)")} AS truth,
    {s(f"{K} * max(w) / (SELECT sum(w) FROM {f_sql('doc_words')} a)")} AS certified FROM {_S} x""",
)
def flagship(spark, d):
    w = freq(spark, d, "doc_words")
    rows = B.ppswor(w, K)
    truth = w.agg(F.sum(moment(3)("w")).alias("truth"), F.sum("w").alias("mass"))
    found = rows.agg(F.count("*").alias("keys"), F.sum(moment(3)("w") / F.col("p_incl")).alias("estimate"), F.max("w").alias("largest"))
    both = found.crossJoin(F.broadcast(truth))
    return both.select("keys", sig("estimate").alias("estimate"), sig("truth").alias("truth"), sig(K * F.col("largest") / F.col("mass")).alias("certified"))


__all__ = ["certify", "flagship"]
