"""Pieces of SQL for the oracles, and columns that round as they do."""

from __future__ import annotations

from pyspark.sql import Column, functions as F

from ..operators.exact import frequencies, histogram
from ..plans.lineage import cut
from ..sources.tables import FREQUENCY_SQL, elements


def freq(spark, d, name):
    return frequencies(elements(spark, d, name))


def hist(spark, d, name):
    """The histogram of a workload, computed once: it is small and asked for many times."""
    return cut(histogram(freq(spark, d, name)))


def sig(c: Column | str) -> Column:
    """Seven significant digits, written and read back: engines differ in the last bits of a sum.

    The factor moves whole numbers off the middle between two, which engines round apart.
    """
    return F.format_string("%.6e", (F.col(c) if isinstance(c, str) else c).cast("double") * F.lit(1.0000000001)).cast("double")


def s(x: str) -> str:
    return f"CAST(printf('%.6e', CAST({x} AS DOUBLE) * CAST(1.0000000001 AS DOUBLE)) AS DOUBLE)"


def f_sql(name: str) -> str:
    return f"({FREQUENCY_SQL[name]})"


def v_sql(name: str) -> str:
    return f"(SELECT w, count(*) AS m FROM {f_sql(name)} a GROUP BY w)"


def r_sql(name: str) -> str:
    """Ranked histogram."""
    return f"""(SELECT w, m, sum(m) OVER (ORDER BY w DESC) - m + 1 AS first_rank, sum(m) OVER (ORDER BY w DESC) AS last_rank,
      sum(m * w) OVER (ORDER BY w DESC) AS prefix, coalesce(sum(m * w) OVER (ORDER BY w DESC ROWS BETWEEN 1 FOLLOWING AND UNBOUNDED FOLLOWING), 0) AS tail,
      max(w) OVER () AS top FROM {v_sql(name)} b)"""


def u_sql(salt: str = "'s'", key: str = "key") -> str:
    return f"((CAST(CAST('0x' || substr(md5({salt} || '|' || {key}), 1, 13) AS BIGINT) AS DOUBLE) + CAST(0.5 AS DOUBLE)) / CAST(4503599627370496 AS DOUBLE))"


def h_sql(scheme: str = "ppswor", salt: str = "'s'", key: str = "key") -> str:
    u = u_sql(salt, key)
    return f"(-ln(1 - {u}))" if scheme == "ppswor" else u


def p_sql(scheme: str, weight: str, tau: str) -> str:
    p = f"1 - exp(-({weight}) * {tau})" if scheme == "ppswor" else f"least(1.0, ({weight}) * {tau})"
    return f"CASE WHEN {tau} IS NULL THEN 1.0 ELSE {p} END"


def sample_sql(rows: str, weight: str, k: int, scheme: str = "ppswor", salt: str = "'s'") -> str:
    """Strict part of a bottom-k sample of ``rows`` (key, w, ...)."""
    return f"""(SELECT key, w, weight, seed, tau, {p_sql(scheme, 'weight', 'tau')} AS p_incl FROM (
      SELECT *, max(CASE WHEN rn = {k} THEN seed END) OVER () AS tau FROM (
        SELECT *, row_number() OVER (ORDER BY seed, key) AS rn FROM (
          SELECT key, w, {weight} AS weight, {h_sql(scheme, salt)} / ({weight}) AS seed FROM {rows} a WHERE ({weight}) > 0) b) c WHERE rn <= {k}) d
      WHERE tau IS NULL OR rn < {k})"""


def drawn_sql(rows: str, p: int, k: int) -> str:
    """(key, w, q, draws, p_incl) of k draws with replacement by w^p: the points that fall into each key's interval."""
    v = "*".join(["w"] * p)
    return f"""(SELECT key, max(w) AS w, max(v / total) AS q, count(*) AS draws, max(CASE WHEN v >= total THEN 1 ELSE 1 - pow(1 - v / total, {k}) END) AS p_incl FROM (
      SELECT key, w, {v} AS v, sum({v}) OVER (ORDER BY substr(md5(key), 1, 3), key ROWS UNBOUNDED PRECEDING) AS upto, sum({v}) OVER () AS total FROM {rows} a) b
      JOIN (SELECT {u_sql("'wr|s'", "CAST(i AS VARCHAR)")} AS x FROM (SELECT unnest(range(0, {k})) AS i) c) p ON x * total >= upto - v AND x * total < upto GROUP BY key)"""


def q_sql(name: str, scheme: str) -> str:
    """Ranked histogram with the scheme's single-draw chance q, and u = w / w_1."""
    v = {"l0": "1.0", "l1": "w / top", "l2": "(w / top) * (w / top)", "concave": "w / (last_rank * w + tail)"}[scheme]
    return f"(SELECT *, w / top AS u, ({v}) / sum(m * ({v})) OVER () AS q, {v} AS v FROM {r_sql(name)} r)"


def union_sql(names, body) -> str:
    return "\nUNION ALL ".join(f"SELECT '{n}' AS dataset, t.* FROM ({body(n)}) t" for n in names)


def union(frames):
    out = None
    for name, df in frames:
        df = df.select(F.lit(name).alias("dataset"), "*")
        out = df if out is None else out.unionByName(df)
    return out
