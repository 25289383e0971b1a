"""Sampling by advice: sketches, merging, estimates, conditions, sources of advice, errors."""

from __future__ import annotations

from pyspark.sql import functions as F

from ..functions.frequency import moment
from ..operators import advice as A
from ..operators import advice_models as AM
from ..operators import kernel as KN
from ..operators import measures as M
from ..operators.exact import frequencies
from ..plans import planner
from ..plans.registry import query
from ..sources.tables import load, to_elements, tokens
from .sql import f_sql, freq, h_sql, p_sql, s, sig, u_sql

PAST, NOW, END = "1997-01-01", "1997-07-01", "1998-01-01"


def between(column: str, start: str, end: str):
    return (F.col(column) >= F.expr(f"timestamp_ntz'{start}'")) & (F.col(column) < F.expr(f"timestamp_ntz'{end}'"))


# -- data with advice: (key, w, advice) ------------------------------------------------------


def cust_parts(spark, d):
    o = load(spark, d, "orders").select("o_custkey", "o_orderdate")
    return to_elements(o.where(between("o_orderdate", PAST, NOW)), ["o_custkey"]), to_elements(o.where(between("o_orderdate", NOW, END)), ["o_custkey"])


def supp_parts(spark, d):
    o = load(spark, d, "orders").select("o_orderkey", "o_orderdate")
    li = load(spark, d, "lineitem").select("l_orderkey", "l_suppkey")
    e = o.where(between("o_orderdate", PAST, END)).join(li, F.col("o_orderkey") == F.col("l_orderkey"))
    return to_elements(e.where(between("o_orderdate", PAST, NOW)), ["l_suppkey"]), to_elements(e.where(between("o_orderdate", NOW, END)), ["l_suppkey"])


def word_parts(spark, d):
    t = load(spark, d, "documents").select("doc_id", "text")
    return tokens(t.where("doc_id % 2 = 0")), tokens(t.where("doc_id % 2 = 1"))


def event_parts(spark, d):
    e = load(spark, d, "events").select("user_id", "ts")
    return to_elements(e.where(between("ts", "2024-01-01", "2024-01-16")), ["user_id"]), to_elements(e.where(between("ts", "2024-01-16", "2024-01-31")), ["user_id"])


PARTS = {"cust": cust_parts, "supp": supp_parts, "words": word_parts, "events": event_parts}


def rows_of(spark, d, name):
    past, now = PARTS[name](spark, d)
    return A.attach(frequencies(now), AM.past_frequency(past))


def _words(parity):
    return f"SELECT key, CAST(count(*) AS DOUBLE) AS w FROM (SELECT unnest(regexp_extract_all(lower(text), '[\\p{{L}}\\p{{N}}]+')) AS key FROM documents WHERE doc_id % 2 = {parity}) x GROUP BY 1"


def _cust(a, b):
    return f"SELECT CAST(o_custkey AS VARCHAR) AS key, CAST(count(*) AS DOUBLE) AS w FROM orders WHERE o_orderdate >= TIMESTAMP '{a} 00:00:00' AND o_orderdate < TIMESTAMP '{b} 00:00:00' GROUP BY 1"


def _supp(a, b):
    return f"SELECT CAST(l_suppkey AS VARCHAR) AS key, CAST(count(*) AS DOUBLE) AS w FROM orders JOIN lineitem ON l_orderkey = o_orderkey WHERE o_orderdate >= TIMESTAMP '{a} 00:00:00' AND o_orderdate < TIMESTAMP '{b} 00:00:00' GROUP BY 1"


def _events(a, b):
    return f"SELECT CAST(user_id AS VARCHAR) AS key, CAST(count(*) AS DOUBLE) AS w FROM events WHERE ts >= TIMESTAMP '{a} 00:00:00' AND ts < TIMESTAMP '{b} 00:00:00' GROUP BY 1"


def _attached(now, past):
    return f"(SELECT f.key, f.w, coalesce(p.w, 0.0) AS advice FROM ({now}) f LEFT JOIN ({past}) p ON p.key = f.key)"


ROWS = {
    "cust": _attached(_cust(NOW, END), _cust(PAST, NOW)),
    "supp": _attached(_supp(NOW, END), _supp(PAST, NOW)),
    "words": _attached(_words(1), _words(0)),
    "events": _attached(_events("2024-01-16", "2024-01-31"), _events("2024-01-01", "2024-01-16")),
}


def sketch_ctes(rows: str, fa: str, kh: int, kp: int, ku: int, scheme: str) -> str:
    return f"""a AS (SELECT *, {h_sql(scheme)} AS h, CASE WHEN advice > 0 THEN {fa} ELSE 0.0 END AS fa FROM {rows} z),
    b AS (SELECT *, CASE WHEN fa > 0 THEN h / fa END AS r, row_number() OVER (ORDER BY advice DESC, h, key) AS tr FROM a),
    c AS (SELECT *, tr <= {kh} AS in_top, CASE WHEN tr > {kh} AND r IS NOT NULL THEN row_number() OVER (PARTITION BY tr <= {kh}, r IS NULL ORDER BY r, key) END AS rr,
      CASE WHEN tr > {kh} THEN row_number() OVER (PARTITION BY tr <= {kh} ORDER BY h, key) END AS ur FROM b),
    sk AS (SELECT *, coalesce(rr <= {kp}, false) AS in_advice, coalesce(ur <= {ku}, false) AS in_uniform FROM c WHERE tr <= {kh} OR coalesce(rr <= {kp}, false) OR coalesce(ur <= {ku}, false)),
    marks AS (SELECT max(CASE WHEN rr = {kp - 1} THEN r END) AS p1, max(CASE WHEN rr = {kp} THEN r END) AS p2, max(CASE WHEN ur = {ku - 1} THEN h END) AS u1, max(CASE WHEN ur = {ku} THEN h END) AS u2 FROM sk),
    th AS (SELECT sk.*, CASE WHEN rr < {kp} THEN p2 ELSE p1 END AS tau_p, CASE WHEN ur < {ku} THEN u2 ELSE u1 END AS tau_u FROM sk, marks),
    lim AS (SELECT *, CASE WHEN fa <= 0 THEN tau_u WHEN tau_p IS NULL OR tau_u IS NULL THEN NULL ELSE greatest(fa * tau_p, tau_u) END AS lim FROM th)"""


SHOWN = f"key, CAST(w AS BIGINT) AS w, CAST(advice AS BIGINT) AS advice, {s('h')} AS h, in_top, in_advice, in_uniform"


def shown(sk):
    return sk.select("key", F.col("w").cast("bigint").alias("w"), F.col("advice").cast("bigint").alias("advice"), sig("h").alias("h"), "in_top", "in_advice", "in_uniform")


KH, KP, KU = 4, 32, 32


def _sketch(name, scheme, make, rows="words"):
    @query(name, f"WITH {sketch_ctes(ROWS[rows], 'advice*advice*advice', KH, KP, KU, scheme)} SELECT {SHOWN} FROM sk")
    def run(spark, d):
        return shown(make(spark, d))

    run.__name__ = name


def _relational(spark, d, scheme):
    past, now = word_parts(spark, d)
    return A.advice_sketch(now, AM.past_frequency(past), moment(3), KH, KP, KU, scheme)


def _with_advice(spark, d, name="words"):
    """Elements that carry their advice."""
    past, now = PARTS[name](spark, d)
    return now.join(AM.past_frequency(past), "key", "left").select("key", "value", F.coalesce("advice", F.lit(0.0)).alias("advice"))


def _merged(spark, d):
    past, _ = word_parts(spark, d)
    advice = AM.past_frequency(past)
    docs = load(spark, d, "documents").where("doc_id % 2 = 1").select("doc_id", "text")
    parts = [A.advice_sketch(tokens(docs.where(f"(doc_id DIV 2) % 3 = {i}")), advice, moment(3), KH, KP, KU) for i in range(3)]
    return A.merge_advice(parts, KH, KP, KU)


_sketch("advice_sketch", "ppswor", lambda spark, d: _relational(spark, d, "ppswor"))
_sketch("advice_sketch_priority", "priority", lambda spark, d: _relational(spark, d, "priority"))


def _kernel(spark, d):
    past, now = word_parts(spark, d)
    return KN.kernel_sketch(now, moment(3), KH, KP, KU, advice=AM.past_frequency(past))


_sketch("advice_sketch_kernel", "ppswor", _kernel)
_sketch("advice_merge", "ppswor", _merged)


def _prefiltered(spark, d):
    past, now = word_parts(spark, d)
    part = tokens(load(spark, d, "documents").select("doc_id", "text").where("doc_id % 16 = 1"))  # some of the input; in files, a few of them
    return planner.prefiltered_sketch(now, part, AM.past_frequency(past), moment(3), KH, KP, KU)


_sketch("advice_sketch_prefiltered", "ppswor", _prefiltered)


@query("advice_top", f"SELECT key, CAST(w AS BIGINT) AS w, CAST(advice AS BIGINT) AS advice FROM (SELECT *, row_number() OVER (ORDER BY advice DESC, {h_sql()}, key) AS i FROM {ROWS['words']} z) y WHERE i <= 16")
def advice_top(spark, d):
    rows = A.seeded(rows_of(spark, d, "words"), moment(3))
    return A.cut_sketch(rows, 16, 0, 0).select("key", F.col("w").cast("bigint").alias("w"), F.col("advice").cast("bigint").alias("advice"))


@query("advice_exact_counts", f"WITH {sketch_ctes(ROWS['words'], 'advice*advice*advice', KH, KP, KU, 'ppswor')} SELECT sk.key, CAST(f.w AS BIGINT) AS stored, CAST(f.w AS BIGINT) AS exact FROM sk JOIN ({_words(1)}) f ON f.key = sk.key")
def advice_exact_counts(spark, d):
    _, now = word_parts(spark, d)
    sk = KN.kernel_sketch(_with_advice(spark, d), moment(3), KH, KP, KU).select("key", F.col("w").alias("stored"))
    exact = frequencies(now).withColumnRenamed("w", "exact")
    return exact.join(F.broadcast(sk), "key").select("key", F.col("stored").cast("bigint").alias("stored"), F.col("exact").cast("bigint").alias("exact"))


@query(
    "advice_estimate",
    f"""WITH {sketch_ctes(ROWS['words'], 'advice*advice*advice', KH, KP, KU, 'ppswor')},
    e AS (SELECT *, CASE WHEN in_top THEN 1.0 ELSE {p_sql('ppswor', '1.0', 'lim')} END AS p_incl FROM lim
      WHERE in_top OR tau_u IS NULL OR h < tau_u OR (r IS NOT NULL AND (tau_p IS NULL OR r < tau_p)))
    SELECT key, CAST(w AS BIGINT) AS w, in_top, {s('p_incl')} AS p_incl, {s('w*w*w / p_incl')} AS f_hat FROM e""",
)
def advice_estimate(spark, d):
    found = A.advice_estimate(_relational(spark, d, "ppswor"), moment(3), KP, KU)
    return found.select("key", F.col("w").cast("bigint").alias("w"), "in_top", sig("p_incl").alias("p_incl"), sig("f_hat").alias("f_hat"))


def _quality_sql(name, h, cu):
    top = f"WHERE advice < (SELECT min(advice) FROM (SELECT advice FROM q ORDER BY advice DESC, key LIMIT {h}) t)" if h else ""
    return f"""WITH q AS (SELECT key, advice, w*w*w AS fw, CASE WHEN advice > 0 THEN advice*advice*advice ELSE 0.0 END AS fa FROM {ROWS[name]} z),
    t AS (SELECT sum(fw) AS sw, sum(fa) AS sa, count(*) AS n FROM q)
    SELECT {s("coalesce(max(CASE WHEN fa > 0 THEN (fw / sw) / (fa / sa) ELSE CAST('inf' AS DOUBLE) END), 0)")} AS cp FROM (SELECT * FROM q {top}) x, t WHERE fw / sw > {cu} / n"""


_QUALITY = (("supp", 0, 0.0), ("supp", 3, 0.5), ("events", 0, 1.0), ("words", 8, 200.0))


@query("advice_quality", "\nUNION ALL ".join(f"SELECT '{n}' AS dataset, CAST({h} AS BIGINT) AS h, CAST({cu} AS DOUBLE) AS cu, t.* FROM ({_quality_sql(n, h, cu)}) t" for n, h, cu in _QUALITY))
def advice_quality(spark, d):
    out = None
    for n, h, cu in _QUALITY:
        one = A.advice_quality(rows_of(spark, d, n), moment(3), h, cu).select(F.lit(n).alias("dataset"), F.lit(h).cast("bigint").alias("h"), F.lit(cu).alias("cu"), F.when(F.col("cp") == float("inf"), F.col("cp")).otherwise(sig("cp")).alias("cp"))
        out = one if out is None else out.union(one)
    return out


@query("advice_ratio", f"SELECT {s('min(x)')} AS low, {s('max(x)')} AS high, {s('max(x) / min(x)')} AS cp FROM (SELECT advice*advice / (w*w) AS x FROM {ROWS['supp']} z) y")
def advice_ratio(spark, d):
    return A.advice_ratio(rows_of(spark, d, "supp"), moment(2)).select(*[sig(c).alias(c) for c in ("low", "high", "cp")])


@query("advice_var_bound", f"SELECT key, {s('w*w*w*w * sum(advice*advice) OVER () / (advice*advice) / 62')} AS by_advice, {s('w*w*w*w * count(*) OVER () / 30')} AS by_uniform FROM {ROWS['supp']} z")
def advice_var_bound(spark, d):
    return A.advice_variance_bound(rows_of(spark, d, "supp"), moment(2), 64, 32).select("key", sig("by_advice").alias("by_advice"), sig("by_uniform").alias("by_uniform"))


@query("advice_past", f"SELECT key, CAST(w AS BIGINT) AS w, CAST(advice AS BIGINT) AS advice FROM {ROWS['cust']} z")
def advice_past(spark, d):
    return rows_of(spark, d, "cust").select("key", F.col("w").cast("bigint").alias("w"), F.col("advice").cast("bigint").alias("advice"))


_NOISE = u_sql("'noise'")


@query("advice_noisy", f"SELECT key, {s(f'w * pow(2, 1.5 * (2 * {_NOISE} - 1))')} AS advice FROM {f_sql('cust_out')} z")
def advice_noisy(spark, d):
    return AM.noisy_advice(freq(spark, d, "cust_out"), 1.5).select("key", sig("advice").alias("advice"))


@query("advice_hh_flag", f"SELECT key, CASE WHEN w*w >= 0.01 * sum(w*w) OVER () THEN CAST(1000000 AS DOUBLE) ELSE CAST(0 AS DOUBLE) END AS advice FROM ({_words(0)}) z")
def advice_hh_flag(spark, d):
    past, _ = word_parts(spark, d)
    return AM.heavy_hitter_advice(frequencies(past), 2, 0.01)


@query("advice_learned")
def advice_learned(spark, d):
    past, now = word_parts(spark, d)
    docs = load(spark, d, "documents").select("doc_id", "text")
    first, second = tokens(docs.where("doc_id % 4 = 0")), tokens(docs.where("doc_id % 4 = 2"))
    train, earlier = frequencies(second), frequencies(first)
    return AM.learned_advice(train, earlier, frequencies(now), frequencies(past), rounds=8)


@query("sketch_size", f"WITH {sketch_ctes(ROWS['words'], 'advice*advice*advice', KH, KP, KU, 'ppswor')} SELECT CAST(count(*) AS BIGINT) AS held, CAST({KH + KP + KU} AS BIGINT) AS most FROM sk")
def sketch_size(spark, d):
    return M.sketch_size(_relational(spark, d, "ppswor"), KH, KP, KU)


def advice_error_sql(rows: str, sizes, p: int, runs: int) -> str:
    """(k, k_uniform, nrmse) of sampling by advice with k_h = 0, averaged over runs."""
    x = "{0}*{0}*{0}" if p == 3 else f"pow({{0}}, {p})"
    fa, fw = x.format("advice"), x.format("w")
    h = f"-ln(1 - {u_sql('CAST(run AS VARCHAR)')})"
    base = f"""a AS (SELECT run, key, w, {h} AS h, CASE WHEN advice > 0 THEN {fa} ELSE 0.0 END AS fa, {fw} AS fw FROM {rows} z, (SELECT unnest(range(0, {runs})) AS run) q),
    b AS (SELECT *, CASE WHEN fa > 0 THEN h / fa END AS r FROM a),
    c AS (SELECT *, CASE WHEN r IS NOT NULL THEN row_number() OVER (PARTITION BY run, r IS NULL ORDER BY r, key) END AS rr, row_number() OVER (PARTITION BY run ORDER BY h, key) AS ur, sum(CASE WHEN run = 0 THEN fw END) OVER () AS truth FROM b)"""
    out = []
    for kp, ku in sizes:
        marks = f"(SELECT run, max(CASE WHEN rr = {kp - 1} THEN r END) AS p1, max(CASE WHEN rr = {kp} THEN r END) AS p2, max(CASE WHEN ur = {ku - 1} THEN h END) AS u1, max(CASE WHEN ur = {ku} THEN h END) AS u2 FROM c GROUP BY run)"
        tp = f"CASE WHEN rr < {kp} THEN p2 ELSE p1 END"
        tu = f"CASE WHEN ur < {ku} THEN u2 ELSE u1 END"
        lim = f"CASE WHEN fa <= 0 THEN {tu} WHEN ({tp}) IS NULL OR ({tu}) IS NULL THEN NULL ELSE greatest(fa * ({tp}), {tu}) END"
        v = f"pow(fw / truth, 2) * (1 / ({p_sql('ppswor', '1.0', 'lim')}) - 1)"
        out.append(f"SELECT CAST({kp + ku} AS BIGINT) AS k, CAST({ku} AS BIGINT) AS k_uniform, 'moment_{p}' AS f, {s(f'sqrt(sum({v}) / {runs})')} AS nrmse FROM (SELECT c.*, {lim} AS lim FROM c JOIN {marks} m ON m.run = c.run) y")
    return f"WITH {base} " + " UNION ALL ".join(out)


def advice_errors(rows, p, sizes, runs):
    found = M.conditional_nrmse_advice(rows, moment(p), [(0, kp, ku) for kp, ku in sizes], runs)
    return found.select("k", "k_uniform", "f", sig("nrmse").alias("nrmse"))


@query("nrmse_advice", advice_error_sql(ROWS["cust"], ((32, 32), (96, 32)), 3, 5))
def nrmse_advice(spark, d):
    return advice_errors(rows_of(spark, d, "cust"), 3, ((32, 32), (96, 32)), 5)
