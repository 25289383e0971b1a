"""Functions, exact statistics, samples, estimators, overheads, combinations, universal samples, measures."""

from __future__ import annotations

from pyspark.sql import functions as F

from ..functions import frequency as FF
from ..functions.seeds import exp_of, seed_bits, unit_seed
from ..operators import bottomk as B
from ..operators import combos as C
from ..operators import concave as K
from ..operators import estimators as E
from ..operators import exact as X
from ..operators import linear as L
from ..operators import measures as M
from ..operators import overhead as O
from ..operators import rankcurve as R
from ..operators import unaggregated as N
from ..operators import universal as U
from ..operators import wr
from ..plans.registry import query
from ..plans.lineage import cut
from ..sources.tables import elements, load, to_elements
from .sql import drawn_sql, f_sql, freq, hist, p_sql, q_sql, r_sql, s, sample_sql, sig, u_sql, union, union_sql, v_sql

DATASETS = ("doc_words", "conv_words", "doc_lines", "page_hosts", "cust_out", "part_in", "supp_in", "ps_qty", "li_tuple", "event_tuple", "event_props", "doc_source")
SKEWED = ("doc_words", "conv_words", "doc_lines", "page_hosts")
KS = 64


# -- functions of frequency ------------------------------------------------------------------


def _functions(name, functions, sql):
    @query(name, "SELECT key, " + ", ".join(f"{s(x)} AS {n}" for n, x in sql.items()) + f" FROM {f_sql('cust_out')} a")
    def run(spark, d):
        return freq(spark, d, "cust_out").select("key", *[sig(f("w")).alias(n) for n, f in functions.items()])

    run.__name__ = name


_functions("f_moment", {"half": FF.moment(0.5), "one": FF.moment(1), "three": FF.moment(3), "ten": FF.moment(10)}, {"half": "sqrt(w)", "one": "w", "three": "w*w*w", "ten": "pow(w, 10)"})
_functions("f_distinct", {"d": FF.distinct()}, {"d": "1.0"})
_functions("f_threshold", {"over": FF.threshold(10), "at": FF.threshold(10, strict=False)}, {"over": "CASE WHEN w > 10 THEN 1 ELSE 0 END", "at": "CASE WHEN w >= 10 THEN 1 ELSE 0 END"})
_functions("f_threshold_weight", {"x": FF.threshold_weight(10)}, {"x": "CASE WHEN w > 10 THEN w ELSE 0 END"})
_functions("f_cap", {"x": FF.cap(8)}, {"x": "least(w, 8)"})
_functions("f_concave", {"log": FF.log1p(), "root": FF.moment(0.5), "soft": FF.soft_cap(8)}, {"log": "ln(1 + w)", "root": "sqrt(w)", "soft": "1 - exp(-w / 8)"})
_functions("f_combo", {"x": FF.combination([(2, FF.moment(3)), (5, FF.cap(8)), (1, FF.threshold(10))])}, {"x": "2 * w*w*w + 5 * least(w, 8) + CASE WHEN w > 10 THEN 1 ELSE 0 END"})


# -- exact statistics --------------------------------------------------------------------------


@query("freq_table", f"SELECT key, CAST(w AS BIGINT) AS w FROM {f_sql('doc_words')} a")
def freq_table(spark, d):
    return freq(spark, d, "doc_words").select("key", F.col("w").cast("bigint").alias("w"))


@query("freq_hist", f"SELECT CAST(w AS BIGINT) AS w, CAST(m AS BIGINT) AS m FROM {v_sql('doc_words')} a")
def freq_hist(spark, d):
    return X.histogram(freq(spark, d, "doc_words")).select(F.col("w").cast("bigint").alias("w"), "m")


@query("stat_moments", union_sql(DATASETS, lambda n: f"SELECT {s('sum(w)')} AS m1, {s('sum(w*w)')} AS m2, {s('sum(w*w*w)')} AS m3, {s('sum(pow(w, 10))')} AS m10, {s('sum(least(w, 8))')} AS cap8 FROM {f_sql(n)} a"))
def stat_moments(spark, d):
    fs = {"m1": FF.moment(1), "m2": FF.moment(2), "m3": FF.moment(3), "m10": FF.moment(10), "cap8": FF.cap(8)}
    return union((n, freq(spark, d, n).agg(*[sig(F.sum(f("w"))).alias(k) for k, f in fs.items()])) for n in DATASETS)


@query("stat_linear", f"SELECT {s('sum(c.c_acctbal * w*w)')} AS value FROM {f_sql('cust_out')} a JOIN customer c ON CAST(c.c_custkey AS VARCHAR) = a.key")
def stat_linear(spark, d):
    coef = load(spark, d, "customer").select(F.col("c_custkey").cast("string").alias("key"), F.col("c_acctbal").alias("coef"))
    return X.linear_statistic(freq(spark, d, "cust_out"), FF.moment(2), coef).select(sig("value").alias("value"))


@query("stat_domain", f"SELECT c.c_mktsegment AS segment, {s('sum(w*w*w)')} AS value FROM {f_sql('cust_out')} a JOIN customer c ON CAST(c.c_custkey AS VARCHAR) = a.key WHERE c.c_nationkey < 10 GROUP BY 1")
def stat_domain(spark, d):
    side = load(spark, d, "customer").select(F.col("c_custkey").cast("string").alias("key"), F.col("c_mktsegment").alias("segment"), "c_nationkey")
    rows = freq(spark, d, "cust_out").join(side, "key")
    return X.domain_statistic(rows, FF.moment(3), F.col("c_nationkey") < 10, ["segment"]).select("segment", sig("value").alias("value"))


@query("pps_probs", f"SELECT key, {s('w / sum(w) OVER ()')} AS p1, {s('w*w / sum(w*w) OVER ()')} AS p2 FROM {f_sql('cust_out')} a")
def pps_probs(spark, d):
    w = freq(spark, d, "cust_out")
    one = X.pps(w, FF.moment(1)).withColumnRenamed("p", "p1")
    return X.pps(one, FF.moment(2)).select("key", sig("p1").alias("p1"), sig("p").alias("p2"))


_RANKED = "CAST(m AS BIGINT) AS m, CAST(first_rank AS BIGINT) AS first_rank, CAST(last_rank AS BIGINT) AS last_rank"


@query("rank_vector", f"SELECT {s('w')} AS w, {_RANKED}, {s('prefix')} AS prefix, {s('tail')} AS tail FROM {r_sql('event_user_val')} a")
def rank_vector(spark, d):
    e = to_elements(load(spark, d, "events"), ["user_id"], "value", ["event_id"])
    return _ranked_out(X.ranked(cut(X.histogram(X.frequencies_in_order(e, "event_id", "value")))))


@query("rank_vector_parts", f"SELECT {s('w')} AS w, {_RANKED}, {s('prefix')} AS prefix, {s('tail')} AS tail FROM {r_sql('doc_words')} a")
def rank_vector_parts(spark, d):
    return _ranked_out(X.ranked_by_parts(hist(spark, d, "doc_words"), 5))


def _ranked_out(rows):
    return rows.select(sig("w").alias("w"), "m", F.col("first_rank").cast("bigint").alias("first_rank"), F.col("last_rank").cast("bigint").alias("last_rank"), sig("prefix").alias("prefix"), sig("tail").alias("tail"))


@query("self_join_size", f"SELECT CAST(sum(w*w) AS BIGINT) AS two, CAST(sum(w*w*w) AS BIGINT) AS three FROM {f_sql('cust_out')} a")
def self_join_size(spark, d):
    w = freq(spark, d, "cust_out")
    return X.self_join_size(w, 2).select(F.col("value").cast("bigint").alias("two")).crossJoin(X.self_join_size(w, 3).select(F.col("value").cast("bigint").alias("three")))


_PS = (0.0, 0.5, 1.0, 2.0, 3.0, 10.0)


@query("normalized_norms", union_sql(SKEWED, lambda n: " UNION ALL ".join(f"SELECT CAST({p} AS DOUBLE) AS p, {s(f'sum(m * pow(w / top, {p}))')} AS scaled FROM {r_sql(n)} a" for p in _PS)))
def normalized_norms(spark, d):
    return union((n, X.norms(hist(spark, d, n), _PS).select("p", sig("scaled").alias("scaled"))) for n in SKEWED)


# -- seeds and bottom-k samples -----------------------------------------------------------------


@query("seeds", f"SELECT key, CAST('0x' || substr(md5('s|' || key), 1, 13) AS BIGINT) AS bits, {u_sql()} AS u, {s(f'-ln(1 - {u_sql()})')} AS e FROM {f_sql('cust_out')} a")
def seeds(spark, d):
    return freq(spark, d, "cust_out").select("key", seed_bits(F.col("key"), "s").alias("bits"), unit_seed(F.col("key")).alias("u"), sig(exp_of(unit_seed(F.col("key")))).alias("e"))


def _sample(name, dataset, weight, k, scheme, make):
    sql = f"SELECT key, {s('w')} AS w, {s('seed')} AS seed, {s('tau')} AS tau, {s('p_incl')} AS p_incl FROM {sample_sql(f_sql(dataset), weight, k, scheme)} x"

    @query(name, sql)
    def run(spark, d):
        return make(freq(spark, d, dataset)).select("key", *[sig(c).alias(c) for c in ("w", "seed", "tau", "p_incl")])

    run.__name__ = name


_sample("bottomk_uniform", "doc_words", "1.0", KS, "ppswor", lambda w: B.uniform(w, KS))
_sample("ppswor_l1", "doc_words", "w", KS, "ppswor", lambda w: B.ppswor(w, KS))
_sample("ppswor_l2", "doc_words", "w*w", KS, "ppswor", lambda w: B.ppswor(w, KS, 2))
_sample("ppswor_f", "doc_words", "ln(1 + w)", KS, "ppswor", lambda w: B.sample(w, FF.log1p(), KS))
_sample("priority_l1", "doc_words", "w", KS, "priority", lambda w: B.priority(w, KS))
_sample("priority_l2", "doc_words", "w*w", KS, "priority", lambda w: B.priority(w, KS, 2))
_sample("cap_sample", "doc_words", "least(w, 50)", KS, "ppswor", lambda w: K.cap_sample(w, 50, KS))


@query("merge_bottomk", f"SELECT key, {s('w')} AS w, {s('seed')} AS seed FROM (SELECT key, w, {u_sql()} / w AS seed FROM {f_sql('doc_words')} a ORDER BY seed, key LIMIT {KS}) x")
def merge_bottomk(spark, d):
    w = freq(spark, d, "doc_words")
    parts = [B.bottom_k(B.seeded(w.where(F.pmod(F.crc32(F.col("key").cast("binary")), F.lit(3)) == i), F.col("w"), scheme="priority"), KS) for i in range(3)]
    return B.merge(parts, KS, FF.moment(1)).select("key", sig("w").alias("w"), sig("seed").alias("seed"))


_UNAGG = f"""(SELECT key, min(-ln(1 - {u_sql("'s'", "eid || '|' || key")})) AS seed FROM (SELECT CAST(event_id AS VARCHAR) AS eid, user_id || '|' || event_type || '|' || props AS key FROM events) e GROUP BY key)"""


def _event_elements(spark, d):
    key = F.concat_ws("|", "user_id", "event_type", "props")
    return load(spark, d, "events").select(key.alias("key"), F.lit(1.0).alias("value"), "event_id")


_UNAGG_KEPT = f"(SELECT * FROM (SELECT key, seed, max(CASE WHEN rn = {KS} THEN seed END) OVER () AS tau FROM (SELECT *, row_number() OVER (ORDER BY seed, key) AS rn FROM {_UNAGG} a) b WHERE rn <= {KS}) c WHERE tau IS NULL OR seed < tau)"


@query("ppswor_unagg", f"SELECT key, {s('seed')} AS seed, {s('tau')} AS tau FROM {_UNAGG_KEPT} x")
def ppswor_unagg(spark, d):
    return N.ppswor_by_elements(_event_elements(spark, d), KS, "event_id").select("key", sig("seed").alias("seed"), sig("tau").alias("tau"))


@query("ppswor_two_pass", f"SELECT x.key, CAST(f.w AS BIGINT) AS w, {s(p_sql('ppswor', 'f.w', 'x.tau'))} AS p_incl FROM {_UNAGG_KEPT} x JOIN {f_sql('event_tuple')} f ON f.key = x.key")
def ppswor_two_pass(spark, d):
    e = _event_elements(spark, d)
    return N.two_pass(e, N.ppswor_by_elements(e, KS, "event_id")).select("key", F.col("w").cast("bigint").alias("w"), sig("p_incl").alias("p_incl"))


_HOLD_WAIT = f"""-ln(1 - {u_sql("'s'", "CAST(event_id AS VARCHAR) || '|' || key")}) / 0.02"""


@query(
    "sample_hold",
    f"""WITH e AS (SELECT event_id, user_id || '|' || event_type || '|' || props AS key FROM events),
    t AS (SELECT key, event_id, 1 - {_HOLD_WAIT} AS rest FROM e),
    f AS (SELECT key, min(event_id) AS since, arg_min(rest, event_id) AS rest FROM t WHERE rest > 0 GROUP BY key),
    c AS (SELECT f.key, max(f.rest) + count(e.event_id) AS c FROM f LEFT JOIN e ON e.key = f.key AND e.event_id > f.since GROUP BY f.key)
    SELECT {s('sum(c*c*c + 3*c*c / 0.02)')} AS estimate, CAST(count(*) AS BIGINT) AS held, (SELECT CAST(sum(w*w*w) AS BIGINT) FROM {f_sql('event_tuple')} a) AS value FROM c""",
)
def sample_hold(spark, d):
    held = N.sample_and_hold(_event_elements(spark, d), 0.02, "event_id")
    cube = FF.custom("square3", lambda w: 3 * w * w)
    guess = N.hold_estimate(held, FF.moment(3), cube, 0.02).select(sig("estimate").alias("estimate"))
    truth = X.f_statistic(freq(spark, d, "event_tuple"), FF.moment(3)).select(F.col("value").cast("bigint").alias("value"))
    return guess.crossJoin(held.agg(F.count("*").alias("held"))).crossJoin(truth)


# -- with replacement, linear, concave ---------------------------------------------------------


def _wr(name, dataset, p, k):
    @query(name, f"SELECT key, CAST(w AS BIGINT) AS w, {s('q')} AS q, draws, {s('p_incl')} AS p_incl FROM {drawn_sql(f_sql(dataset), p, k)} x")
    def run(spark, d):
        return wr.pps_wr(freq(spark, d, dataset), FF.moment(p), k).select("key", F.col("w").cast("bigint").alias("w"), sig("q").alias("q"), "draws", sig("p_incl").alias("p_incl"))

    run.__name__ = name


_wr("pps_wr", "doc_words", 3, KS)
_wr("wr_l1", "doc_words", 1, KS)
_wr("wr_l2", "doc_words", 2, KS)

_WIN = u_sql("'s'", "j || '|' || key")


@query(
    "pps_wr_min",
    f"""SELECT key, {s('max(w)')} AS w, {s('max(q)')} AS q, CAST(count(*) AS BIGINT) AS draws, {s('1 - pow(1 - max(q), 16)')} AS p_incl FROM (
    SELECT j, key, w, q, row_number() OVER (PARTITION BY j ORDER BY -ln(1 - {_WIN}) / w, key) AS rn
    FROM (SELECT key, w, w / sum(w) OVER () AS q FROM {f_sql('page_hosts')} a) b, (SELECT unnest(range(0, 16)) AS j) c) x WHERE rn = 1 GROUP BY key""",
)
def pps_wr_min(spark, d):
    return wr.pps_wr_min(freq(spark, d, "page_hosts"), FF.moment(1), 16).select("key", sig("w").alias("w"), sig("q").alias("q"), "draws", sig("p_incl").alias("p_incl"))


_CELL = "CAST('0x' || substr(md5('cell|s|' || r || '|' || key), 1, 13) AS BIGINT)"


@query(
    "linear_l2_cells",
    f"""SELECT CAST(r AS INTEGER) AS "row", CAST(b AS BIGINT) AS bucket, {s('sum(x)')} AS total FROM (
    SELECT r, (bits // 2) % 64 AS b, (bits % 2 * 2 - 1) * w / sqrt(-ln(1 - {u_sql()})) AS x FROM (SELECT r, key, w, {_CELL} AS bits FROM {f_sql('page_hosts')} a, (SELECT unnest(range(0, 5)) AS r) c) y) z GROUP BY r, b""",
)
def linear_l2_cells(spark, d):
    return L.sketch_cells(elements(spark, d, "page_hosts"), 2, 5, 64).select("row", "bucket", sig("total").alias("total"))


@query("linear_l2_sample")
def linear_l2_sample(spark, d):
    return L.linear_sample(elements(spark, d, "doc_words"), 2, 32)


@query("second_moment_sketch")
def second_moment_sketch(spark, d):
    return L.second_moment(L.second_moment_cells(elements(spark, d, "doc_words")))


_CONC = f"(SELECT a.key, a.w, q.v, q.q FROM {f_sql('conv_words')} a JOIN {q_sql('conv_words', 'concave')} q ON q.w = a.w)"


@query("concave_probs", f"SELECT key, {s('w')} AS w, {s('v')} AS v, {s('q')} AS p FROM {_CONC} x")
def concave_probs(spark, d):
    return K.concave_probabilities(freq(spark, d, "conv_words")).select("key", *[sig(c).alias(c) for c in ("w", "v", "p")])


@query("concave_sample", f"SELECT key, {s('w')} AS w, {s('seed')} AS seed, {s('p_incl')} AS p_incl FROM {sample_sql(_CONC, 'v', KS)} x")
def concave_sample(spark, d):
    return K.concave_sample(freq(spark, d, "conv_words"), KS).select("key", *[sig(c).alias(c) for c in ("w", "seed", "p_incl")])


@query(
    "multi_cap_sample",
    f"""WITH a AS (SELECT key, w, t, least(w, t) AS v, -ln(1 - {u_sql()}) AS h FROM {f_sql('conv_words')} f, (SELECT pow(4.0, i) AS t FROM (SELECT unnest(range(0, 31)) AS i) r, (SELECT max(w) AS top FROM {f_sql('conv_words')} z) m WHERE i = 0 OR pow(4.0, i - 1) < top) c),
    b AS (SELECT *, h / v AS seed, row_number() OVER (PARTITION BY t ORDER BY h / v, key) AS rn FROM a),
    k AS (SELECT t, max(CASE WHEN rn = 32 THEN seed END) AS k_th, max(CASE WHEN rn = 31 THEN seed END) AS k_before FROM b WHERE rn <= 32 GROUP BY t),
    c AS (SELECT b.*, CASE WHEN rn <= 31 THEN k_th ELSE k_before END AS tau FROM b JOIN k ON k.t = b.t)
    SELECT key, {s('max(w)')} AS w, {s('max(1 - exp(-v * tau))')} AS p_incl FROM c GROUP BY key HAVING bool_or(seed < tau)""",
)
def multi_cap_sample(spark, d):
    return K.multi_cap_sample(cut(freq(spark, d, "conv_words")), 32).select("key", sig("w").alias("w"), sig("p_incl").alias("p_incl"))


# -- estimators ----------------------------------------------------------------------------------

_S1 = sample_sql(f_sql("cust_out"), "w", 256)


def _cust_sample(spark, d):
    return B.ppswor(freq(spark, d, "cust_out"), 256)


def _cust_side(spark, d):
    return load(spark, d, "customer").select(F.col("c_custkey").cast("string").alias("key"), F.col("c_mktsegment").alias("segment"), F.col("c_nationkey").alias("nation"), F.col("c_acctbal").alias("coef"))


_SIDE = f"{_S1} x JOIN customer c ON CAST(c.c_custkey AS VARCHAR) = x.key"


@query("ipw_keys", f"SELECT key, {s('w*w*w / p_incl')} AS f_hat FROM {_S1} x")
def ipw_keys(spark, d):
    return E.estimate(_cust_sample(spark, d), FF.moment(3)).select("key", sig("f_hat").alias("f_hat"))


@query("ipw_total", f"SELECT {s('sum(w*w*w / p_incl)')} AS estimate FROM {_S1} x")
def ipw_total(spark, d):
    return E.estimate_statistic(_cust_sample(spark, d), FF.moment(3)).select(sig("estimate").alias("estimate"))


@query("ipw_domain", f"SELECT c.c_mktsegment AS segment, {s('sum(w*w / p_incl)')} AS estimate FROM {_SIDE} WHERE c.c_nationkey < 15 GROUP BY 1")
def ipw_domain(spark, d):
    rows = _cust_sample(spark, d).join(_cust_side(spark, d), "key")
    return E.estimate_domain(rows, FF.moment(2), F.col("nation") < 15, ["segment"]).select("segment", sig("estimate").alias("estimate"))


@query("ipw_linear", f"SELECT {s('sum(c.c_acctbal * w / p_incl)')} AS estimate FROM {_SIDE}")
def ipw_linear(spark, d):
    return E.estimate_linear(_cust_sample(spark, d), FF.moment(1), _cust_side(spark, d)).select(sig("estimate").alias("estimate"))


_MANY = {"moment_0.5": "sqrt(w)", "moment_1": "w", "moment_3": "w*w*w", "cap_8": "least(w, 8)", "threshold_10": "CASE WHEN w > 10 THEN 1 ELSE 0 END"}


@query("ipw_many", " UNION ALL ".join(f"SELECT '{n}' AS f, c.c_mktsegment AS segment, {s(f'sum({x} / p_incl)')} AS estimate FROM {_SIDE} GROUP BY 2" for n, x in _MANY.items()))
def ipw_many(spark, d):
    rows = _cust_sample(spark, d).join(_cust_side(spark, d), "key")
    fs = [FF.moment(0.5), FF.moment(1), FF.moment(3), FF.cap(8), FF.threshold(10)]
    return E.estimate_many(rows, fs, ["segment"]).select("f", "segment", sig("estimate").alias("estimate"))


@query("ipw_variance", f"SELECT {s('sum(w*w*w*w * (1 - p_incl) / (p_incl * p_incl))')} AS variance FROM {_S1} x")
def ipw_variance(spark, d):
    return E.variance_hat(_cust_sample(spark, d), FF.moment(2)).select(sig("variance").alias("variance"))


# -- overheads -------------------------------------------------------------------------------------


@query("bench_var", f"SELECT {s('w')} AS w, CAST(m AS BIGINT) AS m, {s('w*w*w * sum(m*w*w*w) OVER () / 64')} AS variance FROM {v_sql('doc_words')} a")
def bench_var(spark, d):
    return O.benchmark_key_variance(hist(spark, d, "doc_words"), FF.moment(3), 64).select(sig("w").alias("w"), "m", sig("variance").alias("variance"))


@query("bench_var_domain", f"SELECT {s('sum(CASE WHEN w >= 10 THEN w*w ELSE 0 END) * sum(w*w) / 64')} AS variance FROM {f_sql('cust_out')} a")
def bench_var_domain(spark, d):
    return O.benchmark_domain_variance(freq(spark, d, "cust_out"), FF.moment(2), F.col("w") >= 10, 64).select(sig("variance").alias("variance"))


@query("bench_nrmse", f"SELECT CAST(k AS BIGINT) AS k, {s('sqrt(sum(m*w*w*w * total / k)) / max(total)')} AS nrmse FROM (SELECT *, sum(m*w*w*w) OVER () AS total FROM {v_sql('cust_out')} v) x, (SELECT unnest([32, 64, 128, 256, 512, 1024, 2048, 4096]) AS k) a GROUP BY k")
def bench_nrmse(spark, d):
    return M.benchmark_errors(hist(spark, d, "cust_out"), FF.moment(3), [2**i for i in range(5, 13)]).select("k", sig("nrmse").alias("nrmse"))


_TARGETS = {"moment_3": "u*u*u", "moment_10": "pow(u, 10)"}


def _overhead_sql(name, scheme, what):
    out = []
    for f, x in _TARGETS.items():
        ratio = f"(({x}) / sum(m * ({x})) OVER ()) / q"
        share = f"m * (({x}) / sum(m * ({x})) OVER ())"
        col = {"emulation": "max(r)", "estimation": "sum(sh * r)"}[what]
        out.append(f"SELECT '{f}' AS f, {s(col)} AS {what} FROM (SELECT {ratio} AS r, {share} AS sh FROM {q_sql(name, scheme)} a) b")
    return " UNION ALL ".join(out)


def _overhead_query(name, what):
    schemes = (("l1", 1.0), ("l2", 2.0), ("concave", "concave"))
    sql = "\nUNION ALL ".join(f"SELECT '{n}' AS dataset, '{k}' AS scheme, t.* FROM ({_overhead_sql(n, k, what)}) t" for n in SKEWED for k, _ in schemes)

    @query(name, sql)
    def run(spark, d):
        out = []
        for n in SKEWED:
            v = hist(spark, d, n)
            for k, scheme in schemes:
                rows = O.overheads(v, [FF.moment(3), FF.moment(10)], scheme)
                out.append((n, rows.select(F.lit(k).alias("scheme"), "f", sig(what).alias(what))))
        return union(out)

    run.__name__ = name


_overhead_query("overhead_emulation", "emulation")
_overhead_query("overhead_estimation", "estimation")


@query(
    "overhead_domain",
    f"SELECT {s('max(o) * sum(f) * max(t) / 64')} AS variance, {s('max(o)')} AS overhead FROM (SELECT w, w*w*w AS f, sum(w*w*w) OVER () AS t, (w*w*w / sum(w*w*w) OVER ()) / (w / sum(w) OVER ()) AS o FROM {f_sql('cust_out')} a) b WHERE w <= 12",
)
def overhead_domain(spark, d):
    return O.emulated_domain_variance(freq(spark, d, "cust_out"), FF.moment(3), FF.moment(1), F.col("w") <= 12, 64).select(sig("variance").alias("variance"), sig("overhead").alias("overhead"))


@query(
    "wr_variance",
    f"SELECT {s('w')} AS w, CAST(m AS BIGINT) AS m, {s('pi')} AS p_incl, {s('w*w*w*w * (1 / pi - 1)')} AS variance, {s('w*w*w*w / (64 * q)')} AS bound FROM (SELECT *, 1 - pow(1 - q, 64) AS pi FROM {q_sql('page_hosts', 'l1')} a) b",
)
def wr_variance(spark, d):
    return O.wr_key_variance(hist(spark, d, "page_hosts"), FF.moment(2), 1.0, 64).select(sig("w").alias("w"), "m", *[sig(c).alias(c) for c in ("p_incl", "variance", "bound")])


@query(
    "overhead_chain",
    union_sql(SKEWED, lambda n: f"SELECT {s('max(p / q)')} AS direct, {s('max(p / q2)')} AS first, {s('max(q2 / q)')} AS second FROM (SELECT q, (u*u*u) / sum(m*u*u*u) OVER () AS p, (u*u) / sum(m*u*u) OVER () AS q2 FROM {q_sql(n, 'l1')} a) b"),
)
def overhead_chain(spark, d):
    return union((n, O.chain(hist(spark, d, n), FF.moment(3), 2.0, 1.0).select(*[sig(c).alias(c) for c in ("direct", "first", "second")])) for n in SKEWED)


_FAMILY = {"moment_3": "w*w*w", "moment_2": "w*w", "threshold_4": "CASE WHEN w > 4 THEN 1.0 ELSE 0 END"}
_COMBO = "(w*w*w + 3 * w*w + 9 * CASE WHEN w > 4 THEN 1.0 ELSE 0 END)"


@query(
    "overhead_combo",
    union_sql(SKEWED, lambda n: f"SELECT {s('greatest(' + ', '.join(f'max(r{i})' for i in range(len(_FAMILY))) + ')')} AS worst, {s('max(rc)')} AS combination FROM (SELECT " + ", ".join(f"(({x}) / sum(m * ({x})) OVER ()) / q AS r{i}" for i, x in enumerate(_FAMILY.values())) + f", ({_COMBO} / sum(m * {_COMBO}) OVER ()) / q AS rc FROM {q_sql(n, 'l1')} a) b"),
)
def overhead_combo(spark, d):
    family = [FF.moment(3), FF.moment(2), FF.threshold(4)]
    combo = FF.combination([(1, family[0]), (3, family[1]), (9, family[2])])
    out = []
    for n in SKEWED:
        v = hist(spark, d, n)
        a = O.family_overhead(v, family, 1.0).select(sig("emulation").alias("worst"))
        out.append((n, a.crossJoin(O.family_overhead(v, [combo], 1.0).select(sig("emulation").alias("combination")))))
    return union(out)


def _lp(p, q):
    base = "top" if p >= q else "bottom"
    bound = s(f"sum(m * pow(w / {base}, {q}))") if p >= q else "CAST(NULL AS DOUBLE)"
    return f"SELECT CAST({p} AS DOUBLE) AS p, CAST({q} AS DOUBLE) AS q, {s(f'sum(m * pow(w / {base}, {q})) / sum(m * pow(w / {base}, {p}))')} AS overhead, {bound} AS bound FROM (SELECT *, min(w) OVER () AS bottom FROM {{r}} z) a"


def _lp_query(name, pairs, bound=True):
    cols = "p, q, overhead" + (", bound" if bound else "")
    sql = union_sql(SKEWED, lambda n: f"SELECT {cols} FROM (" + " UNION ALL ".join(_lp(p, q).format(r=r_sql(n)) for p, q in pairs) + ") z")

    @query(name, sql)
    def run(spark, d):
        out = []
        for n in SKEWED:
            rows = O.lp_by_lq(hist(spark, d, n), pairs).withColumns({"overhead": sig("overhead"), "bound": F.when(F.col("bound").isNotNull(), sig("bound"))})
            out.append((n, rows if bound else rows.drop("bound")))
        return union(out)

    run.__name__ = name


_lp_query("overhead_lp_lq", [(3.0, 1.0), (10.0, 1.0), (3.0, 2.0), (10.0, 2.0), (2.0, 1.5)])
_lp_query("overhead_lq_bound", [(1.0, 1.0), (2.0, 2.0), (3.0, 3.0)])
_lp_query("overhead_low_p", [(0.5, 1.0), (1.0, 2.0)], bound=False)


@query("overhead_worst", union_sql(SKEWED, lambda n: f"SELECT CAST(sum(m) AS BIGINT) AS n, {s('pow(sum(m), 1 - 2.0 / 3)')} AS p3, {s('pow(sum(m), 1 - 2.0 / 10)')} AS p10 FROM {v_sql(n)} a"))
def overhead_worst(spark, d):
    return union((n, hist(spark, d, n).agg(F.sum("m").alias("n")).select("n", sig(O.worst_case_bound(F.col("n"), 3)).alias("p3"), sig(O.worst_case_bound(F.col("n"), 10)).alias("p10"))) for n in SKEWED)


_FLAT = ("supp_in", "event_props", "doc_source", "part_in")


@query("overhead_near_uniform", union_sql(_FLAT, lambda n: f"SELECT {s('pow(max(w) / min(w), 2)')} AS p2, {s('pow(max(w) / min(w), 3)')} AS p3 FROM {v_sql(n)} a"))
def overhead_near_uniform(spark, d):
    out = []
    for n in _FLAT:
        v = hist(spark, d, n)
        out.append((n, O.near_uniform_bound(v, 2).select(sig("bound").alias("p2")).crossJoin(O.near_uniform_bound(v, 3).select(sig("bound").alias("p3")))))
    return union(out)


@query(
    "overhead_concave",
    union_sql(("page_hosts", "cust_out"), lambda n: f"SELECT {s('max(worst)')} AS measured, {s('max(norm)')} AS bound FROM (SELECT t.w AS t, max((least(r.w, t.w) / t.s) / r.q) AS worst, max(r.norm) AS norm FROM (SELECT *, sum(m * v) OVER () AS norm FROM {q_sql(n, 'concave')} a) r, (SELECT x.w, sum(y.m * least(x.w, y.w)) AS s FROM {v_sql(n)} x, {v_sql(n)} y GROUP BY x.w) t GROUP BY t.w) z"),
)
def overhead_concave(spark, d):
    out = []
    for n in ("page_hosts", "cust_out"):
        v = hist(spark, d, n)
        q = O.chances(v, [], "concave").select("w", "m", "q")
        grid = v.select(F.col("w").alias("t"))
        sums = grid.crossJoin(v).groupBy("t").agg(F.sum(F.col("m") * F.least("w", "t")).alias("s"))
        worst = sums.crossJoin(q).agg(F.max(F.least("w", "t") / F.col("s") / F.col("q")).alias("measured"))
        norm = O.weighted(v, "concave").agg(F.sum(F.col("m") * F.col("v")).alias("bound"))
        out.append((n, worst.crossJoin(norm).select(sig("measured").alias("measured"), sig("bound").alias("bound"))))
    return union(out)


# -- heavy hitters, Zipf, combinations ----------------------------------------------------------


@query("heavy_hitters", f"SELECT key, CAST(w AS BIGINT) AS w, {s('share')} AS share FROM (SELECT *, w*w / sum(w*w) OVER () AS share FROM {f_sql('doc_words')} a) b WHERE share >= 0.01")
def heavy_hitters(spark, d):
    return C.heavy_hitters(freq(spark, d, "doc_words"), 2, 0.01).select("key", F.col("w").cast("bigint").alias("w"), sig("share").alias("share"))


@query("heavy_hitters_norm", f"SELECT key, CAST(w AS BIGINT) AS w FROM (SELECT *, sqrt(sum(w*w) OVER ()) AS norm FROM {f_sql('doc_words')} a) b WHERE w >= 0.1 * norm")
def heavy_hitters_norm(spark, d):
    return C.heavy_hitters(freq(spark, d, "doc_words"), 2, 0.1, "norm").select("key", F.col("w").cast("bigint").alias("w"))


def profile_sql(n):
    second = "CASE WHEN max(CASE WHEN i = 1 THEN m END) > 1 THEN max(w) ELSE max(CASE WHEN i = 2 THEN w END) END"
    second = f"coalesce({second}, max(w))"
    return f"""SELECT CAST(sum(m) AS BIGINT) AS n, {s('ln(sum(m))')} AS ln_n, {s('max(w) / sum(m*w)')} AS l1_first, {s(f'{second} / sum(m*w)')} AS l1_second,
      {s('max(w)*max(w) / sum(m*w*w)')} AS l2_first, {s(f'{second} * {second} / sum(m*w*w)')} AS l2_second,
      {s(f"(SELECT CASE WHEN max(w) > min(w) THEN -regr_slope(ln(w), ln(i)) ELSE 0.0 END FROM (SELECT w, row_number() OVER (ORDER BY w DESC) AS i FROM {f_sql(n)} f) g)")} AS alpha
      FROM (SELECT *, row_number() OVER (ORDER BY w DESC) AS i FROM {v_sql(n)} a) b"""


def profile(v):
    out = C.dataset_profile(v)
    flat = v.agg((F.max("w") == F.min("w")).alias("_flat"))
    cols = [sig(c).alias(c) for c in ("ln_n", "l1_first", "l1_second", "l2_first", "l2_second")]
    return out.crossJoin(F.broadcast(flat)).select("n", *cols, sig(F.when(F.col("_flat"), 0.0).otherwise(F.col("alpha"))).alias("alpha"))


@query("dataset_profile", profile_sql("doc_words"))
def dataset_profile(spark, d):
    return profile(hist(spark, d, "doc_words"))


@query("combo_hh", union_sql(SKEWED, lambda n: " UNION ALL ".join(f"SELECT CAST({q} AS DOUBLE) AS q, {s(f'1 / sum(m * pow(w / top, {q}))')} AS phi, {s(f'sum(m * pow(w / top, {q}))')} AS overhead, CAST(ceil(round(sum(m * pow(w / top, {q})) * 100, 6)) AS BIGINT) AS size FROM {r_sql(n)} a" for q in (1.0, 2.0))))
def combo_hh(spark, d):
    out = []
    for n in SKEWED:
        v = hist(spark, d, n)
        for q in (1.0, 2.0):
            out.append((n, C.heavy_hitter_combination(v, q, 0.1).select("q", sig("phi").alias("phi"), sig("overhead").alias("overhead"), "size")))
    return union(out)


def _certify(name, q, weight):
    x = "w" if q == 1 else "w*w"
    sql = f"SELECT {s('r')} AS r, {s('64 * r')} AS certified, {s('1 - exp(-64 * r)')} AS chance FROM (SELECT max({x}) / (SELECT sum({x}) FROM {f_sql('doc_words')} a) AS r FROM {sample_sql(f_sql('doc_words'), weight, 64)} x) y"

    @query(name, sql)
    def run(spark, d):
        w = freq(spark, d, "doc_words")
        norm = w.agg(F.sum(FF.power(F.col("w"), q))).first()[0]
        return C.certify(B.ppswor(w, 64, q), q, norm, 64).select(*[sig(c).alias(c) for c in ("r", "certified", "chance")])

    run.__name__ = name


_certify("certify_l1", 1, "w")
_certify("certify_l2", 2, "w*w")
_QS = (0.5, 1.0, 1.5, 2.0, 3.0)


@query("tradeoff_q", union_sql(SKEWED, lambda n: " UNION ALL ".join(f"SELECT CAST({q} AS DOUBLE) AS q, {s(f'1 / sum(m * pow(w / top, {q}))')} AS phi, {s(f'sum(m * pow(w / top, {q}))')} AS overhead FROM {r_sql(n)} a" for q in _QS)))
def tradeoff_q(spark, d):
    return union((n, C.tradeoff(hist(spark, d, n), _QS).select("q", sig("phi").alias("phi"), sig("overhead").alias("overhead"))) for n in SKEWED)


@query("zipf_gen", f"SELECT key, {s('top * pow(i, -1.25)')} AS w FROM (SELECT key, max(w) OVER () AS top, row_number() OVER (ORDER BY w DESC, key) AS i FROM {f_sql('cust_out')} f) a")
def zipf_gen(spark, d):
    return C.zipf_like(freq(spark, d, "cust_out"), 1.25).select("key", sig("w").alias("w"))


@query("zipf_fit", union_sql(SKEWED, lambda n: f"SELECT {s('-regr_slope(ln(w), ln(i))')} AS alpha, {s('-regr_slope(CASE WHEN i <= 50 THEN ln(w) END, ln(i))')} AS alpha_top FROM (SELECT w, row_number() OVER (ORDER BY w DESC) AS i FROM {f_sql(n)} f) g"))
def zipf_fit(spark, d):
    out = []
    for n in SKEWED:
        v = hist(spark, d, n)
        out.append((n, C.fit_zipf(v).select(sig("alpha").alias("alpha")).crossJoin(C.fit_zipf(v, 50).select(sig("alpha").alias("alpha_top")))))
    return union(out)


@query("subzipf_c", union_sql(SKEWED, lambda n: f"SELECT {s('max(w / top * last_rank)')} AS c1, {s('max(w / top * pow(last_rank, 2))')} AS c2 FROM {r_sql(n)} a"))
def subzipf_c(spark, d):
    out = []
    for n in SKEWED:
        v = hist(spark, d, n)
        out.append((n, C.subzipf_c(v, 1).select(sig("c").alias("c1")).crossJoin(C.subzipf_c(v, 2).select(sig("c").alias("c2")))))
    return union(out)


@query("harmonic", " UNION ALL ".join(f"SELECT CAST({x} AS DOUBLE) AS s, {s(f'sum(pow(i, -{x}))')} AS value FROM (SELECT row_number() OVER (ORDER BY w DESC, key) AS i FROM {f_sql('cust_out')} f) a" for x in (0.5, 1.0, 2.0)))
def harmonic(spark, d):
    return C.harmonic_terms(freq(spark, d, "cust_out"), (0.5, 1.0, 2.0)).select("s", sig("value").alias("value"))


_PHIS = ((1.0, 1.0), (2.0, 1.0), (0.5, 2.0), (1.0, 2.0))


@query("subzipf_phi", " UNION ALL ".join(f"SELECT CAST({a} AS DOUBLE) AS alpha, CAST({q} AS DOUBLE) AS q, {s(f'1 / (pow(max(w / top * pow(i, {a})), {q}) * sum(pow(i, -{a * q})))')} AS phi FROM (SELECT w, max(w) OVER () AS top, row_number() OVER (ORDER BY w DESC) AS i FROM {f_sql('cust_out')} f) x" for a, q in _PHIS))
def subzipf_phi(spark, d):
    """With the least c that holds on the table's vector, and its number of keys."""
    v = hist(spark, d, "cust_out")
    n = v.agg(F.sum("m")).first()[0]
    out = None
    for a, q in _PHIS:
        phi = C.subzipf_phi(1.0, a, n, q) / F.pow(F.col("c"), F.lit(q))
        one = C.subzipf_c(v, a).select(F.lit(a).alias("alpha"), F.lit(q).alias("q"), sig(phi).alias("phi"))
        out = one if out is None else out.union(one)
    return out


def combo_table_sql(n):
    rows = []
    for q, a, least, fixed in C.SUPPORTED:
        factor = "1.65" if fixed else "(1 + ln(sum(m)))"
        c = f"max(w / top * pow(last_rank, {a}))"
        rows.append(f"SELECT CAST({q} AS DOUBLE) AS q, CAST({a} AS DOUBLE) AS alpha, CAST({least} AS DOUBLE) AS least_p, {s(c)} AS c, {s(f'{factor} * pow({c}, {q})')} AS bound, {s(f'sum(m * pow(w / top, {q})) / sum(m * pow(w / top, 3))')} AS measured FROM {r_sql(n)} a")
    return " UNION ALL ".join(rows)


def combo_rows(v):
    return C.supported_combinations(v).select("q", "alpha", "least_p", *[sig(c).alias(c) for c in ("c", "bound", "measured")])


@query("combo_table", union_sql(SKEWED, combo_table_sql))
def combo_table(spark, d):
    return union((n, combo_rows(hist(spark, d, n))) for n in SKEWED)


_ALPHAS = (0.5, 0.75, 1.0, 1.25, 1.5, 2.0)


@query("zipf_universal", " UNION ALL ".join(f"SELECT CAST({a} AS DOUBLE) AS alpha, {s('max(1 / (i * q))')} AS universal, {s('sum(1.0 / i)')} AS h_n FROM (SELECT i, pow(pow(i, -{a}), {1 / a}) / sum(pow(pow(i, -{a}), {1 / a})) OVER () AS q FROM (SELECT row_number() OVER (ORDER BY w DESC, key) AS i FROM {f_sql('supp_in')} f) x) y" for a in _ALPHAS))
def zipf_universal(spark, d):
    out = None
    ranks = cut(X.global_rank(freq(spark, d, "supp_in")))
    for a in _ALPHAS:
        v = cut(X.histogram(C.zipf_like(ranks, a, 1.0)))
        n = v.agg(F.sum("m").alias("n"))
        one = C.zipf_universal(v, a).crossJoin(n).select(F.lit(a).alias("alpha"), sig("universal").alias("universal"), sig(U.harmonic(F.col("n"))).alias("h_n"))
        out = one if out is None else out.union(one)
    return out


# -- universal samples ----------------------------------------------------------------------------

_IDEAL = f"(SELECT key, w, i, 1.0 / i AS v, 1.0 / i / sum(1.0 / i) OVER () AS p FROM (SELECT key, w, row_number() OVER (ORDER BY w DESC, key) AS i FROM {f_sql('conv_words')} a) b)"


@query("universal_probs", f"SELECT key, CAST(i AS BIGINT) AS rank, {s('p')} AS p FROM {_IDEAL} x")
def universal_probs(spark, d):
    return U.universal_probabilities(freq(spark, d, "conv_words")).select("key", F.col("rank").cast("bigint").alias("rank"), sig("p").alias("p"))


@query("universal_sample", f"SELECT key, {s('w')} AS w, {s('seed')} AS seed, {s('p_incl')} AS p_incl FROM {sample_sql(_IDEAL, 'v', KS)} x")
def universal_sample(spark, d):
    return U.universal_sample(freq(spark, d, "conv_words"), KS).select("key", *[sig(c).alias(c) for c in ("w", "seed", "p_incl")])


_UNI = ("page_hosts", "cust_out", "doc_lines", "doc_source", "event_tuple")
_SCHEMES = (("l0", "uniform"), ("l1", 1.0), ("l2", 2.0), ("concave", "concave"))


def _universal(name, column, body, make):
    sql = "\nUNION ALL ".join(f"SELECT '{n}' AS dataset, '{k}' AS scheme, t.* FROM ({body(q_sql(n, k))}) t" for n in _UNI for k, _ in _SCHEMES)

    @query(name, sql)
    def run(spark, d):
        out = []
        for n in _UNI:
            v = hist(spark, d, n)
            for k, scheme in _SCHEMES:
                out.append((n, make(v, scheme).select(F.lit(k).alias("scheme"), sig(column).alias(column))))
        return union(out)

    run.__name__ = name


_universal("universal_emulation", "universal", lambda q: f"SELECT {s('max(1 / (first_rank * q))')} AS universal FROM {q} a", lambda v, x: U.universal_emulation(v, x))
_universal("universal_emulation_ties", "universal", lambda q: f"SELECT {s('max(1 / (last_rank * q))')} AS universal FROM {q} a", lambda v, x: U.universal_emulation(v, x, "exact"))
_universal("universal_brute", "universal", lambda q: f"SELECT {s('max(worst / n)')} AS universal FROM (SELECT t.w, sum(r.m) AS n, max(1 / r.q) AS worst FROM {q} t JOIN {q} r ON r.w >= t.w GROUP BY t.w) z", lambda v, x: U.universal_bruteforce(v, x))
_universal(
    "universal_estimation",
    "estimation",
    lambda q: f"SELECT {s('max(a / (i * i))')} AS estimation FROM (SELECT i, sum(1 / q) OVER (ORDER BY i) AS a FROM (SELECT q, row_number() OVER (ORDER BY w DESC) AS i FROM (SELECT w, q, unnest(range(0, CAST(m AS BIGINT))) AS j FROM {q} a) b) c) e",
    lambda v, x: U.universal_estimation(v, x),
)


@query("universal_tail", union_sql(_UNI, lambda n: f"SELECT {s('norm')} AS norm, {s('c')} AS c, {s('norm * (1 + 1 / c)')} AS bound FROM (SELECT max(norm) AS norm, min(CASE WHEN tail + (m - 1) * w > 0 THEN first_rank * w / (tail + (m - 1) * w) END) AS c FROM (SELECT *, sum(m * v) OVER () AS norm FROM {q_sql(n, 'concave')} a) b) z"))
def universal_tail(spark, d):
    return union((n, U.concave_universal_bound(hist(spark, d, n)).select(*[sig(c).alias(c) for c in ("norm", "c", "bound")])) for n in _UNI)


def table_sql(n):
    """Emulation and estimation overheads of l1, l2 for moments 3 and 10, universal overheads, norm and H_n."""
    x = {3: "u*u*u", 10: "pow(u, 10)"}
    cols = []
    for k in ("l1", "l2"):
        for p in (3, 10):
            cols.append(f"(SELECT {s('max(r)')} FROM (SELECT (({x[p]}) / sum(m * ({x[p]})) OVER ()) / q AS r FROM {q_sql(n, k)} a) b) AS {k}_{p}")
            cols.append(f"(SELECT {s('sum(sh * r)')} FROM (SELECT m * ({x[p]}) / sum(m * ({x[p]})) OVER () AS sh, (({x[p]}) / sum(m * ({x[p]})) OVER ()) / q AS r FROM {q_sql(n, k)} a) b) AS {k}_{p}_est")
    for k in ("l1", "l2", "concave"):
        cols.append(f"(SELECT {s('max(1 / (first_rank * q))')} FROM {q_sql(n, k)} a) AS {k}_universal")
    cols.append(f"(SELECT {s('sum(m * v)')} FROM {q_sql(n, 'concave')} a) AS concave_norm")
    cols.append(f"(SELECT {s('sum(1.0 / i)')} FROM (SELECT row_number() OVER () AS i FROM {f_sql(n)} a) b) AS h_n")
    return "SELECT " + ", ".join(cols)


def overhead_row(v):
    """One row of all overheads of a histogram."""
    names = [f"{k}_{p}{e}" for k in ("l1", "l2") for p in (3, 10) for e in ("", "_est")] + [f"{k}_universal" for k in ("l1", "l2", "concave")] + ["concave_norm"]
    return O.all_overheads(v, (3, 10)).select(*[sig(c).alias(c) for c in names], "n", sig(U.harmonic(F.col("n"))).alias("h_n")).drop("n")


@query("overhead_table", union_sql(("page_hosts", "cust_out"), table_sql))
def overhead_table(spark, d):
    return union((n, overhead_row(hist(spark, d, n))) for n in ("page_hosts", "cust_out"))


# -- rank curves -------------------------------------------------------------------------------------

_RC = f"(SELECT key, w, sum(1 / p_incl) OVER (ORDER BY w DESC) AS rank_hat FROM {sample_sql(f_sql('doc_words'), 'w', 128)} x)"


@query("rank_curve_ppswor", f"SELECT key, CAST(w AS BIGINT) AS w, {s('rank_hat')} AS rank_hat FROM {_RC} x")
def rank_curve_ppswor(spark, d):
    return R.rank_curve(B.ppswor(freq(spark, d, "doc_words"), 128)).select("key", F.col("w").cast("bigint").alias("w"), sig("rank_hat").alias("rank_hat"))


@query("rank_curve_wr_l2", f"SELECT key, CAST(w AS BIGINT) AS w, {s('sum(1 / p_incl) OVER (ORDER BY w DESC)')} AS rank_hat FROM {drawn_sql(f_sql('doc_words'), 2, 128)} x")
def rank_curve_wr_l2(spark, d):
    curve = R.rank_curve(wr.pps_wr(freq(spark, d, "doc_words"), FF.moment(2), 128))
    return curve.select("key", F.col("w").cast("bigint").alias("w"), sig("rank_hat").alias("rank_hat"))


@query("rank_curve_true", f"SELECT CAST(w AS BIGINT) AS w, CAST(last_rank AS BIGINT) AS rank FROM {r_sql('doc_words')} a")
def rank_curve_true(spark, d):
    return R.rank_curve_true(hist(spark, d, "doc_words")).select(F.col("w").cast("bigint").alias("w"), "rank")


@query("rank_curve_error", f"SELECT CAST(count(*) AS BIGINT) AS points, {s('avg(e)')} AS mean_error, {s('max(e)')} AS max_error, {s('min(w)')} AS lowest FROM (SELECT x.w, abs(ln(x.rank_hat / r.last_rank)) AS e FROM (SELECT DISTINCT w, rank_hat FROM {_RC} a) x JOIN {r_sql('doc_words')} r ON r.w = x.w) z")
def rank_curve_error(spark, d):
    return R.rank_curve_error(B.ppswor(freq(spark, d, "doc_words"), 128), hist(spark, d, "doc_words")).select("points", *[sig(c).alias(c) for c in ("mean_error", "max_error", "lowest")])


_TS = (1, 2, 5, 10, 100, 1000)


@query("threshold_curve", " UNION ALL ".join(f"SELECT CAST({t} AS DOUBLE) AS t, {s(f'sum(CASE WHEN w >= {t} THEN 1 / p_incl ELSE 0 END)')} AS estimate FROM {sample_sql(f_sql('doc_words'), 'w', 128)} x" for t in _TS))
def threshold_curve(spark, d):
    return R.threshold_curve(B.ppswor(freq(spark, d, "doc_words"), 128), _TS).select("t", sig("estimate").alias("estimate"))


# -- measures ------------------------------------------------------------------------------------------


_ERRORS = f"""(SELECT run, sum(CASE WHEN rn < 64 OR tau IS NULL THEN w*w*w / (CASE WHEN tau IS NULL THEN 1 ELSE 1 - exp(-w * tau) END) END) / max(t) - 1 AS error FROM (
    SELECT *, max(CASE WHEN rn = 64 THEN seed END) OVER (PARTITION BY run) AS tau FROM (
      SELECT *, row_number() OVER (PARTITION BY run ORDER BY seed, key) AS rn FROM (
        SELECT run, key, w, sum(w*w*w) OVER (PARTITION BY run) AS t, -ln(1 - {u_sql('CAST(run AS VARCHAR)')}) / w AS seed FROM {f_sql('conv_words')} a, (SELECT unnest(range(0, 50)) AS run) r) b) c WHERE rn <= 64) e GROUP BY run)"""


def _run_errors(spark, d):
    return M.empirical_errors(cut(freq(spark, d, "conv_words")), 1, 64, FF.moment(3), 50)


@query("nrmse_empirical", f"SELECT {s('sqrt(avg(error * error))')} AS nrmse, {s('avg(error)')} AS bias FROM {_ERRORS} x")
def nrmse_empirical(spark, d):
    return M.empirical_nrmse(_run_errors(spark, d)).select(sig("nrmse").alias("nrmse"), sig("bias").alias("bias"))


_WITHIN = ", ".join(f"{s(f'avg(CASE WHEN abs(error) <= {z} * rms THEN 1.0 ELSE 0.0 END)')} AS within_{z}" for z in (1, 2))


@query("error_quantiles", "SELECT " + ", ".join(f"{s(f'quantile_cont(abs(error), {x})')} AS q{int(100 * x)}" for x in (0.5, 0.9, 0.95)) + f", {_WITHIN} FROM (SELECT error, sqrt(avg(error * error) OVER ()) AS rms FROM {_ERRORS} x) y")
def error_quantiles(spark, d):
    found = M.error_quantiles(_run_errors(spark, d))
    return found.select(*[sig(c).alias(c) for c in found.columns])


_NK = (32, 128, 512)


def wr_nrmse_sql(n, k, scheme, x):
    return f"SELECT {s(f'sqrt(sum(m * p * p * (1 / (1 - pow(1 - q, {k})) - 1)))')} AS nrmse FROM (SELECT m, q, ({x}) / sum(m * ({x})) OVER () AS p FROM {q_sql(n, scheme)} a) b"


@query("nrmse_wr", "\nUNION ALL ".join(f"SELECT '{sc}' AS scheme, CAST({k} AS BIGINT) AS k, t.* FROM ({wr_nrmse_sql('page_hosts', k, sc, 'u*u*u')}) t" for sc in ("l1", "l2") for k in _NK))
def nrmse_wr(spark, d):
    v = hist(spark, d, "page_hosts")
    rows = [M.wr_nrmse(v, FF.moment(3), q, _NK).select(F.lit(n).alias("scheme"), "k", sig("nrmse").alias("nrmse")) for n, q in (("l1", 1.0), ("l2", 2.0))]
    return rows[0].union(rows[1])


def wor_nrmse_sql(rows: str, weight: str, ks, fs: dict[str, str], runs: int) -> str:
    """(k, f, nrmse) of bottom-k samples of ``rows`` (key, w), averaged over runs."""
    marks = ", ".join(f"max(CASE WHEN rn = {k} THEN seed END) OVER (PARTITION BY run) AS a{k}, max(CASE WHEN rn = {k - 1} THEN seed END) OVER (PARTITION BY run) AS b{k}" for k in ks)
    truth = ", ".join(f"sum(CASE WHEN run = 0 THEN {x} END) OVER () AS t{j}" for j, x in enumerate(fs.values()))
    base = f"(SELECT *, {marks}, {truth} FROM (SELECT *, row_number() OVER (PARTITION BY run ORDER BY seed, key) AS rn FROM (SELECT run, key, w, ({weight}) AS weight, -ln(1 - {u_sql('CAST(run AS VARCHAR)')}) / ({weight}) AS seed FROM {rows} a, (SELECT unnest(range(0, {runs})) AS run) r) b) c)"
    out = []
    for k in ks:
        tau = f"CASE WHEN rn <= {k - 1} THEN a{k} ELSE b{k} END"
        p = f"CASE WHEN ({tau}) IS NULL THEN 1 ELSE 1 - exp(-weight * ({tau})) END"
        for j, (f, x) in enumerate(fs.items()):
            out.append(f"SELECT CAST({k} AS BIGINT) AS k, '{f}' AS f, {s(f'sqrt(sum(pow(({x}) / t{j}, 2) * (1 / ({p}) - 1)) / {runs})')} AS nrmse FROM base")
    return f"WITH base AS {base} " + " UNION ALL ".join(out)


_NF = {"moment_3": "w*w*w", "moment_10": "pow(w, 10)"}


def _wor(name, q, weight):
    @query(name, wor_nrmse_sql(f_sql("conv_words"), weight, (32, 128), _NF, 5))
    def run(spark, d):
        return M.conditional_nrmse(freq(spark, d, "conv_words"), q, (32, 128), [FF.moment(3), FF.moment(10)], 5).select("k", "f", sig("nrmse").alias("nrmse"))

    run.__name__ = name


_wor("nrmse_ppswor", 1, "w")
_wor("nrmse_l2wor", 2, "w*w")


@query("practicality", union_sql(SKEWED, lambda n: f"SELECT CAST(ceil(round(h * 100, 6)) AS BIGINT) AS size, {s('ceil(round(h * 100, 6)) / n')} AS share, ceil(round(h * 100, 6)) < 0.1 * n AS practical FROM (SELECT max(1 / (first_rank * q)) AS h, sum(m) AS n FROM {q_sql(n, 'l1')} a) b"))
def practicality(spark, d):
    out = []
    for n in SKEWED:
        v = hist(spark, d, n)
        h = F.ceil(F.round(F.col("universal") * 100, 6))
        out.append((n, U.universal_emulation(v, 1.0).crossJoin(v.agg(F.sum("m").alias("n"))).select(h.cast("bigint").alias("size"), sig(h / F.col("n")).alias("share"), (h < 0.1 * F.col("n")).alias("practical"))))
    return union(out)


@query("space_bounds", " UNION ALL ".join(f"SELECT CAST(sum(m) AS BIGINT) AS n, CAST({p} AS DOUBLE) AS p, {s(f'pow(sum(m), 1 - 2.0 / {p})')} AS worst, {s(f'pow(sum(m), 0.5 - 1.0 / {p})')} AS with_oracle, {s('ln(sum(m))')} AS concave FROM {v_sql('doc_words')} a" for p in (3.0, 10.0)))
def space_bounds(spark, d):
    return M.space_bounds(hist(spark, d, "doc_words"), (3.0, 10.0)).select("n", "p", *[sig(c).alias(c) for c in ("worst", "with_oracle", "concave")])


# -- baselines --------------------------------------------------------------------------------------------


def _baseline(name, weight, make):
    sql = f"SELECT {s('sum(w*w*w / p_incl)')} AS estimate, CAST(count(*) AS BIGINT) AS keys FROM {sample_sql(weight[1], weight[0], KS)} x"

    @query(f"baseline_{name}", sql)
    def run(spark, d):
        rows = make(freq(spark, d, "conv_words"))
        return rows.agg(sig(F.sum(F.col("w") * F.col("w") * F.col("w") / F.col("p_incl"))).alias("estimate"), F.count("*").alias("keys"))

    run.__name__ = f"baseline_{name}"


_CW = f_sql("conv_words")
_baseline("ppswor", ("w", _CW), lambda w: B.ppswor(w, KS))
_baseline("l2_wor", ("w*w", _CW), lambda w: B.ppswor(w, KS, 2))
_baseline("ideal_wor", ("w*w*w", _CW), lambda w: B.ppswor(w, KS, 3))
_baseline("uniform", ("1.0", _CW), lambda w: B.uniform(w, KS))
_baseline("concave", ("v", _CONC), lambda w: K.concave_sample(w, KS))
_baseline("universal", ("v", _IDEAL), lambda w: U.universal_sample(w, KS))


@query("baseline_full", f"SELECT CAST(sum(w*w*w) AS BIGINT) AS value, CAST(count(*) AS BIGINT) AS keys FROM {_CW} a")
def baseline_full(spark, d):
    """In whole numbers: a sum of doubles beyond 2^53 depends on its order."""
    n = F.col("w").cast("decimal(19,0)")
    return freq(spark, d, "conv_words").agg(F.sum((n * n * n).cast("decimal(38,0)")).cast("bigint").alias("value"), F.count("*").alias("keys"))


def _baseline_wr(name, p):
    @query(f"baseline_{name}", f"SELECT {s('sum(w*w*w / p_incl)')} AS estimate, CAST(count(*) AS BIGINT) AS keys FROM {drawn_sql(_CW, p, KS)} x")
    def run(spark, d):
        rows = wr.pps_wr(freq(spark, d, "conv_words"), FF.moment(p), KS)
        return rows.agg(sig(F.sum(FF.power(F.col("w"), 3) / F.col("p_incl"))).alias("estimate"), F.count("*").alias("keys"))

    run.__name__ = f"baseline_{name}"


_baseline_wr("l1_wr", 1)
_baseline_wr("l2_wr", 2)
_baseline_wr("ideal_wr", 3)


@query("baseline_theory", " UNION ALL ".join(f"SELECT CAST(sum(m) AS BIGINT) AS n, CAST({p} AS DOUBLE) AS p, {s(f'pow(sum(m), 1 - 2.0 / {p})')} AS worst, {s(f'pow(sum(m), 0.5 - 1.0 / {p})')} AS with_oracle FROM {v_sql('conv_words')} a" for p in (3.0, 10.0)))
def baseline_theory(spark, d):
    return M.space_bounds(hist(spark, d, "conv_words"), (3.0, 10.0)).select("n", "p", sig("worst").alias("worst"), sig("with_oracle").alias("with_oracle"))
