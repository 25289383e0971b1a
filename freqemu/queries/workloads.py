"""The experiment workloads on the given tables; each gives one row for each data set, scheme, moment and size."""

from __future__ import annotations

from pyspark.sql import functions as F

from ..functions.frequency import moment, power
from ..operators import bottomk as B
from ..operators import combos as C
from ..operators import measures as M
from ..operators import overhead as O
from ..operators import rankcurve as R
from ..operators import universal as U
from ..operators import wr
from ..operators.exact import frequencies, histogram, self_join_size
from ..plans.lineage import cut
from ..plans.registry import query
from ..sources.tables import edges, elements, lines, load, to_elements, tokens
from .advice import ROWS, advice_error_sql, advice_errors, between, rows_of
from .methods import DATASETS, combo_rows, combo_table_sql, overhead_row, profile, profile_sql, table_sql, wor_nrmse_sql
from .sql import drawn_sql, f_sql, freq, hist, q_sql, s, sample_sql, sig, union, union_sql, v_sql


def _table(name, sql, make):
    @query(name, f"SELECT key, CAST(w AS BIGINT) AS w FROM ({sql}) a")
    def run(spark, d):
        return frequencies(make(spark, d)).select("key", F.col("w").cast("bigint").alias("w"))

    run.__name__ = name


def _count(body, key):
    return f"SELECT {key} AS key, count(*) AS w FROM {body} GROUP BY 1"


_EDGES = "orders JOIN lineitem ON l_orderkey = o_orderkey"
_SLICE = "events WHERE ts >= TIMESTAMP '2024-01-10 00:00:00' AND ts < TIMESTAMP '2024-01-12 00:00:00'"

_table("wl_doc_words", f_sql("doc_words"), lambda spark, d: tokens(load(spark, d, "documents")))
_table("wl_conv_words", f_sql("conv_words"), lambda spark, d: tokens(load(spark, d, "conversations")))
_table("wl_doc_lines", f_sql("doc_lines"), lambda spark, d: lines(load(spark, d, "documents")))
_table("wl_event_tuples", _count(_SLICE, "concat_ws('|', user_id, event_type, props)"), lambda spark, d: to_elements(load(spark, d, "events").where(between("ts", "2024-01-10", "2024-01-12")), ["user_id", "event_type", "props"]))
_table("wl_li_tuples", f_sql("li_tuple"), lambda spark, d: elements(spark, d, "li_tuple"))
_table("wl_out_degree", _count(_EDGES, "CAST(o_custkey AS VARCHAR)"), lambda spark, d: to_elements(edges(spark, d), ["src"]))
_table("wl_in_degree", _count(_EDGES, "CAST(l_suppkey AS VARCHAR)"), lambda spark, d: to_elements(edges(spark, d), ["dst"]))
_table("wl_part_degree", _count(_EDGES, "CAST(l_partkey AS VARCHAR)"), lambda spark, d: to_elements(edges(spark, d), ["part"]))
_table(
    "wl_pair_volume",
    "SELECT concat_ws('|', l_suppkey, l_partkey) AS key, sum(l_quantity) AS w FROM lineitem WHERE l_returnflag <> 'R' AND l_shipdate >= TIMESTAMP '1997-05-01 00:00:00' AND l_shipdate < TIMESTAMP '1997-08-01 00:00:00' GROUP BY 1",
    lambda spark, d: to_elements(load(spark, d, "lineitem").where((F.col("l_returnflag") != "R") & between("l_shipdate", "1997-05-01", "1997-08-01")), ["l_suppkey", "l_partkey"], "l_quantity"),
)


@query("wl_table1", union_sql(DATASETS, profile_sql))
def wl_table1(spark, d):
    return union((n, profile(hist(spark, d, n))) for n in DATASETS)


_TABLE2 = ("doc_words", "conv_words", "doc_lines", "page_hosts", "cust_out", "supp_in", "ps_qty", "event_tuple", "doc_source")


@query("wl_table2", union_sql(_TABLE2, table_sql))
def wl_table2(spark, d):
    return union((n, overhead_row(hist(spark, d, n))) for n in _TABLE2)


_ERRORS, _EK, _RUNS = ("doc_words", "conv_words", "doc_lines", "event_tuple", "cust_out", "ps_qty"), (32, 128), 5


def _error_sql(rows, ks, runs, moments=(3, 10)):
    f = {f"moment_{p}": "w*w*w" if p == 3 else f"pow(w, {p})" for p in moments}
    parts = [f"SELECT '{sc}' AS scheme, t.* FROM ({wor_nrmse_sql(rows, w, ks, f, runs)}) t" for sc, w in (("ppswor", "w"), ("l2_wor", "w*w"))]
    for sc, q in (("l1_wr", 1), ("l2_wr", 2)):
        for p in moments:
            shares = f"(SELECT pow(u, {q}) / sum(pow(u, {q})) OVER () AS q, pow(u, {p}) / sum(pow(u, {p})) OVER () AS p FROM (SELECT w / max(w) OVER () AS u FROM {rows} a) b)"
            parts += [f"SELECT '{sc}' AS scheme, CAST({k} AS BIGINT) AS k, 'moment_{p}' AS f, {s(f'sqrt(sum(p * p * (1 / (1 - pow(1 - q, {k})) - 1)))')} AS nrmse FROM {shares} c" for k in ks]
    parts += [f"SELECT 'bound' AS scheme, CAST({k} AS BIGINT) AS k, '{x}' AS f, {s(f'1 / sqrt({k})')} AS nrmse" for k in ks for x in f]
    return " UNION ALL ".join(parts)


def moment_errors(w, v, ks, runs, moments=(3, 10)):
    """(scheme, k, f, nrmse): without and with replacement by l_1 and l_2, and the bound of ideal sampling."""
    fs = [moment(p) for p in moments]
    both = M.conditional_nrmse_by(w, (1, 2), ks, fs, runs)
    rows = both.select(F.when(F.col("q") == 1, "ppswor").otherwise("l2_wor").alias("scheme"), "k", "f", sig("nrmse").alias("nrmse"))
    drawn = M.wr_nrmse_by(v, (1, 2), ks, moments).select(F.format_string("l%d_wr", F.col("q").cast("int")).alias("scheme"), "k", "f", sig("nrmse").alias("nrmse"))
    ideal = M.benchmark_curve(w.sparkSession, ks).select(F.lit("bound").alias("scheme"), "k", F.explode(F.array(*[F.lit(f.name) for f in fs])).alias("f"), sig("nrmse").alias("nrmse"))
    return rows.unionByName(drawn).unionByName(ideal)


#: The reference's grid: runs, sizes (those below half the keys are taken) and moments.
FULL_RUNS, FULL_SIZES, FULL_MOMENTS = 50, tuple(2**i for i in range(5, 13)), (3, 7, 10)


def full_moment_errors(spark, d, name, runs=FULL_RUNS, sizes=FULL_SIZES, moments=FULL_MOMENTS):
    """The whole experiment on one data set: (scheme, k, f, nrmse)."""
    w = cut(freq(spark, d, name))
    n = w.count()
    return moment_errors(w, cut(histogram(w)), [k for k in sizes if 2 * k < n] or [min(sizes)], runs, moments)


def full_past_advice(spark, d, name, runs=FULL_RUNS, sizes=FULL_SIZES, moments=FULL_MOMENTS):
    """Advice with half and with 32 of its k keys uniform, beside the schemes without advice: (scheme, k, f, nrmse)."""
    rows = cut(rows_of(spark, d, name))
    n = rows.count()
    ks = [k for k in sizes if k > 32 and 2 * k < n] or [64]
    return advice_beside(rows, sorted({(k - u, u) for k in ks for u in (32, k // 2)}), moments, runs)


@query("wl_moment_error", "\nUNION ALL ".join(f"SELECT '{n}' AS dataset, t.* FROM ({_error_sql(f_sql(n), _EK, _RUNS)}) t" for n in _ERRORS))
def wl_moment_error(spark, d):
    out = []
    for n in _ERRORS:
        w = cut(freq(spark, d, n))
        out.append((n, moment_errors(w, cut(histogram(w)), _EK, _RUNS)))
    return union(out)


_SIZES = ((32, 32), (96, 32), (64, 64))
_PAST, _POWERS = ("cust", "supp", "events", "words"), (3, 7, 10)


def advice_beside(rows, sizes, moments, runs):
    """(scheme, k, f, nrmse): sampling by advice for sizes (k_p, k_u), and every scheme without advice at the same k."""
    w = rows.select("key", "w")
    out = moment_errors(w, cut(histogram(w)), sorted({kp + ku for kp, ku in sizes}), runs, moments)
    for p in moments:
        one = advice_errors(rows, p, sizes, runs)
        out = out.unionByName(one.select(F.concat(F.lit("advice_u"), F.col("k_uniform")).alias("scheme"), "k", "f", "nrmse"))
    return out


def _beside_sql(rows, sizes, moments, runs):
    ks = sorted({kp + ku for kp, ku in sizes})
    parts = [f"SELECT 'advice_u' || k_uniform AS scheme, k, f, nrmse FROM ({advice_error_sql(rows, sizes, p, runs)}) t" for p in moments]
    return " UNION ALL ".join([f"SELECT * FROM ({_error_sql(rows, ks, runs, moments)}) t", *parts])


@query("wl_past_advice", "\nUNION ALL ".join(f"SELECT '{n}' AS dataset, t.* FROM ({_beside_sql(ROWS[n], _SIZES, _POWERS, 3)}) t" for n in _PAST))
def wl_past_advice(spark, d):
    return union((n, advice_beside(cut(rows_of(spark, d, n)), _SIZES, _POWERS, 3)) for n in _PAST)


_LATER = (50, 80)


@query("wl_learned_advice")
def wl_learned_advice(spark, d):
    """Days are hashes of the document; learnt on days 0 to 4, evaluated on days 50 and 80 apart, beside baselines."""
    from ..operators.advice import attach
    from ..operators.advice_models import learned_advice

    docs = load(spark, d, "documents").select("doc_id", "text").withColumn("day", F.pmod(F.xxhash64("doc_id"), F.lit(92)))

    def day(low, high):
        rows = docs.where(F.col("day").between(low, high)).select("doc_id", F.explode(F.array_distinct(F.regexp_extract_all(F.lower("text"), F.lit(r"[\p{L}\p{N}]+"), F.lit(0)))).alias("key"))
        return rows.select("key", F.lit(1.0).alias("value"))

    past, train, recent = cut(frequencies(day(0, 2))), cut(frequencies(day(3, 4))), cut(frequencies(day(0, 4)))
    sizes = [(0, 32, 32), (0, 96, 32), (0, 64, 64)]
    out = None
    for later in _LATER:
        target = cut(frequencies(day(later, later)))
        rows = cut(attach(target, learned_advice(train, past, target, recent, rounds=5)))
        one = moment_errors(target, cut(histogram(target)), (64, 128), 5, _POWERS)
        for p in _POWERS:
            one = one.unionByName(M.conditional_nrmse_advice(rows, moment(p), sizes, 5).select(F.concat(F.lit("advice_u"), F.col("k_uniform")).alias("scheme"), "k", "f", sig("nrmse").alias("nrmse")))
        one = one.select(F.lit(later).alias("day"), "scheme", "k", "f", "nrmse")
        out = one if out is None else out.unionByName(one)
    return out


_RCD, _RCK = ("doc_words", "doc_lines", "cust_out"), (32, 1024)


@query(
    "wl_rank_curves",
    "\nUNION ALL ".join(
        f"SELECT '{n}' AS dataset, CAST({k} AS BIGINT) AS k, {s('w')} AS w, {s('max(rank_hat)')} AS rank_hat, CAST(max(r.rank) AS BIGINT) AS rank FROM (SELECT w, sum(1 / p_incl) OVER (ORDER BY w DESC) AS rank_hat FROM {sample_sql(f_sql(n), 'w', k)} x) y JOIN (SELECT w AS rw, sum(m) OVER (ORDER BY w DESC) AS rank FROM {v_sql(n)} v) r ON r.rw = y.w GROUP BY w"
        for n in _RCD for k in _RCK
    ),
)
def wl_rank_curves(spark, d):
    out = []
    for n in _RCD:
        w = cut(freq(spark, d, n))
        true = R.rank_curve_true(cut(histogram(w)))
        out += [(n, _curve_rows(B.ppswor(w, k), true, k)) for k in _RCK]
    return union(out)


def _curve_rows(sample, true, k):
    """(k, w, rank_hat, rank); the sample's at most k rows are the side to broadcast."""
    curve = R.rank_curve(sample).groupBy("w").agg(F.max("rank_hat").alias("rank_hat"))
    return true.join(F.broadcast(curve), "w").select(F.lit(k).cast("bigint").alias("k"), sig("w").alias("w"), sig("rank_hat").alias("rank_hat"), "rank")


@query(
    "wl_rank_curves_wr",
    "\nUNION ALL ".join(
        f"SELECT '{n}' AS dataset, CAST({k} AS BIGINT) AS k, {s('w')} AS w, {s('max(rank_hat)')} AS rank_hat, CAST(max(r.rank) AS BIGINT) AS rank FROM (SELECT w, sum(1 / p_incl) OVER (ORDER BY w DESC) AS rank_hat FROM {drawn_sql(f_sql(n), 2, k)} x) y JOIN (SELECT w AS rw, sum(m) OVER (ORDER BY w DESC) AS rank FROM {v_sql(n)} v) r ON r.rw = y.w GROUP BY w"
        for n in _RCD for k in _RCK
    ),
)
def wl_rank_curves_wr(spark, d):
    """The curves that draws with replacement by squares show, beside the true ranks."""
    out = []
    for n in _RCD:
        w = cut(freq(spark, d, n))
        true = R.rank_curve_true(cut(histogram(w)))
        out += [(n, _curve_rows(wr.pps_wr(w, moment(2), k), true, k)) for k in _RCK]
    return union(out)


_ZIPF = tuple((a, n) for a in (0.5, 0.75, 1.0, 1.25, 1.5, 2.0) for n in (100, 10000))


def _zipf_combo_sql(a, n):
    r = f"(SELECT w, 1 AS m, i AS first_rank, i AS last_rank, 1.0 AS top FROM (SELECT i, pow(i, -{a}) AS w FROM (SELECT unnest(range(1, {n + 1})) AS i) x) y)"
    from ..operators.combos import SUPPORTED

    rows = []
    for q, least_a, least, fixed in SUPPORTED:
        c = f"max(w * pow(last_rank, {least_a}))"
        factor = "1.65" if fixed else "(1 + ln(count(*)))"
        rows.append(f"SELECT CAST({q} AS DOUBLE) AS q, CAST({least_a} AS DOUBLE) AS alpha, CAST({least} AS DOUBLE) AS least_p, {s(c)} AS c, {s(f'{factor} * pow({c}, {q})')} AS bound, {s(f'sum(pow(w, {q})) / sum(pow(w, 3))')} AS measured FROM {r} z")
    return " UNION ALL ".join(rows)


@query(
    "wl_combinations",
    "\nUNION ALL ".join(f"SELECT 'zipf_{a}_{n}' AS dataset, t.* FROM ({_zipf_combo_sql(a, n)}) t" for a, n in _ZIPF) + "\nUNION ALL " + union_sql(("doc_words", "conv_words"), combo_table_sql),
)
def wl_combinations(spark, d):
    rows = [(f"zipf_{a}_{n}", combo_rows(cut(histogram(C.zipf_frequencies(spark, n, a, 1.0, 4))))) for a, n in _ZIPF]
    return union(rows + [(n, combo_rows(hist(spark, d, n))) for n in ("doc_words", "conv_words")])


_WU = ("doc_words", "doc_lines", "event_tuple", "supp_in", "ps_qty")


def _hn_sql(n):
    return f"(SELECT n, {s('(SELECT sum(1.0 / i) FROM (SELECT unnest(range(1, n + 1)) AS i) q)')} AS h_n FROM (SELECT CAST(sum(m) AS BIGINT) AS n FROM {v_sql(n)} a) b)"


def _tail_sql(n):
    q = q_sql(n, "concave")
    return f"""(SELECT {s('raw')} AS c, * FROM (SELECT min(CASE WHEN tail + (m - 1) * w > 0 THEN first_rank * w / (tail + (m - 1) * w) END) AS raw,
      sum(m * v) AS norm, ceil({s('max(1 / (first_rank * q))')} / 0.01) AS raw_concave FROM {q} a) b)"""


@query("wl_universal", union_sql(_WU, lambda n: "SELECT " + ", ".join(f"(SELECT {s('max(1 / (first_rank * q))')} FROM {q_sql(n, k)} a) AS {k}, (SELECT {s('max(1 / (last_rank * q))')} FROM {q_sql(n, k)} a) AS {k}_exact" for k in ("l1", "l2", "concave")) + f", (SELECT CAST(sum(m) AS BIGINT) FROM {v_sql(n)} a) AS n, h.h_n, t.c, {s('t.norm * (1 + 1 / t.raw)')} AS bound, t.raw_concave < 0.1 * h.n AS practical_concave FROM {_hn_sql(n)} h, {_tail_sql(n)} t"))
def wl_universal(spark, d):
    """Universal overheads by scheme; H_n, the best possible; the concave scheme's bound from the
    tail condition c; and whether a sample for an error of 0.1 is under a tenth of the keys."""
    out = []
    for n in _WU:
        one = O.all_overheads(hist(spark, d, n), ())
        found = [sig(f"{k}_{c}").alias(k + e) for k in ("l1", "l2", "concave") for c, e in (("universal", ""), ("exact", "_exact"))]
        size = F.ceil(sig("concave_universal") / F.lit(0.01))
        bound = sig(F.col("concave_norm") * (1 + 1 / F.col("c")))
        out.append((n, one.select(*found, "n", sig(U.harmonic(F.col("n"))).alias("h_n"), sig("c").alias("c"), bound.alias("bound"), (size < 0.1 * F.col("n")).alias("practical_concave"))))
    return union(out)


_SJ = ("cust_out", "part_in", "page_hosts", "order_lines")


def _joined_sql(n):
    rows = f_sql(n) if n != "order_lines" else "(SELECT CAST(l_orderkey AS VARCHAR) AS key, CAST(count(*) AS DOUBLE) AS w FROM lineitem GROUP BY 1)"
    one = "SELECT CAST({p} AS BIGINT) AS p, CAST(sum({x}) AS BIGINT) AS exact, (SELECT {g} FROM {sample} x) AS estimate FROM {rows} a"
    return " UNION ALL ".join(one.format(p=p, x=x, rows=rows, g=s(f"sum({x} / p_incl)"), sample=sample_sql(rows, "w", 64)) for p, x in ((2, "w*w"), (3, "w*w*w")))


@query("wl_self_join", union_sql(_SJ, _joined_sql))
def wl_self_join(spark, d):
    """Rows of the two-way and three-way self-join on a key, without joining: exact, and from 64 keys."""
    out = []
    for n in _SJ:
        w = cut(freq(spark, d, n) if n != "order_lines" else frequencies(to_elements(load(spark, d, "lineitem"), ["l_orderkey"])))
        kept = cut(B.ppswor(w, 64))
        for p in (2, 3):
            exact = self_join_size(w, p).select(F.lit(p).cast("bigint").alias("p"), F.col("value").cast("bigint").alias("exact"))
            out.append((n, exact.crossJoin(kept.agg(sig(F.sum(power(F.col("w"), p) / F.col("p_incl"))).alias("estimate")))))
    return union(out)


_TS, _TD = (2.0, 5.0, 10.0, 100.0), ("doc_words", "cust_out", "supp_in")


def _threshold_sql(n, t):
    kept = sample_sql(f_sql(n), "w", 256)
    exact = f"(SELECT CAST(count(*) AS BIGINT) FROM {f_sql(n)} a WHERE w >= {t}) AS exact, (SELECT CAST(coalesce(sum(w), 0) AS BIGINT) FROM {f_sql(n)} a WHERE w >= {t}) AS exact_weight"
    guess = ", ".join(f"(SELECT {s(f'sum(CASE WHEN w >= {t} THEN {x} / p_incl ELSE 0 END)')} FROM {kept} x) AS {c}" for x, c in (("1", "estimate"), ("w", "estimate_weight")))
    return f"SELECT '{n}' AS dataset, CAST({t} AS DOUBLE) AS t, {exact}, {guess}"


@query("wl_thresholds", "\nUNION ALL ".join(_threshold_sql(n, t) for n in _TD for t in _TS))
def wl_thresholds(spark, d):
    """Keys at least as frequent as t, and their weight: exact, and from 256 keys."""
    out = []
    for n in _TD:
        w = cut(freq(spark, d, n))
        above = lambda v: F.inline(F.array(*[F.struct(F.lit(t).alias("t"), *[F.when(F.col("w") >= t, x).otherwise(0.0).alias(c) for x, c in v]) for t in _TS]))
        exact = w.select(above([(F.lit(1.0), "a"), (F.col("w"), "b")])).groupBy("t").agg(F.sum("a").cast("bigint").alias("exact"), F.sum("b").cast("bigint").alias("exact_weight"))
        guess = B.ppswor(w, 256).select(above([(1 / F.col("p_incl"), "a"), (F.col("w") / F.col("p_incl"), "b")])).groupBy("t").agg(sig(F.sum("a")).alias("estimate"), sig(F.sum("b")).alias("estimate_weight"))
        out.append((n, exact.join(F.broadcast(guess), "t")))
    return union(out)


_NU = ("supp_in", "event_props", "doc_source")


@query("wl_near_uniform", union_sql(_NU, lambda n: f"SELECT {s('pow(max(w) / min(w), 3)')} AS bound, {s('max(r0)')} AS l0, {s('max(r1)')} AS l1 FROM (SELECT w, (w*w*w / sum(m*w*w*w) OVER ()) * sum(m) OVER () AS r0, (w*w*w / sum(m*w*w*w) OVER ()) / (w / sum(m*w) OVER ()) AS r1 FROM {v_sql(n)} a) b"))
def wl_near_uniform(spark, d):
    out = []
    for n in _NU:
        v = hist(spark, d, n)
        row = O.near_uniform_bound(v, 3).select(sig("bound").alias("bound"))
        for k, scheme in (("l0", "uniform"), ("l1", 1.0)):
            row = row.crossJoin(O.overheads(v, [moment(3)], scheme).select(sig("emulation").alias(k)))
        out.append((n, row))
    return union(out)
