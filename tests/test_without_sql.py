"""Queries that SQL cannot say: each is held against exact figures of the same tables."""

import pytest

from freqemu.operators import measures as M
from freqemu.operators import overhead as O
from freqemu.operators.bottomk import ppswor
from freqemu.queries import ORACLES, QUERIES
from freqemu.queries.sql import freq, hist
from freqemu.queries.workloads import full_moment_errors, full_past_advice

CHECKED = {"linear_l2_sample", "second_moment_sketch", "approx_distinct", "approx_topk", "kll_quantiles", "count_min", "theta_overlap", "st_certificate", "wl_learned_advice", "advice_learned"}


def test_every_query_without_sql_has_a_test():
    core = {n for n in QUERIES if n not in ORACLES}
    assert core <= CHECKED, core - CHECKED


def run(spark, data, name):
    return QUERIES[name](spark, data).collect()


def test_distinct_count_sketches(spark, data):
    (r,) = run(spark, data, "approx_distinct")
    assert r.hll == pytest.approx(r.exact, rel=0.08) and r.sketch == pytest.approx(r.exact, rel=0.08)


def test_top_keys_sketch(spark, data, duck):
    exact = dict(duck.execute("SELECT l_suppkey, count(*) FROM lineitem GROUP BY 1").fetchall())
    found = run(spark, data, "approx_topk")
    assert len(found) == min(10, len(exact))
    assert all(r[1] == exact[r[0]] for r in found)  # few suppliers: the sketch holds them all
    assert min(r[1] for r in found) >= sorted(exact.values(), reverse=True)[len(found) - 1]


def test_quantile_sketch(spark, data, duck):
    (r,) = run(spark, data, "kll_quantiles")
    below = duck.execute(f"SELECT avg(CASE WHEN l_extendedprice <= {r.mid} THEN 1.0 ELSE 0.0 END) FROM lineitem").fetchone()[0]
    assert abs(below - 0.5) < 0.03
    assert r.exact == pytest.approx(duck.execute("SELECT quantile_cont(l_extendedprice, 0.5) FROM lineitem").fetchone()[0])


def test_count_min_sketch_has_the_size_of_its_error(spark, data, duck):
    (r,) = run(spark, data, "count_min")
    assert r.n == duck.execute("SELECT count(*) FROM lineitem").fetchone()[0]
    assert 200 * 5 * 8 <= r.bytes <= 200 * 5 * 8 + 200  # depth 5, width 200, whatever the rows


def test_intersection_of_key_sketches(spark, data, duck):
    half = "SELECT DISTINCT o_custkey FROM orders WHERE o_orderdate >= TIMESTAMP '{}' AND o_orderdate < TIMESTAMP '{}'"
    exact = duck.execute(f"SELECT count(*) FROM ({half.format('1997-01-01', '1997-07-01')} INTERSECT {half.format('1997-07-01', '1998-01-01')}) x").fetchone()[0]
    assert run(spark, data, "theta_overlap")[0][0] == pytest.approx(exact, rel=0.08)


def test_second_moment_sketch_and_linear_sample(spark, data, duck):
    w = freq(spark, data, "doc_words").cache()
    truth = w.selectExpr("sum(w * w)").first()[0]
    assert run(spark, data, "second_moment_sketch")[0][0] == pytest.approx(truth, rel=0.25)
    top = {r.key for r in w.orderBy(w.w.desc()).limit(3).collect()}
    found = {r.key for r in run(spark, data, "linear_l2_sample")}
    assert 0 < len(found) <= 32 and found & top


def test_stream_certificates_hold(spark, data):
    from freqemu.sources.tables import load
    from pyspark.sql import functions as F

    w = load(spark, data, "events").groupBy(F.col("user_id").cast("string").alias("key")).agg(F.count("*").cast("double").alias("w"))
    top, norm = w.agg(F.max("w"), F.sum(F.col("w") * F.col("w"))).first()
    total = w.agg(F.sum("w")).first()[0]
    found = {r.q: r for r in run(spark, data, "st_certificate")}
    assert found[1].r <= top / total + 1e-12
    assert found[2].r <= top * top / norm * 1.4  # the norm is a sketch's estimate


def test_learned_advice_orders_keys_by_frequency(spark, data):
    found = QUERIES["advice_learned"](spark, data)
    assert found.columns[0] == "key" and found.where("advice < 0").isEmpty()
    both = found.join(freq(spark, data, "doc_words").withColumnRenamed("w", "all_w"), "key")
    assert both.stat.corr("advice", "all_w") > 0.5


def test_full_grids_run_with_any_number_of_runs(spark, data):
    rows = full_moment_errors(spark, data, "doc_lines", runs=2, sizes=(32, 64, 4096)).collect()
    assert {r.f for r in rows} == {"moment_3", "moment_7", "moment_10"}
    assert {r.scheme for r in rows} == {"ppswor", "l2_wor", "l1_wr", "l2_wr", "bound"}
    n = freq(spark, data, "doc_lines").count()
    assert {r.k for r in rows} == {k for k in (32, 64, 4096) if 2 * k < n}
    rows = full_past_advice(spark, data, "words", runs=2, sizes=(64,)).collect()
    assert {r.scheme for r in rows} == {"ppswor", "l2_wor", "l1_wr", "l2_wr", "bound", "advice_u32"}


def test_errors_of_several_powers_equal_those_of_one(spark, data):
    from freqemu.functions.frequency import moment

    w = freq(spark, data, "page_hosts").cache()
    v = hist(spark, data, "page_hosts")
    both = {(r.q, r.k): r.nrmse for r in M.wr_nrmse_by(v, (1, 2), (32, 64), (3,)).collect()}
    for q in (1, 2):
        assert {k: x for (p, k), x in both.items() if p == q} == pytest.approx({r.k: r.nrmse for r in M.wr_nrmse(v, moment(3), float(q), (32, 64)).collect()})
    assert M.conditional_nrmse_by(w, (1, 2), (8,), [moment(3)], 2).count() == 2
    table = O.all_overheads(v, (3,)).first()
    one = O.overheads(v, [moment(3)], 2.0).first()
    assert (table["l2_3"], table["l2_3_est"]) == pytest.approx((one.emulation, one.estimation))
    assert ppswor(w, 8).count() <= 8
