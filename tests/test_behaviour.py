"""What the experiments show, on the given tables: which scheme wins, and where it does not."""

import pytest

from freqemu.functions.frequency import moment
from freqemu.operators import measures as M
from freqemu.operators import overhead as O
from freqemu.operators import rankcurve as R
from freqemu.operators import universal as U
from freqemu.operators.bottomk import ppswor
from freqemu.operators.combos import certify
from freqemu.queries import QUERIES
from freqemu.queries.advice import rows_of
from freqemu.queries.sql import freq, hist


@pytest.fixture(scope="module")
def words(spark, data):
    return freq(spark, data, "doc_words").cache()


@pytest.fixture(scope="module")
def vector(spark, data):
    return hist(spark, data, "doc_words")


def error(df):
    return df.first()["nrmse"]


def test_second_moment_samples_are_best_for_high_moments_of_skewed_data(words, vector):
    l1, l2 = (error(M.conditional_nrmse(words, q, [64], [moment(3)], 5)) for q in (1, 2))
    l2_wr = error(M.wr_nrmse(vector, moment(3), 2.0, [64]))
    assert l2 < l2_wr < l1
    assert l2 < M.benchmark_curve(words.sparkSession, [64]).first()["nrmse"]


def test_overheads_fall_with_a_heavy_hitter_and_rise_with_the_moment(vector):
    e = {(p, q): O.overheads(vector, [moment(p)], q).first().emulation for p in (3, 10) for q in (1.0, 2.0)}
    assert e[3, 2.0] < e[3, 1.0] and e[10, 2.0] < e[10, 1.0]
    assert e[3, 1.0] <= e[10, 1.0] and e[3, 2.0] <= e[10, 2.0]
    bound = {q: O.lp_by_lq(vector, [(q, q)]).first().bound for q in (1.0, 2.0)}
    assert all(e[p, q] <= bound[q] for p in (3, 10) for q in (1.0, 2.0))


def test_universal_overheads(vector):
    u = {s: U.universal_emulation(vector, s).first()[0] for s in (1.0, 2.0, "concave")}
    assert u[2.0] > 10 * max(u[1.0], u["concave"])
    n = vector.agg({"m": "sum"}).first()[0]
    h_n = sum(1 / i for i in range(1, n + 1))
    assert all(x >= h_n for x in u.values())


def test_advice_helps_on_words_and_not_on_even_degrees(spark, data):
    for name, better in (("words", True), ("cust", False)):
        rows = rows_of(spark, data, name).cache()
        by_advice = error(M.conditional_nrmse_advice(rows, moment(10), [(0, 32, 32)], 5))
        by_frequency = error(M.conditional_nrmse(rows.select("key", "w"), 1, [64], [moment(10)], 5))
        assert (by_advice < by_frequency) == better


def test_rank_curves(words, vector):
    few, many = (R.rank_curve_error(ppswor(words, k), vector).first() for k in (32, 1024))
    assert many.mean_error < few.mean_error and many.mean_error < 0.2
    rare = {q: ppswor(words, 256, q).where("w <= 2").count() for q in (1, 2)}
    assert rare[2] < rare[1]  # samples by squares see less of the tail


def test_certificates_never_promise_too_much(words, vector):
    phi = 1 / O.lp_by_lq(vector, [(1, 1)]).first().bound
    for salt in "abc":
        c = certify(ppswor(words, 64, 1, salt), 1, words.agg({"w": "sum"}).first()[0], 64).first()
        assert c.r <= phi + 1e-12 and c.certified <= 64 / O.overheads(vector, [moment(3)], 1.0).first().emulation + 1e-9


def test_learned_advice_is_evaluated_on_each_later_day(spark):
    rows = QUERIES["wl_learned_advice"](spark, "/root/testdata/sf0.01").collect()
    assert {(r.day, r.f) for r in rows} == {(d, f"moment_{p}") for d in (50, 80) for p in (3, 7, 10)}
    assert len({r.scheme for r in rows if r.scheme.startswith("advice")}) == 2
    assert len({(r.day, r.f, r.scheme) for r in rows}) == 2 * 3 * 7
