"""Worked examples: the vector (8, 4, 2, 1), and a seven-key sketch by advice."""

import math

import pytest
from pyspark.sql import functions as F

from freqemu.functions.frequency import cap, combination, custom, is_monotone_on, log1p, moment, soft_cap, threshold
from freqemu.operators import advice as A
from freqemu.operators import combos as C
from freqemu.operators import measures as M
from freqemu.operators import overhead as O
from freqemu.operators import universal as U
from freqemu.operators.exact import histogram, norms, ranked, ranked_by_parts


@pytest.fixture(scope="module")
def v(spark):
    w = spark.createDataFrame([("a", 8.0), ("b", 4.0), ("c", 2.0), ("d", 1.0)], "key string, w double")
    return histogram(w).cache()


def one(df):
    r = df.first()
    return r[0] if len(r) == 1 else r


#: FIXTURES.md prints 1.326803 for the last emulation overhead; 1.328125 / (1 + 2^-10 + 4^-10 + 8^-10) is 1.326828.
CASES = [(3, 1.0, 1.641026, 1.482577), (10, 1.0, 1.873169, 1.871343), (3, 2.0, 1.162393, 1.085149), (10, 2.0, 1.326828, 1.325537)]


@pytest.mark.parametrize("p,q,emulation,estimation", CASES)
def test_overheads(v, p, q, emulation, estimation):
    r = O.overheads(v, [moment(p)], q).first()
    assert r.emulation == pytest.approx(emulation, abs=1e-6)
    assert r.estimation == pytest.approx(estimation, abs=1e-6)
    closed = O.lp_by_lq(v, [(p, q)]).first()
    assert closed.overhead == pytest.approx(emulation, abs=1e-6)
    assert closed.overhead <= closed.bound == pytest.approx({1.0: 1.875, 2.0: 1.328125}[q])


def test_universal(v):
    expected = {1.0: (3.75, 1.875), 2.0: (21.25, 7.055664), "concave": (2.686282, 2.686282), "uniform": (4, 4)}
    for scheme, (emulation, estimation) in expected.items():
        assert one(U.universal_emulation(v, scheme)) == pytest.approx(emulation, abs=1e-6)
        assert one(U.universal_estimation(v, scheme)) == pytest.approx(estimation, abs=1e-6)
        assert one(U.universal_bruteforce(v, scheme)) == pytest.approx(emulation, abs=1e-6)
    h4 = 25 / 12
    ideal = custom("ideal", lambda w: F.when(w == 8, 1.0).when(w == 4, 1 / 2).when(w == 2, 1 / 3).otherwise(1 / 4))
    assert one(U.universal_emulation(v, ideal)) == pytest.approx(h4)
    bound = U.concave_universal_bound(v).first()
    assert bound.norm == pytest.approx(1.432684, abs=1e-6) and bound.c == pytest.approx(1.142857, abs=1e-6)
    assert one(U.universal_emulation(v, "concave")) <= bound.bound


@pytest.mark.parametrize("q,k,expected", [(1.0, 1, 0.839297), (1.0, 2, 0.477253), (1.0, 4, 0.207988), (2.0, 1, 0.554068), (2.0, 2, 0.273661), (2.0, 4, 0.113975)])
def test_with_replacement_error(v, q, k, expected):
    assert M.wr_nrmse(v, moment(3), q, [k]).first().nrmse == pytest.approx(expected, abs=1e-6)


def test_norms_and_ranks(v, spark):
    rows = {r.p: r.scaled for r in norms(v, [0, 1, 2, 3]).collect()}
    assert rows == {0.0: 4.0, 1.0: 15 / 8, 2.0: 85 / 64, 3.0: pytest.approx(585 / 512)}
    plain = [tuple(r) for r in ranked(v).orderBy(F.col("w").desc()).collect()]
    parts = [tuple(r) for r in ranked_by_parts(v, 3).orderBy(F.col("w").desc()).collect()]
    assert plain == parts == [(8.0, 1, 1, 1, 8.0, 7.0), (4.0, 1, 2, 2, 12.0, 3.0), (2.0, 1, 3, 3, 14.0, 1.0), (1.0, 1, 4, 4, 15.0, 0.0)]


def test_low_moments_take_the_rarest_key(v):
    r = O.lp_by_lq(v, [(0.5, 1.0)]).first()
    assert r.bound is None
    assert r.overhead == pytest.approx(15 / (8**0.5 + 2 + 2**0.5 + 1))
    assert O.overheads(v, [moment(0.5)], 1.0).first().emulation == pytest.approx(r.overhead)


def test_families_and_chains(v):
    family = [moment(2), moment(3), threshold(3)]
    worst = one(O.family_overhead(v, family, 1.0))
    assert one(O.family_overhead(v, [combination([(2, family[0]), (0.5, family[1]), (7, family[2])])], 1.0)) <= worst + 1e-9
    c = O.chain(v, moment(3), 2.0, 1.0).first()
    assert c.direct <= c.first * c.second + 1e-12
    for f in (cap(1), cap(3), cap(8), log1p(), soft_cap(2)):
        assert O.overheads(v, [f], "concave").first().emulation <= 1.432685
    with pytest.raises(ValueError):
        combination([(-1, moment(1))])
    assert is_monotone_on(moment(3), v) and not is_monotone_on(custom("down", lambda w: -w), v)


def test_combinations(v):
    hh = C.heavy_hitter_combination(v, 1, 0.1).first()
    assert hh.phi == pytest.approx(8 / 15) and hh.size == 188
    claim = C.Combination(lambda h: one(C.heavy_hitter_combination(h, 1, 1).select("phi")) >= 0.5, [moment(2), moment(5)], 2.0, 1.0)
    assert claim.check(v)
    assert not C.Combination(lambda h: True, [moment(5)], 1.5, 1.0).check(v)
    for r in C.supported_combinations(v).collect():
        assert r.measured <= r.bound
    assert C.generalized_harmonic(10**6, 1.0) == pytest.approx(math.log(10**6) + 0.5772156649015329 + 5e-7, rel=1e-9)
    assert C.generalized_harmonic(4, 2) == pytest.approx(1.423611, abs=1e-6)


@pytest.mark.parametrize("alpha", [0.5, 0.75, 1.0, 1.25, 1.5, 2.0])
@pytest.mark.parametrize("n", [500])
def test_zipf_vectors(spark, alpha, n):
    v = histogram(C.zipf_frequencies(spark, n, alpha, 1.0, 2)).cache()
    assert one(C.fit_zipf(v)) == pytest.approx(alpha, abs=1e-6)
    assert one(C.subzipf_c(v, alpha)) == pytest.approx(1.0)
    assert one(C.zipf_universal(v, alpha)) == pytest.approx(C.generalized_harmonic(n, 1.0))
    for r in C.supported_combinations(v).collect():
        assert r.measured <= r.bound * (1 + 1e-9)
    for q in (1.0, 2.0):
        if q * alpha >= 1:
            assert C.subzipf_phi(1.0, alpha, n, q) == pytest.approx(one(C.heavy_hitter_combination(v, q, 0.5).select("phi")))


SEVEN = [("A", 10.0, 9.0, 0.30), ("B", 6.0, 1.0, 0.20), ("C", 5.0, 6.0, 0.90), ("D", 3.0, 3.0, 0.60), ("E", 2.0, 0.0, 0.05), ("F", 1.0, 2.0, 0.80), ("G", 1.0, 1.0, 0.50)]


def seven(spark):
    rows = spark.createDataFrame(SEVEN, "key string, w double, advice double, h double")
    rows = rows.withColumn("fa", F.col("advice") * F.col("advice"))
    return rows.withColumn("r", F.when(F.col("fa") > 0, F.col("h") / F.col("fa")))


def test_seven_keys(spark):
    sk = A.cut_sketch(seven(spark), 1, 3, 2)
    flags = {r.key: (r.in_top, r.in_advice, r.in_uniform) for r in sk.collect()}
    assert flags == {"A": (True, False, False), "B": (False, True, True), "C": (False, True, False), "D": (False, True, False), "E": (False, False, True)}
    expected = {
        "ppswor": ({"A": 1, "C": 0.999253, "D": 0.834701, "E": 0.181269}, 157.8676),
        "priority": ({"A": 1, "C": 1, "D": 1, "E": 0.2}, 154),
    }
    for scheme, (chances, total) in expected.items():
        rows = A.advice_estimate(sk, moment(2), 3, 2, scheme).collect()
        assert {r.key: pytest.approx(r.p_incl, abs=1e-6) for r in rows} == chances
        assert sum(r.f_hat for r in rows) == pytest.approx(total, abs=1e-3)


def test_sizes():
    assert A.size_for(100, 1.5, 0.25, 4) == (4, 152, 27)
    assert A.size_for(10, 2, 0) == (0, 22, 0)
    assert O.size_for_nrmse(0.1) in (100, 101) and O.benchmark_nrmse(100) == pytest.approx(0.1)
    assert (O.effective_k("wr", 10), O.effective_k("ppswor", 10), O.effective_k("ppswor", 10, False)) == (10, 8, 9)
    assert M.practicality(20, 0.1, 10**6)["practical"] and not M.practicality(20, 0.1, 3000)["practical"]


def test_overhead_is_tight_on_single_rare_keys(spark):
    """For a key of small chance the variance under another scheme is p/q times that under the ideal one."""
    n, k = 4000, 5
    rows = [(f"k{i}", 2.0 if i < n // 2 else 1.0) for i in range(n)]
    v = histogram(spark.createDataFrame(rows, "key string, w double"))
    f = moment(3)
    ideal = {r.w: r.variance for r in O.wr_key_variance(v, f, 3.0, k).collect()}
    actual = {r.w: r.variance for r in O.wr_key_variance(v, f, 1.0, k).collect()}
    ratio = {r.w: r.p0 / r.q for r in O.chances(v, [f], 1.0).collect()}
    for w in (1.0, 2.0):
        assert actual[w] / ideal[w] == pytest.approx(ratio[w], rel=0.01)
    assert all(r.variance <= r.bound for r in O.wr_key_variance(v, f, 1.0, k).collect())


def test_samples_of_a_range_of_moments_are_universal_on_zipf_vectors(spark):
    low, high, bound = U.zipf_range_universal(1.5, 500, 0.5, 2.0)
    assert (low, high) == (0.5, 2.0) and bound == pytest.approx(1.5 * C.generalized_harmonic(500, 1.0))
    for alpha in (0.5, 1.0, 2.0):
        v = histogram(C.zipf_frequencies(spark, 500, alpha, 1.0, 2))
        exact = one(U.universal_emulation(v, 1 / alpha))
        h = O.overheads(v, [moment(1 / alpha)], 1 / alpha).first().emulation
        assert h == pytest.approx(1) and exact <= h * C.generalized_harmonic(500, 1.0) * (1 + 1e-9)


def test_composition_with_the_ideal_universal_sample(v):
    """A scheme's universal overhead is its overhead for the ideal universal one, times H_n at most."""
    h4 = C.generalized_harmonic(4, 1.0)
    ideal = custom("ideal", lambda w: F.when(w == 8, 1.0).when(w == 4, 1 / 2).when(w == 2, 1 / 3).otherwise(1 / 4))
    for scheme in (1.0, 2.0, "concave"):
        through = O.overheads(v, [ideal], scheme).first().emulation
        assert one(U.universal_emulation(v, scheme)) == pytest.approx(through * h4)
