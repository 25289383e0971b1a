"""Samples: edge cases, merging, unbiasedness, and the several ways to one sketch."""

import random

import numpy as np
import pyarrow as pa
import pytest
from pyspark.sql import functions as F

from freqemu.functions.frequency import combination, moment
from freqemu.operators import advice as A
from freqemu.operators import bottomk as B
from freqemu.operators import concave as K
from freqemu.operators import estimators as E
from freqemu.operators import kernel as KN
from freqemu.operators import linear as L
from freqemu.operators import measures as M
from freqemu.operators import unaggregated as N
from freqemu.operators import universal as U
from freqemu.operators import wr
from freqemu.operators.exact import frequencies
from freqemu.plans import planner
from freqemu.sources.tables import to_elements

W = [("k%03d" % i, float(max(1, 200 // (i + 1)))) for i in range(120)]


@pytest.fixture(scope="module")
def freq(spark):
    return spark.createDataFrame(W, "key string, w double").repartition(3).cache()


def total(sample, f=moment(3)):
    return E.estimate_statistic(sample, f).first()[0]


def test_fewer_keys_than_the_sample(freq):
    few = freq.where("w >= 20")
    truth = few.agg(F.sum(F.pow("w", F.lit(3.0)))).first()[0]
    for s in (B.ppswor(few, 50), B.priority(few, 50, 2), B.uniform(few, 50), K.concave_sample(few, 50), U.universal_sample(few, 50)):
        assert {r.p_incl for r in s.collect()} == {1.0}
        assert total(s) == pytest.approx(truth)


def test_empty_and_single(spark, freq):
    none = freq.where("w < 0")
    for s in (B.ppswor(none, 4), K.concave_sample(none, 4), wr.pps_wr_min(none, moment(1), 4)):
        assert s.count() == 0
    assert total(B.ppswor(none, 4)) == 0
    single = freq.where("key = 'k000'")
    assert [r.p_incl for r in B.ppswor(single, 4).collect()] == [1.0]
    assert wr.pps_wr(single, moment(2), 5).first().draws == 5
    assert B.ppswor(freq, 1).count() == 0  # the only stored key is the threshold


@pytest.mark.parametrize("make", [lambda w, s: B.ppswor(w, 20, 1, s), lambda w, s: B.priority(w, 20, 1, s), lambda w, s: wr.pps_wr_min(w, moment(1), 20, s), lambda w, s: K.concave_sample(w, 20, s), lambda w, s: K.multi_cap_sample(w, 12, (1.0, 4.0, 16.0, 64.0, 256.0), s)])
def test_unbiased(freq, make):
    truth = sum(w**1.5 for _, w in W)
    found = [total(make(freq, f"run{i}"), moment(1.5)) / truth for i in range(16)]
    mean = sum(found) / len(found)
    sd = (sum((x - mean) ** 2 for x in found) / (len(found) - 1)) ** 0.5
    assert abs(mean - 1) < 4 * sd / len(found) ** 0.5 + 1e-3


def test_merge_equals_one_shot(freq):
    whole = {r.key for r in B.bottom_k(B.seeded(freq, F.col("w")), 16).collect()}
    parts = [B.bottom_k(B.seeded(freq.where(F.pmod(F.crc32(F.col("key").cast("binary")), F.lit(4)) == i), F.col("w")), 16) for i in range(4)]
    assert {r.key for r in B.merge(parts, 16, moment(1)).collect()} == whole
    assert {r.key for r in B.merge([B.merge(parts[:2], 16, moment(1)), *parts[2:]], 16, moment(1)).collect()} == whole


def elements_of(spark, seed, shuffled=True):
    rng = random.Random(seed)
    rows, advice = [], {}
    for i in range(rng.randint(3, 40)):
        key = f"x{i}"
        advice[key] = float(rng.choice([0, 0, 1, 1, 2, 5, 9]))
        rows += [(key, float(rng.randint(1, 5))) for _ in range(rng.randint(1, 6))]
    rng.shuffle(rows)
    return rows, advice, rng


def loop_sketch(rows, advice, f, kh, kp, ku):
    """One element after another, as a stream would be taken; test model only."""
    top, rest = {}, {}

    def seeds(key):
        import math

        u = KN.unit_seed_of(key, "s")
        h = -math.log1p(-u)
        return h, (h / f(advice[key]) if advice[key] > 0 else math.inf)

    def settle(key, value):
        if key in rest:
            rest[key] += value
            return
        rest[key] = value
        by_r = sorted((k for k in rest if seeds(k)[1] < float("inf")), key=lambda k: (seeds(k)[1], k))[:kp]
        by_h = sorted(rest, key=lambda k: (seeds(k)[0], k))[:ku]
        for k in [k for k in rest if k not in by_r and k not in by_h]:
            del rest[k]

    for key, value in rows:
        if key in top:
            top[key] += value
        elif key in rest:
            rest[key] += value
        else:
            rank = lambda k: (-advice[k], seeds(k)[0], k)
            if len(top) < kh or (kh and rank(key) < max(map(rank, top))):
                top[key] = value
                if len(top) > kh:
                    worst = max(top, key=rank)
                    settle(worst, top.pop(worst))
            else:
                settle(key, value)
    return top | rest


@pytest.mark.parametrize("seed", range(4))
def test_all_ways_to_a_sketch_agree(spark, seed):
    rows, advice, rng = elements_of(spark, seed)
    kh, kp, ku = rng.choice([0, 1, 3]), rng.choice([0, 2, 5]), rng.choice([0, 2, 5])
    f = moment(2)
    e = spark.createDataFrame([(k, v, advice[k]) for k, v in rows], "key string, value double, advice double")
    a = spark.createDataFrame(list(advice.items()), "key string, advice double")
    expected = loop_sketch(rows, advice, lambda x: x * x, kh, kp, ku)

    def held(sk):
        return {r.key: r.w for r in sk.collect()}

    assert held(A.advice_sketch(e.select("key", "value"), a, f, kh, kp, ku)) == expected
    assert held(KN.kernel_sketch(e.repartition(3), f, kh, kp, ku)) == expected
    assert held(KN.kernel_sketch(e.select("key", "value").repartition(3), f, kh, kp, ku, advice=a)) == expected
    assert held(planner.prefiltered_sketch(e.select("key", "value"), e.limit(20), a, f, kh, kp, ku)) == expected
    parts = [A.advice_sketch(e.where(F.pmod(F.xxhash64("key", "value"), F.lit(3)) == i).select("key", "value"), a, f, kh, kp, ku) for i in range(3)]
    assert held(A.merge_advice(parts, kh, kp, ku)) == expected
    assert len(expected) <= kh + kp + ku


def test_kernel_state_is_bounded():
    state = KN.PartialSketch(2, 8, 8, lambda a: a * a, "ppswor", "s", slack=20)
    most = 0
    for i in range(0, 20_000, 50):
        state.add(pa.array([f"k{j}" for j in range(i, i + 50)]), np.ones(50), np.arange(i, i + 50) % 7.0)
        most = max(most, len(state.rows))
    assert most <= state.full
    assert len(state.cut()[0]) <= 18


def test_no_element_is_shuffled_before_the_filter(spark):
    """Up to the sums by key, plans of the two scale forms exchange no element: the join with passing advice is a broadcast."""
    e = spark.range(20_000).select((F.col("id") % 3000).cast("string").alias("key"), F.lit(1.0).alias("value"))
    a = spark.range(500).select(F.col("id").cast("string").alias("key"), (F.col("id") + 1).cast("double").alias("advice"))
    for sk in (planner.prefiltered_sketch(e, e.limit(2000), a, moment(2), 2, 8, 8), KN.kernel_sketch(e, moment(2), 2, 8, 8, advice=a)):
        plan = sk._jdf.queryExecution().sparkPlan().toString()
        assert "SortMergeJoin" not in plan and "repartition" not in plan.lower()
    below = planner.prefiltered_sketch(e, e.limit(2000), a, moment(2), 2, 8, 8)
    assert {r.key: r.w for r in below.collect()} == {r.key: r.w for r in A.advice_sketch(e, a, moment(2), 2, 8, 8).collect()}


def test_kernel_joins_advice_that_is_too_large_to_broadcast(spark, monkeypatch):
    rows, advice, _ = elements_of(spark, 1)
    e = spark.createDataFrame(rows, "key string, value double").repartition(3)
    a = spark.createDataFrame([(k, v) for k, v in advice.items() if k != rows[0][0]], "key string, advice double")
    expected = {(r.key, r.w, r.advice) for r in A.advice_sketch(e, a, moment(2), 1, 5, 5).collect()}
    monkeypatch.setattr(KN, "MOST_ADVICE", len(advice) - 2)
    assert {(r.key, r.w, r.advice) for r in KN.kernel_sketch(e, moment(2), 1, 5, 5, advice=a).collect()} == expected


def test_kernel_sums_batches_by_blocks(monkeypatch):
    batches = [pa.RecordBatch.from_pydict({"key": [str(i), "x"], "value": [1.0, 2.0]}) for i in range(10)]
    monkeypatch.setattr(KN, "BLOCK_ROWS", 6)
    assert [len(t) for t in KN.blocks(iter(batches))] == [6, 6, 6, 2]
    assert [r for t in KN.blocks(iter(batches)) for r in t.to_pylist()] == [r for b in batches for r in b.to_pylist()]
    monkeypatch.setattr(KN, "BLOCK_BYTES", 1)
    assert [len(t) for t in KN.blocks(iter(batches))] == [2] * 10
    assert list(KN.blocks(iter([]))) == []


@pytest.mark.parametrize("scheme", ["ppswor", "priority"])
def test_advice_estimates_are_unbiased(spark, scheme):
    rows, advice, _ = elements_of(spark, 99)
    e = spark.createDataFrame(rows, "key string, value double")
    w = frequencies(e).cache()
    a = spark.createDataFrame(list(advice.items()), "key string, advice double")
    truth = w.agg(F.sum(F.col("w") * F.col("w"))).first()[0]
    base = A.attach(w, a).cache()
    found = []
    for i in range(20):
        sk = A.cut_sketch(A.seeded(base, moment(2), scheme, f"r{i}"), 2, 8, 8)
        found.append(A.advice_estimate(sk, moment(2), 8, 8, scheme).agg(F.sum("f_hat")).first()[0] / truth)
    mean = sum(found) / len(found)
    sd = (sum((x - mean) ** 2 for x in found) / (len(found) - 1)) ** 0.5
    assert abs(mean - 1) < 4 * sd / len(found) ** 0.5 + 1e-3


def test_no_advice_keeps_the_sketch_small(spark, freq):
    rows = A.seeded(freq.withColumn("advice", F.lit(0.0)), moment(3))
    sk = A.cut_sketch(rows, 0, 10, 6)
    assert sk.count() == 6 and sk.where("in_advice").count() == 0
    assert A.advice_estimate(sk, moment(3), 10, 6).count() == 5


def test_conditional_error_of_exact_advice_is_that_of_ppswor(spark, freq):
    rows = freq.withColumn("advice", F.col("w"))
    a = M.conditional_nrmse_advice(rows, moment(2), [(0, 20, 0)], 10).first().nrmse
    b = M.conditional_nrmse(freq, 2, [20], [moment(2)], 10).first().nrmse
    assert a == pytest.approx(b, rel=1e-9)


def test_directions_of_error(freq):
    """On skewed data l_2 samples beat l_1 samples for high moments, and both beat uniform ones."""
    e = {q: M.conditional_nrmse(freq, q, [16], [moment(3)], 10).first().nrmse for q in (0, 1, 2)}
    assert e[2] < e[1] < e[0]


def test_unaggregated_samples(spark):
    rows = [("k%d" % (i % 9), 1.0, i) for i in range(300)]
    e = spark.createDataFrame(rows, "key string, value double, id long")
    kept = N.ppswor_by_elements(e, 5, "id")
    two = N.two_pass(e, kept)
    assert kept.count() == two.count() == 4
    exact = {r.key: r.w for r in frequencies(e).collect()}
    assert all(exact[r.key] == r.w and 0 < r.p_incl <= 1 for r in two.collect())
    guesses = []
    slope = combination([(2, moment(1))])
    for salt in range(25):
        held = N.sample_and_hold(e.repartition(3), 0.2, "id", str(salt))
        guesses.append(N.hold_estimate(held, moment(2), slope, 0.2).first()[0])
    one, other = ({(r.key, round(r.c, 9)) for r in N.sample_and_hold(e.repartition(n), 0.2, "id").collect()} for n in (1, 5))
    assert one == other  # how elements lie in partitions does not matter
    mean, truth = sum(guesses) / len(guesses), sum(w * w for w in exact.values())
    sd = (sum((x - mean) ** 2 for x in guesses) / (len(guesses) - 1)) ** 0.5
    assert abs(mean - truth) < 4 * sd / len(guesses) ** 0.5


def test_linear_sketch_finds_the_sample(spark, freq):
    e = freq.select("key", F.col("w").alias("value"))
    exact = {r.key for r in B.ppswor(freq, 12, 2).collect()}
    found = {r.key for r in L.linear_sample(e, 2, 12, 7, 1024, fast=False).collect()}
    assert len(exact & found) >= 10
    truth = sum(w * w for _, w in W)
    assert L.second_moment(L.second_moment_cells(e, 5, 512)).first()[0] == pytest.approx(truth, rel=0.25)


def test_with_replacement_draws(freq):
    rows = wr.pps_wr(freq, moment(1), 500).collect()
    assert sum(r.draws for r in rows) == 500
    mass = sum(w for _, w in W)
    top = next(r for r in rows if r.key == "k000")
    assert top.draws / 500 == pytest.approx(200 / mass, abs=0.1)
    spans = wr.cumulated(freq, moment(1), 1).orderBy("lo").collect()
    assert spans[0].lo == 0 and spans[-1].hi == pytest.approx(1)
    assert all(a.hi == pytest.approx(b.lo) for a, b in zip(spans, spans[1:]))


def test_elements_drop_what_cannot_count(spark):
    rows = [("a", 1.0), (None, 2.0), ("b", None), ("b", 0.0), ("b", -1.0), ("c", float("nan")), ("c", float("inf")), ("d|e", 4.0)]
    e = to_elements(spark.createDataFrame(rows, "k string, v double"), ["k"], "v")
    assert {(r.key, r.value) for r in e.collect()} == {("a", 1.0), ("d|e", 4.0)}
    two = to_elements(spark.createDataFrame([("a|", "b"), ("a", "|b")], "x string, y string"), ["x", "y"])
    assert two.select("key").distinct().count() == 2


def test_planner(spark, freq):
    from freqemu.operators.exact import histogram

    v = histogram(freq)
    choice = planner.choose_scheme(v, [moment(3), moment(10)], 0.1)
    assert choice["scheme"] == 2.0 and choice["size"] >= 100
    assert planner.sketch_plan(freq.select("key"), 1.0) == "relational"
