"""Queries that once made up their data: each reads its table, and says of a small one what can be worked out by hand."""

from datetime import datetime

import duckdb
import pytest
from pyspark.errors import AnalysisException

from freqemu.queries import ORACLES, QUERIES
from tests.oracle import compare


@pytest.fixture
def of(spark, tmp_path):
    """A query's rows on one table of the given rows, which its SQL gives too."""

    def run(name, table, rows, schema):
        path = f"{tmp_path}/{table}.parquet"
        spark.createDataFrame(rows, schema).write.parquet(path)
        con = duckdb.connect()
        con.execute(f"create view {table} as select * from '{path}/*.parquet'")
        found = QUERIES[name](spark, str(tmp_path))
        compare(found, con, ORACLES[name])
        return found.collect()

    return run


#: Customers 1, 2 and 3 with 6, 3 and 1 orders.
ORDERS = [(i, c) for i, c in enumerate([1] * 6 + [2] * 3 + [3])]


def test_bench_nrmse_follows_from_the_variances_of_the_keys(of):
    found = {r.k: r.nrmse for r in of("bench_nrmse", "orders", ORDERS, "o_orderkey bigint, o_custkey bigint")}
    assert found == pytest.approx({2**i: 2 ** (-i / 2) for i in range(5, 13)}, rel=1e-6)


def test_bench_nrmse_needs_its_table(spark, tmp_path):
    with pytest.raises(AnalysisException):
        QUERIES["bench_nrmse"](spark, str(tmp_path)).collect()


def test_harmonic_sums_over_the_ranks_of_the_keys(of):
    found = {r.s: r.value for r in of("harmonic", "orders", ORDERS, "o_orderkey bigint, o_custkey bigint")}
    assert found == pytest.approx({x: 1 + 2**-x + 3**-x for x in (0.5, 1.0, 2.0)}, rel=1e-6)


def test_subzipf_phi_takes_c_and_the_number_of_keys_from_the_table(of):
    found = {(r.alpha, r.q): r.phi for r in of("subzipf_phi", "orders", ORDERS, "o_orderkey bigint, o_custkey bigint")}
    assert found[1.0, 1.0] == pytest.approx(1 / (1 + 1 / 2 + 1 / 3), rel=1e-6)  # c = 1: the second key has half of the first
    assert found[2.0, 1.0] == pytest.approx(1 / (2 * (1 + 1 / 4 + 1 / 9)), rel=1e-6)  # c = 2, at the second key


def test_udtf_zipf_makes_a_vector_for_each_user(of):
    rows = [(1, "2024-01-01 10:00:00", 8.0), (1, "2024-01-01 23:59:59", 2.0), (1, "2024-01-02 00:00:00", 1.0), (2, "2024-01-05 00:00:00", 3.0), (3, "2024-01-05 00:00:00", 0.0)]
    rows = [(u, datetime.fromisoformat(t), v) for u, t, v in rows]
    found = {(r.user_id, r.key): r.w for r in of("udtf_zipf", "events", rows, "user_id bigint, ts timestamp_ntz, value double")}
    assert found == pytest.approx({(1, "1"): 8.0, (1, "2"): 8 * 2**-1.5, (2, "1"): 3.0}, rel=1e-6)


def test_zipf_gen_gives_the_keys_of_the_table_zipf_frequencies(of):
    found = {r.key: r.w for r in of("zipf_gen", "orders", [*ORDERS, (99, 10)], "o_orderkey bigint, o_custkey bigint")}
    assert found == pytest.approx({"1": 6.0, "2": 6 * 2**-1.25, "10": 6 * 3**-1.25, "3": 6 * 4**-1.25}, rel=1e-6)


def test_zipf_universal_has_the_harmonic_number_of_the_keys_of_the_table(of):
    found = of("zipf_universal", "lineitem", [(i, c) for i, c in ORDERS], "l_orderkey bigint, l_suppkey bigint")
    assert len(found) == 6 and all(x == pytest.approx(1 + 1 / 2 + 1 / 3, rel=1e-6) for r in found for x in (r.universal, r.h_n))
