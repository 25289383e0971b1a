"""Ties, halves and large sums: tables on which engines and orders of rows tell apart what small tables do not."""

import duckdb
import pytest

from freqemu.queries import ORACLES, QUERIES
from tests.oracle import compare


@pytest.fixture
def same(spark, tmp_path):
    """Writes a table of rows in the order given (SQL) and in another, in several files (Spark); compares a query with its SQL."""

    def run(name, table, rows, schema):
        whole = spark.createDataFrame(rows, schema)
        whole.coalesce(1).write.parquet(str(tmp_path / "sql"))
        spark.createDataFrame(rows[::-1], schema).repartition(3).write.parquet(str(tmp_path / f"{table}.parquet"))
        con = duckdb.connect()
        con.execute("set threads = 1")
        con.execute(f"create view {table} as select * from '{tmp_path}/sql/*.parquet'")
        found = QUERIES[name](spark, str(tmp_path))
        compare(found, con, ORACLES[name])
        return found.collect()

    return run


def test_agg_maxby_takes_the_smallest_key_of_equal_balances(same):
    rows = [(k, float(k % 3), "ab"[k % 2]) for k in range(1, 200)] + [(200, None, "a"), (None, 9.0, "a"), (201, None, "c")]
    found = same("agg_maxby", "customer", rows, "c_custkey bigint, c_acctbal double, c_mktsegment string")
    assert {tuple(r) for r in found} == {("a", 2, 6), ("b", 5, 3), ("c", None, None)}


def test_win_range_rounds_halves_to_even(same):
    prices = [0.5, 1.5, 1000.5, 1001.5, 2000.5, 2001.5, 2002.5, 2003.5, 3003.5, None, None]
    rows = [(i, "FO"[i % 2], p) for i, p in enumerate(prices * 3)] + [(99, None, 7.0), (100, None, None)]
    assert len(same("win_range", "orders", rows, "o_orderkey bigint, o_orderstatus string, o_totalprice double")) == 35


def test_rank_vector_adds_in_the_order_of_the_rows(same):
    values = [0.1, 0.2, 0.3]  # from the right their sum is 0.6, from the left a bit more
    rows = [(100 * u + i, u, v) for u in range(30) for i, v in enumerate(values)] + [(9000 + i, 99, v) for i, v in enumerate(values[::-1])]
    found = same("rank_vector", "events", rows, "event_id bigint, user_id bigint, value double")
    assert sorted(r.m for r in found) == [1, 30]


def test_baseline_full_is_exact_beyond_the_whole_numbers_of_a_double(spark, tmp_path):
    text = "x " * 300_001 + " ".join(f"a{i}" for i in range(1000))
    spark.createDataFrame([(1, 1, "user", text)], "conv_id bigint, turn int, role string, text string").write.parquet(str(tmp_path / "conversations.parquet"))
    assert QUERIES["baseline_full"](spark, str(tmp_path)).first() == (300_001**3 + 1000, 1001)
