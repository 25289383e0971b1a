import pytest

from freqemu.queries import ORACLES, QUERIES
from tests.oracle import compare

SLOW = {"wl_past_advice", "wl_combinations", "wl_table1", "universal_emulation_ties", "universal_brute", "universal_estimation"}


@pytest.mark.parametrize("name", [n for n in QUERIES if n in ORACLES and n not in SLOW])
def test_query_equals_sql(spark, data, duck, name):
    compare(QUERIES[name](spark, data), duck, ORACLES[name])


@pytest.mark.parametrize("name", ["subq_scalar", "filter_domain"])
def test_filters_keep_some_rows(spark, data, name):
    assert QUERIES[name](spark, data).count() > 0


def test_entry(spark):
    import __spark_entry__ as entry

    assert entry.entry(spark).count() == 1
    assert set(entry.oracle_sql()) <= set(entry.queries())
