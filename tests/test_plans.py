"""Plans: limits instead of sorts, broadcasts of bounded sides, no Python in core queries, pushed filters."""

import pytest

from freqemu.queries import QUERIES


def plan(df):
    return df._jdf.queryExecution().executedPlan().toString()


@pytest.mark.parametrize("name", ["ppswor_l1", "priority_l2", "bottomk_uniform", "advice_top", "topk_global"])
def test_samples_take_a_limit_in_each_task(spark, data, name):
    text = plan(QUERIES[name](spark, data))
    assert "TakeOrderedAndProject" in text
    assert "Python" not in text and "Pandas" not in text


@pytest.mark.parametrize("name", ["freq_table", "stat_moments", "advice_sketch", "nrmse_ppswor", "concave_sample", "pps_probs"])
def test_core_queries_run_without_python(spark, data, name):
    text = plan(QUERIES[name](spark, data))
    assert not any(x in text for x in ("BatchEvalPython", "ArrowEvalPython", "MapInArrow", "MapInPandas"))


def test_filters_reach_the_scan(spark, data):
    text = plan(QUERIES["src_parquet"](spark, data))
    assert "PushedFilters" in text and "o_totalprice" in text.split("PushedFilters")[1]
    assert "o_orderdate" not in text.split("ReadSchema")[1]


def test_group_limits(spark, data):
    assert "WindowGroupLimit" in plan(QUERIES["topk_group"](spark, data))
