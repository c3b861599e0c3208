"""Queries against their SQL, on the smallest tables."""

import pytest

from conftest import SMALL, same
from patcard.plans import registry

NAMES = ["exact_P5", "exact_P6", "exact_P10", "exact_P16", "exact_P19", "stats_P5", "vwalk_P5", "vwalk_P6", "vwalk_nobranch_P6", "vwalk_b1_P5", "vwalk_iso_P9", "ewalk_P5", "ewalk_early_P6", "domain_exact_P5", "edges_G_act", "vertices_G_doc", "op_as_of_join", "op_range_join", "op_rollup", "op_recursive", "op_hash_sample", "stream_complete", "order_P7", "agm_P7", "vwalk_budget_P6", "batchwalk_P5", "corrhash_P5", "summary_P6", "boundsketch_P5", "htblind_toy", "samplesize_P6", "vwalk_disconnected", "index_saved", "op_views", "op_udtf", "source_triples", "stream_late", "stream_sessions"]


@pytest.mark.parametrize("name", NAMES)
def test_query_equals_sql(spark, duck, name):
    assert same(registry.queries()[name](spark, SMALL), duck.execute(registry.oracle_sql()[name]).df())


def test_every_oracle_has_a_query():
    assert set(registry.oracle_sql()) <= set(registry.queries())


def test_plans_have_no_cartesian_product(spark):
    df = registry.queries()["exact_P7"](spark, SMALL)
    plan = df._jdf.queryExecution().executedPlan().toString()
    assert "CartesianProduct" not in plan and "LeftSemi" in plan


def test_walks_cross_no_graph_rows(spark):
    """The first vertex is drawn by number: no product of calls and candidates."""
    for name in ("vwalk_P6", "vwalk_P5", "batchwalk_P5"):
        plan = registry.queries()[name](spark, SMALL)._jdf.queryExecution().optimizedPlan().toString()
        crossed = [line for line in plan.splitlines() if "Join Cross" in line or "Join Inner" in line and "=" not in line]
        assert all("broadcast" in line for line in crossed), crossed


def test_entry(spark):
    import __spark_entry__ as e

    assert set(registry.queries()) <= set(e.queries())
