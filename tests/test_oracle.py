"""Every registered query with a SQL twin gives the twin's rows, on the smallest tables."""

import pytest
from conftest import same

from treeline.queries import forest, plans, relational, streams, workloads

ALL = {}
for m in (forest, plans, relational, streams, workloads):
    ALL |= {n: (m.QUERIES[n], s) for n, s in m.SQL.items()}
#: Those that grow a forest or run a stream take seconds each; a few stand for the rest here, all run in the driver.
SLOW = {"q_tree_depth3", "q_tree_vertical", "q_tree_predict_joins", "q_vote_table", "q_oob_by_class", "q_task_graph", "q_dynamic_weights", "q_regress_vote_norm", "q_stream_hourly", "q_stream_score", "q_accuracy"}
FAST = [n for n in relational.SQL] + [n for n in forest.SQL if n.startswith(("q_bins", "q_draw", "q_oob", "q_slice", "q_gain", "q_sel", "q_imp", "q_sparse", "q_poisson"))] + ["q_volume", "q_allocate_prefix", "q_allocate_first_fit", "q_speedup", "q_ops"]


@pytest.mark.parametrize("name", sorted({*FAST, *SLOW}))
def test_twin(spark, duck, small, name):
    query, sql = ALL[name]
    left, right = same(query(spark, small), duck, sql)
    assert left == right


def test_contract(spark):
    import __spark_entry__ as e

    assert {n for n in e.oracle_sql()} <= set(e.queries())
    assert e.entry(spark).count() >= 0
