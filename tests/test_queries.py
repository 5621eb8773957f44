"""Queries against their SQL, on the smallest tables; the driver runs all of them on larger ones."""

import pytest

from pathq import oracles, workloads

FAST = [
    "handoff_sparse", "flow_funnel", "flow_dead_end", "relay_sparse", "chat_alternation", "customer_to_region", "same_nation_suppliers", "co_linked_pages",
    "copy_components", "quoted_items", "automaton_transitions", "word_expansion", "query_classes", "graph_handoff_edges", "graph_partchain_edges", "graph_turns_edges",
    "canonical_sizes", "light_heavy_classes", "heavy_answers", "light_answers", "cost_report", "bound_checks", "two_rings_cost", "one_path_cost", "matrix_blocks",
    "stream_window_tumbling", "stream_session_paths", "stream_user_automaton", "sql_path_query", "sql_path_matches", "flow_in_window", "asof_label", "interval_edges", "answers_rollup",
]


@pytest.mark.parametrize("name", FAST)
def test_query(spark, duck, sf, name):
    df = workloads.QUERIES[name](spark, sf)
    columns = sorted(df.columns)
    cursor = duck.execute(oracles.ORACLES[name])
    names = [d[0] for d in cursor.description]
    assert sorted(names) == columns
    order = [names.index(c) for c in columns]
    key = lambda r: tuple((x is None, str(x)) for x in r)
    assert sorted((tuple(r) for r in df.select(columns).collect()), key=key) == sorted((tuple(r[i] for i in order) for r in cursor.fetchall()), key=key)


def test_entry_points(spark):
    import __spark_entry__ as entry

    assert set(entry.oracle_sql()) <= set(entry.queries())
    assert entry.entry(spark).columns == ["src", "dst"]


def test_batches_in_any_order(spark):
    from pathq.streaming.incremental import IncrementalClosure

    e = [(1, 2), (2, 3), (3, 1), (4, 5), (3, 4)]
    found = []
    for order in ([0, 1, 2, 3, 4], [4, 2, 0, 3, 1]):
        grow = IncrementalClosure(spark)
        for i in order:
            grow.add(spark.createDataFrame([e[i]], "src long, dst long"))
        found.append(sorted(tuple(r) for r in grow.pairs.collect()))
    assert found[0] == found[1] and len(found[0]) == 16
