import random

import pytest
from brute import answers, random_expr, random_graph

from pyspark.sql import functions as F

from pathq.functions import bounds
from pathq.functions.metrics import RunReport
from pathq.operators import kernels, matrix
from pathq.operators.capped_split import default_cap, evaluate_capped_split
from pathq.operators.fixpoint import Parts
from pathq.operators.closure import delta_sizes, transitive_closure
from pathq.operators.local import Local, flat
from pathq.operators.product import direct, product_edges, stored_loops
from pathq.operators.reach import capped_reach
from pathq.operators.reachable import connected, decide, shortest_length
from pathq.operators.search import product_search, recursive_sql
from pathq.operators.starfree import evaluate_star_free, path_join, plain_join, relations
from pathq.plans.automaton import compile_path
from pathq.plans.classify import classify
from pathq.plans.expr import parse
from pathq.plans.planner import canonical_of, choose, evaluate, evaluate_many, evaluate_with_report, explain_path, join_paths
from pathq.sources import builders
from pathq.sources.builders import from_sequence, from_triples
from pathq.store import Store, shared_root

EXAMPLE = [(1, "d", 2), (2, "e", 3), (3, "f", 4), (4, "g", 1), (2, "g", 5), (5, "e", 3), (6, "d", 6)]
EXPECTED = sorted([(1, 1), (1, 2), (1, 4), (1, 5), (2, 1), (2, 2), (2, 4), (2, 5), (3, 3), (4, 1), (4, 4), (5, 1), (5, 4), (5, 5), (6, 6)])


def rows(df):
    return sorted(tuple(r) for r in df.collect())


@pytest.mark.parametrize("method", ["auto", "capped-split", "search", "backward", "two-ended", "fused", "naive", "kernel", "kernel-search"])
def test_worked_example(spark, method):
    assert rows(evaluate(from_triples(spark, EXAMPLE), "d*(e f|g)*", method)) == EXPECTED


def test_reduction_sizes(spark):
    g, a = from_triples(spark, EXAMPLE), compile_path("d*(e f|g)*")
    assert product_edges(g, a).count() == 11
    count = {r["label"]: r["count"] for r in stored_loops(g, a).groupBy("label").count().collect()}
    assert count == {"a": 6, "b": 11, "c": 12}


def local(edges, expr):
    """The canonical graph of a query, built in Python."""
    a = compile_path(expr)
    import numpy as np

    n = a.n_states
    m = sorted({((t if s.backward else f) * n + q, (f if s.backward else t) * n + p) for f, label, t in edges for q, s, p in a.transitions if s.matches(label)})
    src, dst = (np.array([e[i] for e in m], np.int64) for i in (0, 1))
    starts = np.unique(src[np.isin(src % n, sorted(a.initial))])
    ends = np.unique(dst[np.isin(dst % n, sorted(a.accepting))])
    return a, Local.build((starts // n, starts), (src, dst), (ends, ends // n)) if len(m) else None


@pytest.mark.parametrize("seed", range(60))
def test_local_methods_against_brute_force(seed):
    rng = random.Random(seed)
    edges, expr = random_graph(rng), random_expr(rng)
    expected = [p for p in answers(edges, expr)]
    a, g = local(edges, expr)
    own = {(v, v) for e in edges for v in (e[0], e[2])} if a.nullable else set()
    for cap in (1, 2, 3, 7, "sqrt", None, "adaptive"):
        _, g = local(edges, expr)
        found = set(zip(*(x.tolist() for x in flat(g.capped_split(cap))), strict=True)) if g else set()
        assert sorted(found | own) == expected, (cap, expr)
        if g and isinstance(cap, int):
            c = g.counters
            assert c.reach_rows <= (c.n_light + c.n_heavy) * cap
            assert c.inspect_reach <= g.n_edges * cap and c.inspect_trail <= max(1, c.heavy_sources) * g.n_edges * a.n_states
    for method in ("search", "two_ended"):
        _, g = local(edges, expr)
        assert sorted((set(zip(*(x.tolist() for x in flat(getattr(g, method)())), strict=True)) if g else set()) | own) == expected


@pytest.mark.parametrize("seed", range(3))
def test_distributed_methods_against_brute_force(spark, seed):
    rng = random.Random(100 + seed)
    edges, expr = random_graph(rng, 9, 20, "abc"), random_expr(rng, 2, "abc")
    g, expected = from_triples(spark, edges), answers(edges, expr)
    canon, _ = canonical_of(g, expr, Store(spark, "test"))
    for cap in (1, 2, "sqrt"):
        assert rows(evaluate_capped_split(canon, Store(spark, "test"), cap)[0]) == expected
    assert rows(evaluate_capped_split(canon, Store(spark, "test"), 2, prune=True, shortcut=True)[0]) == expected
    assert rows(evaluate_capped_split(canon, Store(spark, "test"), 2, layout="array")[0]) == expected
    for direction in ("forward", "both"):
        assert rows(product_search(canon, Store(spark, "test"), direction)[0]) == expected
    assert rows(evaluate(g, expr)) == expected


def rings(n):
    one = [(i, x, i % n + 1) for i in range(1, n + 1) for x in "ab"]
    return one + [(100 + i, x, 100 + i % n + 1) for i in range(1, n + 1) for x in "bc"]


def test_two_rings(spark):
    canon = direct(from_triples(spark, rings(6)))
    assert canon.n_edges() == 24 and default_cap(24) == 5
    found, told = evaluate_capped_split(canon, Store(spark, "test"))
    assert found.count() == 0
    assert (told["cap"], told["reach_rows"], told["n_heavy"], told["n_light"], told["heavy_sources"], told["trail_rows"]) == (5, 30, 6, 0, 0, 0)
    # the search looks at 6 first edges before its walk and at 6 middle edges from each of 6 starts
    _, told = product_search(canon, Store(spark, "test"))
    assert told["inspect_search"] + 6 == 42


def test_path_without_end(spark):
    g = from_triples(spark, [(i, "b", i + 1) for i in range(1, 10)])
    canon, _ = canonical_of(g, "b* c")
    assert evaluate_with_report(g, "b* c", "capped-split")[1].inspect_reach == 0
    assert product_search(canon, Store(spark, "test"))[1]["inspect_search"] == 45
    assert product_search(canon, Store(spark, "test"), "backward")[1]["inspect_search"] == 0
    assert choose(g, "b* c").method == "empty"


def test_cap_boundary(spark):
    """A hub with as many answers as the root of the edge count is light, with one more it is heavy."""
    for n, heavy in ((4, 0), (5, 1)):
        star = [(0, "a", 1), *[(1, "c", 10 + i) for i in range(n)], *[(50 + i, "b", 60 + i) for i in range(16 - n - 1 + 4)]]
        canon = direct(from_triples(spark, star))
        cap = default_cap(canon.n_edges())
        assert cap == 5
        told = evaluate_capped_split(canon, Store(spark, "test"))[1]
        assert told["n_heavy"] == heavy


def test_nullable_and_isolated(spark):
    g = from_triples(spark, [(1, "a", 2)], vertices=[1, 2, 3])
    for method in ("closure", "capped-split", "search", "fused", "kernel"):
        assert rows(evaluate(g, "a*", method)) == [(1, 1), (1, 2), (2, 2), (3, 3)]
    assert rows(evaluate(g, "x*")) == [(1, 1), (2, 2), (3, 3)]
    assert rows(evaluate(g, "x")) == []


def test_overlap_of_light_and_heavy(spark):
    """One pair through a light and a heavy middle vertex appears once."""
    e = [(0, "a", 1), (0, "a", 2), (1, "c", 9), *[(2, "c", 9 + i) for i in range(8)]]
    canon = direct(from_triples(spark, e))
    found, told = evaluate_capped_split(canon, Store(spark, "test"), 3)
    assert told["n_heavy"] == 1 and told["n_light"] == 1
    assert rows(found) == [(0, 9 + i) for i in range(8)]


def test_empty_graph(spark):
    g = from_triples(spark, [(1, "a", 2)]).restrict_labels({"nothing"})
    for method in ("auto", "capped-split", "search", "two-ended", "fused", "kernel"):
        assert rows(evaluate(g, "a b*", method)) == []


def test_closure(spark):
    rng = random.Random(5)
    edges = random_graph(rng, 14, 26, "a")
    g = from_triples(spark, edges)
    e = g.edges.select("src", "dst")
    expected = answers(edges, "a+")
    for rule in ("delta", "right", "squaring", "deep"):
        assert rows(transitive_closure(e, Store(spark, "test"), rule, patience=2)[0]) == expected
    _, log = transitive_closure(e, Store(spark, "test"))
    out, n, v = len(expected), len(edges), len({x for s, _, t in edges for x in (s, t)})
    assert log.inspected <= out * n**0.5 + 1e-9 and log.inspected <= v * n
    degree = {}
    for s, _, _ in edges:
        degree[s] = degree.get(s, 0) + 1
    assert log.inspected == sum(degree.get(y, 0) for _, y in expected)
    assert sum(r["new_pairs"] for r in delta_sizes(e, Store(spark, "test")).collect()) == out
    assert rows(matrix.matrix_closure(e, Store(spark, "test"), 4)) == expected


@pytest.mark.parametrize("word", ["a b", "a a c", "b ^a c", "c b a b"])
def test_words(spark, word):
    edges = random_graph(random.Random(7), 12, 50, "abc")
    g = from_triples(spark, edges)
    parts = relations(g, classify(word).word)
    expected = answers(edges, word)
    assert rows(plain_join(parts)) == expected
    for cap in (1, 3, "adaptive"):
        assert rows(path_join(parts, Store(spark, "test"), cap)[0]) == expected
    assert rows(matrix.matrix_word(parts, Store(spark, "test"), 4)) == expected


def test_star_free_union(spark):
    edges = random_graph(random.Random(8), 10, 40, "abc")
    g = from_triples(spark, edges)
    for expr in ("(a|b c)(a|c)", "(a|b)?", "a (b|()) c"):
        assert rows(evaluate_star_free(g, parse(expr), Store(spark, "test"))[0]) == answers(edges, expr)
        assert rows(evaluate(g, expr, "layered")) == answers(edges, expr)


def test_sources_targets_decisions_lengths(spark):
    edges = random_graph(random.Random(9), 12, 30, "ab")
    g, expr = from_triples(spark, edges), "a (a|b)*"
    expected = answers(edges, expr)
    some = spark.createDataFrame([(1,), (5,)], "id long")
    assert rows(evaluate(g, expr, sources=some)) == [p for p in expected if p[0] in (1, 5)]
    assert rows(evaluate(g, expr, "capped-split", targets=some)) == [p for p in expected if p[1] in (1, 5)]
    canon, _ = canonical_of(g, expr)
    for pair in ((1, 5), (5, 1), (0, 11)):
        assert connected(canon, *pair, Store(spark, "test")) == (pair in expected)
    hops = {(r["src"], r["dst"]): r["hops"] for r in shortest_length(canon, Store(spark, "test")).collect()}
    assert sorted(hops) == expected and all(hops[s, t] == 1 for s, label, t in edges if label == "a")


def test_many_queries_and_conjunctions(spark):
    edges = random_graph(random.Random(10), 10, 30, "abc")
    g = from_triples(spark, edges)
    queries = {"p": "a b*", "q": "c a", "r": "(a|c)+ b"}
    queries["s"] = "a*"
    for limit in (0, 200_000):
        found = evaluate_many(g, queries, kernel_limit=limit).collect()
        for name, expr in queries.items():
            assert sorted((r["src"], r["dst"]) for r in found if r["query"] == name) == answers(edges, expr)
    joined = join_paths([(evaluate(g, "a"), "x", "y"), (evaluate(g, "b"), "y", "z")])
    a, b = answers(edges, "a"), answers(edges, "b")
    assert rows(joined.select("x", "y", "z")) == sorted((x, y, z) for x, y in a for y2, z in b if y == y2)


def test_components_kernel(spark):
    edges = [(10 * c + s, x, 10 * c + t) for c in range(3) for s, x, t in random_graph(random.Random(c), 6, 10, "ab")]
    g = from_triples(spark, edges)
    part = g.vertices.selectExpr("id", "id div 10 AS part")
    assert rows(evaluate(g, "a b*", "component", component=part)) == answers(edges, "a b*")


def test_limits_are_checked(spark):
    canon, _ = canonical_of(from_triples(spark, EXAMPLE), "d*(e f|g)*")
    with pytest.raises(kernels.TooLarge):
        kernels.in_tasks(canon, Store(spark, "test"), limit=3)
    with pytest.raises(ValueError):
        evaluate(from_triples(spark, EXAMPLE), "d", "unheard-of")


def test_bounds():
    assert bounds.bound_split(10, 100, 0) == 1000 and bounds.bound_search(10, 100) == 1000
    assert bounds.wins(1000, 2000, 10) and not bounds.wins(100, 10_000, 10**5)
    r = {(i, j) for i in range(4) for j in range(4) if (i + j) % 2}
    triangle = [(("x", "z"), r, 0.5), (("z", "y"), r, 0.5), (("x", "y"), r, 0.5)]
    assert bounds.decomposition_holds(triangle, ("x", "z"))
    with pytest.raises(ValueError):
        bounds.decomposition_holds([(("x", "y"), r, 0.4)], ("x",))
    assert all(RunReport(n_light=3, cap=2, reach_rows=6, canonical_edges=5, inspect_reach=10).invariants().values())


def test_plans(spark):
    """Rounds join by keys, the automaton is broadcast, and a cap is cut before the shuffle."""
    g = from_triples(spark, EXAMPLE)
    text = product_edges(g, compile_path("d*(e f|g)*"))._jdf.queryExecution().executedPlan().toString()
    assert "BroadcastHashJoin" in text and "Cartesian" not in text and "BroadcastNestedLoop" not in text
    canon, _ = canonical_of(g, "d*(e f|g)*")
    from pathq.operators.reach import _added

    lists = canon.ends.withColumn("n", F.lit(1))
    text = _added(canon.ends, lists, 3)._jdf.queryExecution().executedPlan().toString()
    assert "Window" in text and "left_anti" not in text.split("Union")[0]  # old and new entries meet in the window
    assert "Cartesian" not in text and "BroadcastNestedLoop" not in text
    assert capped_reach(canon, 2, Store(spark, "test"))[0].groupBy("x").count().filter("count > 2").count() == 0
    assert "method:" in explain_path(g, "d e*")


def test_store_is_removed(spark):
    import os

    store = Store(spark, "test")
    t, n = store.counted(spark.range(5), "numbers")
    assert n == 5 and t.count() == 5
    root = store.root.removeprefix("file://")
    assert os.path.isdir(root)
    last, n = store.finish(t.filter("id > 2"))
    assert n == 2 and not os.path.exists(root) and last.count() == 2


def test_store_wants_a_shared_folder():
    from types import SimpleNamespace

    conf = SimpleNamespace(get=lambda key: None)
    far = SimpleNamespace(sparkContext=SimpleNamespace(getConf=lambda: conf, getCheckpointDir=lambda: None, master="spark://host:7077"))
    with pytest.raises(ValueError):
        shared_root(far)


@pytest.mark.parametrize("method", ["auto", "capped-split", "search", "backward", "two-ended"])
def test_ids_that_leave_no_room(spark, method):
    """Ids so large that a vertex and a state do not fit one number."""
    top, expr = (1 << 63) - 20, "(a ^a)* b"
    edges = [(top + s, x, top + t - (1 << 63) * (t > 6)) for s, x, t in random_graph(random.Random(4), 9, 24, "ab")]
    assert rows(evaluate(from_triples(spark, edges), expr, method)) == answers(edges, expr)


def test_null_vertices_in_sequences(spark):
    """A null keeps its place in the order, at the border of ranges too, and no edge leads over it."""
    seq = [10, 20, None, 40, 50, None, None, 80, 90, 100, None, 120]
    df = spark.createDataFrame([(i, 0, v) for i, v in enumerate(seq)], "i long, k int, v long")
    expected = sorted((a, "x", b) for a, b in zip(seq, seq[1:], strict=False) if a is not None and b is not None)
    for width in (1, 3, 5, 12):
        assert rows(from_sequence(df, [], ["i"], "v", F.lit("x"), width=width).edges) == expected
    assert rows(from_sequence(df, ["k"], ["i"], "v", F.lit("x")).edges) == expected


def test_larger_caps_extend_lists(spark, monkeypatch):
    from pathq.operators import capped_split

    monkeypatch.setattr(capped_split, "FIRST_CAP", 1)
    for seed in (1, 2):
        edges = random_graph(random.Random(seed), 14, 60, "abc")
        canon, _ = canonical_of(from_triples(spark, edges), "a (b|c)* a", Store(spark, "test"))
        found, told = evaluate_capped_split(canon, Store(spark, "test"), "adaptive")
        assert told["cap"] >= 4 and rows(found) == answers(edges, "a (b|c)* a")


def test_parts_keep_all_rows(spark):
    parts = Parts(Store(spark, "test"), "parts", fan_in=2)
    for i in range(7):
        parts.add(spark.range(i, i + 1))
    assert sorted(r["id"] for r in parts.all().collect()) == list(range(7)) and sum(map(len, parts.levels)) <= 4


def test_decisions_of_many_pairs(spark):
    edges = random_graph(random.Random(12), 12, 26, "ab")
    for expr in ("a (a|b)* b", "b*"):
        expected = set(answers(edges, expr))
        canon, _ = canonical_of(from_triples(spark, edges), expr)
        ends = sorted({v for e in edges for v in (e[0], e[2])})
        pairs = [(s, t) for s in ends for t in ends if (s + t) % 3]
        told = decide(canon, spark.createDataFrame([*pairs, *pairs[:4], (None, 1)], "src long, dst long"), Store(spark, "test"))
        assert rows(told) == sorted((s, t, (s, t) in expected) for s, t in pairs)


def test_recursive_sql(spark):
    edges = [(i, "b", i + 1) for i in range(20)] + [(0, "a", 1), (3, "a", 4), (20, "c", 30)]
    found, levels = recursive_sql(canonical_of(from_triples(spark, edges), "a b* c")[0], Store(spark, "test"))
    assert rows(found) == answers(edges, "a b* c") and levels == 32


def test_report_is_filled(spark):
    edges = random_graph(random.Random(3), 12, 50, "abc")
    g = from_triples(spark, edges)
    own, base = (evaluate_with_report(g, "a b* c", m)[1] for m in ("capped-split", "search"))
    out = len(answers(edges, "a b* c"))
    assert own.out == base.out == out and own.n_edges == len(edges) and own.n_labels == 3
    assert own.n_light + own.n_heavy + own.n_absent == own.product_vertices and own.product_edges == base.product_edges > 0
    assert own.seconds > 0 and own.shuffle_bytes > 0 and own.peak_rows > 0 and base.out_states >= out
    assert own.gain_over(base) == base.inspect_search / (own.inspect_reach + own.inspect_trail) and own.bound_split > 0
    assert all(own.invariants().values()) and own.to_df(spark).count() == 1


def test_chooser_order(spark):
    g = from_triples(spark, random_graph(random.Random(6), 10, 40, "abc"))
    one = spark.createDataFrame([(1,)], "id long")
    assert choose(g, "a+").method == "closure" and choose(g, "x a").method == "empty"
    assert choose(g, "a b").method in ("plain-words", "star-free") and choose(g, "a b", plain_factor=0).method == "star-free"
    assert choose(g, "a b* c", sources=one, targets=one).method == "between" and choose(g, "a b* c", sources=one).method == "sources"
    assert choose(g, "a b* c").method == "kernel" and choose(g, "a b* c", kernel_limit=0).method == "capped-split"
    assert choose(g, " ".join(["(a|b)"] * 6)).method == "layered"


def test_table_function_matches_the_empty_path(spark):
    from pathq.functions import sqlapi

    sqlapi.register(spark)
    edges = [(1, "a", 2), (2, "a", 3), (4, "b", 5)]
    spark.createDataFrame([*edges, (None, "a", 9)], "src long, label string, dst long").withColumn("k", F.lit(1)).createOrReplaceTempView("pathq_edges")
    for expr in ("a*", "a a", "b ^b", "(a|b)?"):
        assert rows(spark.sql(f"SELECT src, dst FROM path_query(TABLE(pathq_edges) PARTITION BY (k), '{expr}')")) == answers(edges, expr)


def test_sources_and_sinks(spark, tmp_path):
    edges = sorted(random_graph(random.Random(2), 8, 20, "ab"))
    g = from_triples(spark, edges)
    g.edges.write.parquet(f"{tmp_path}/p")
    g.edges.select("src", "label", "dst").write.csv(f"{tmp_path}/c", header=True)
    g.edges.write.json(f"{tmp_path}/j")
    spark.sql("DROP TABLE IF EXISTS pathq_bucketed")
    builders.write_bucketed(g, "pathq_bucketed", 4)
    read = [builders.from_parquet(spark, f"{tmp_path}/p"), builders.from_csv(spark, f"{tmp_path}/c"), builders.from_json(spark, f"{tmp_path}/j"), builders.from_table(spark, "pathq_bucketed")]
    assert all(rows(x.edges.select("src", "label", "dst")) == edges for x in read)
    answers_ = evaluate(g, "a b")
    builders.write_parquet(answers_, f"{tmp_path}/out", 3)
    assert rows(spark.read.parquet(f"{tmp_path}/out")) == rows(answers_)
    spark.sql("DROP TABLE pathq_bucketed")
    stream = builders.from_stream(spark, f"{tmp_path}/p")
    q = stream.writeStream.format("memory").queryName("pathq_memory").trigger(availableNow=True).start()
    q.awaitTermination()
    assert spark.table("pathq_memory").count() == len(edges)


def test_neighbours_in_blocks(spark):
    import numpy as np

    x = np.random.default_rng(1).standard_normal((70, 6))
    rows_ = [(i, v.tolist()) for i, v in enumerate(x)] + [(70, None), (71, [0.0] * 6), (72, [1.0, None, 0.0, 0.0, 0.0, 0.0])]
    found = builders.nearest_by_cosine(spark.createDataFrame(rows_, "vec_id long, embedding array<double>"), 3, block=16)
    unit = x / np.linalg.norm(x, axis=1)[:, None]
    near = np.round(unit @ unit.T, 6)
    np.fill_diagonal(near, -9)
    best = np.argsort(-near, axis=1, kind="stable")[:, :3]
    assert rows(found) == sorted((i, int(j), r + 1) for i in range(70) for r, j in enumerate(best[i]))


def test_late_events_and_idle_users(spark):
    """What comes behind the watermark is dropped from windows; an idle user's state starts anew."""
    from pathq.store import Store as Folder
    from pathq.streaming import incremental as inc

    row = lambda i, minute, kind, user=1: (i, "2024-01-01 00:00:00", minute, kind, user)
    # the bound on late events follows the watermark by a batch
    batches = [[row(1, 0, "view"), row(2, 5, "purchase")], [row(3, 200, "view")], [row(7, 199, "view")], [row(4, 6, "click"), row(5, 201, "purchase")]]
    batches += [[row(8, 2000, "error", 2)], [row(9, 2001, "error", 2)], [row(6, 2002, "view")]]
    where = Folder(spark, "late").root
    for b in batches:
        df = spark.createDataFrame(b, "event_id long, day string, minute int, event_type string, user_id long")
        df.selectExpr("event_id", "timestampadd(MINUTE, minute, timestamp(day)) AS ts", "event_type", "user_id").repartition(1).write.mode("append").parquet(where)
    schema = spark.read.parquet(where).schema
    stream = lambda: spark.readStream.schema(schema).option("maxFilesPerTrigger", 1).parquet(where)
    told = inc.spread_pairs(inc.drain(inc.window_paths(stream(), "view (click)* purchase", "1 hour"), "late", "update", ("start", "user_id")))
    assert told.collect() == []  # nothing follows the purchases in their windows; with the late click something would
    told = inc.spread_pairs(inc.drain(inc.window_paths(stream(), "view", "1 hour"), "late2", "update", ("start", "user_id")))
    assert sorted((r["src"], r["dst"]) for r in told.collect()) == [(1, 2), (3, 5), (7, 3)]
    counts = inc.drain(inc.window_edges(stream(), "1 hour"), "late3", "update", ("start", "label"))
    assert sum(r["n"] for r in counts.collect()) == 8  # the late click is not counted
    stepped = inc.drain(inc.step_automaton(stream(), "view", idle="30 minutes"), "idle", "update", ("user_id",))
    assert {r["user_id"]: r["matched"] for r in stepped.collect()}[1] == 1  # of the last view alone: the state before it was dropped
