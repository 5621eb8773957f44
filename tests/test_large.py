"""What let queries end on larger tables: rounds inside tasks, answers that are read later, counts without answers."""

import random

import numpy as np
import pytest
from brute import answers, random_graph

from pathq.operators import kernels, local
from pathq.operators.local import Local
from pathq.plans.planner import choose, evaluate, evaluate_with_report
from pathq.sources.builders import from_triples

CHAIN = [(i, "x", i + 1) for i in range(150)]


def jobs(spark, run):
    """(what ``run`` gives, Spark jobs that it took)."""
    group = f"counted-{random.random()}"
    spark.sparkContext.setJobGroup(group, "counted")
    try:
        return run(), len(spark.sparkContext.statusTracker().getJobIdsForGroup(group))
    finally:
        spark.sparkContext.setLocalProperty("spark.jobGroup.id", None)


@pytest.mark.parametrize("expr,method", [("x+", "auto"), ("x*", "auto"), ("x x* x", "search"), ("x x* x", "capped-split")])
def test_deep_chains_take_few_jobs(spark, expr, method):
    n, took = jobs(spark, lambda: evaluate(from_triples(spark, CHAIN), expr, method).count())
    assert n == {"x+": 150 * 151 // 2, "x*": 151 * 152 // 2}.get(expr, 149 * 150 // 2)
    assert took < 100


def test_report_of_a_deep_search(spark):
    g = from_triples(spark, CHAIN)
    (_, r), took = jobs(spark, lambda: evaluate_with_report(g, "x x* x", "search"))
    assert (r.out, r.rounds, took < 100) == (149 * 150 // 2, 151, True)


def test_lists_over_arrays_are_those_of_sets():
    rng = random.Random(4)
    for _ in range(20):
        e = np.array(sorted({(rng.randrange(30), rng.randrange(30)) for _ in range(45)}))
        ends = np.unique(e[:10, 1])
        for cap in (1, 3, None):
            one, two = (Local.build((e[:5, 0], e[:5, 0]), (e[:, 0], e[:, 1]), (ends, ends)) for _ in range(2))
            a, b = one.reach(cap), two.lists(cap)
            assert [len(x or ()) for x in a] == np.diff(b.at).tolist()
            if cap is None:
                assert [sorted(x or ()) for x in a] == [b.of(v).tolist() for v in range(two.n)]
                assert one.counters.inspect_reach == two.counters.inspect_reach == sum(two.looks)
            assert two.lists(None, 1) is None


def test_looks_of_a_long_way_are_not_walked(monkeypatch):
    at, none = np.arange(200_000), np.zeros(0, np.int64)
    g = Local.build((at, at), (at, at + 1), (none, none))
    monkeypatch.setattr(g, "visits", None)
    assert list(g.search()) == [] and g.counters.inspect_search == 200_000 * 200_001 // 2


def test_searches_beyond_one_task_of_lists_are_dealt(spark):
    edges = random_graph(random.Random(8), 12, 40, "abc")
    g = from_triples(spark, edges)
    assert choose(g, "a b* c", kernel_limit=1).method == "kernel-search"
    for later in (False, True):
        assert sorted(tuple(r) for r in evaluate(g, "a b* c", later=later, kernel_limit=1).collect()) == answers(edges, "a b* c")


def _links(spark, tmp_path, n):
    """Pages of which each links to its own number and the next, in two chains."""
    html = [(i, "http://x", "".join(f'<a href="/{t}">' for t in (i, i + 1) if not (t == n and i < n))) for i in range(2 * n)]
    spark.createDataFrame(html, "page_id long, url string, html string").write.parquet(f"{tmp_path}/pages.parquet")


@pytest.mark.parametrize("name", ["co_linked_closure", "co_linked_pages_closure"])
def test_co_linked_pages_are_classes(spark, tmp_path, name):
    from pathq import workloads

    _links(spark, tmp_path, 40)
    df, took = jobs(spark, lambda: workloads.QUERIES[name](spark, str(tmp_path)))
    if name == "co_linked_closure":
        assert sorted(tuple(r) for r in df.collect()) == [(0, 2 * 40 * 40, 80), (1, 81, 81)]
    else:
        found = [tuple(r) for r in df.collect()]
        assert sorted(found) == sorted((2 * a, 2 * b) for a in range(80) for b in range(80) if (a < 40) == (b < 40))
    assert took < 40


@pytest.mark.parametrize("giant", [1, 3])
def test_a_giant_part_is_searched_once(monkeypatch, giant):
    monkeypatch.setattr(local, "GIANT", giant)
    rng, real = np.random.default_rng(3), Local.giant
    pairs = lambda a, b, n: np.unique(np.stack((rng.integers(*a, n), rng.integers(*b, n)), 1), axis=0)
    for _ in range(40):
        n = int(rng.integers(2, 60))
        parts = [tuple(pairs(a, b, k).T) for a, b, k in (((100, 120), (0, n), 30), ((0, n), (0, n), int(rng.integers(1, 150))), ((0, n), (200, 215), 25))]
        one, two, whole = Local.build(*parts), Local.build(*parts), []
        written = sorted(zip(*(c.tolist() for c in local.flat(one.search())), strict=True))
        rest = list(zip(*(c.tolist() for c in local.flat(two.search(crossed=whole))), strict=True))
        assert written == sorted(rest + [(a, b) for p, q in whole for a in p.tolist() for b in q.tolist()])
        assert len(written) == len(set(written)) == one.counters.out and one.counters == two.counters
        monkeypatch.setattr(Local, "giant", lambda g: None)
        plain = Local.build(*parts)
        assert written == sorted(zip(*(c.tolist() for c in local.flat(plain.search())), strict=True))
        assert (plain.counters.inspect_search, plain.counters.trail_rows) == (one.counters.inspect_search, one.counters.trail_rows)
        monkeypatch.setattr(Local, "giant", real)


def test_answers_through_a_ring_take_few_looks(monkeypatch):
    n = 20_000
    at = np.arange(n)
    g = Local.build((at, at), (np.append(at, 0), np.append((at + 1) % n, 7)), (at, at))
    monkeypatch.setattr(Local, "visits", lambda g, only=None: iter(()) if not len(g.s) else pytest.fail("searched anew"))
    whole = []
    assert list(g.search(crossed=whole)) == [] and [(len(a), len(b)) for a, b in whole] == [(n, n)]
    assert g.counters.out == n * n


@pytest.mark.parametrize("limit", [0, kernels.LIMIT])
def test_shortest_lengths_beyond_40_hops(spark, monkeypatch, limit):
    from pathq.operators.reachable import shortest_length
    from pathq.plans.planner import canonical_of
    from pathq.store import Store

    monkeypatch.setattr(kernels, "LIMIT", limit)
    n = 60 if limit else 8  # in rounds over the cluster only as long as needed to hold them against the others
    chain = [(0, "a", 1), *((i, "b", i + 1) for i in range(1, n)), (n, "c", n + 1), (n, "b", 1)]
    found, took = jobs(spark, lambda: sorted(tuple(r) for r in shortest_length(canonical_of(from_triples(spark, chain), "a b* c")[0], Store(spark, "test")).collect()))
    assert found == [(0, n + 1, n + 1)] and (took < 20 or not limit)


@pytest.mark.parametrize("cut", [1, 1 << 20])
def test_shortest_lengths_are_those_of_plain_rounds(monkeypatch, cut):
    monkeypatch.setattr(local, "CUT", cut)
    rng = random.Random(7)
    for _ in range(30):
        n = rng.randrange(2, 25)
        pairs = lambda a, b, k: sorted({(a + rng.randrange(n), b + rng.randrange(n)) for _ in range(k)})
        starts, middle, ends = pairs(100, 0, 12), pairs(0, 0, 2 * n), pairs(0, 200, 10)
        expected = {}
        for s in {s for s, _ in starts}:
            front, seen, far = {x for a, x in starts if a == s}, set(), 0
            while front:
                for y in {y for x, y in ends if x in front}:
                    expected.setdefault((s, y), far)
                seen, far = seen | front, far + 1
                front = {b for a, b in middle if a in front} - seen
        g = Local.build(*(tuple(np.array(p).T) for p in (starts, middle, ends)))
        blocks = list(g.hops())
        found = {(s, y): h for b in blocks for s, y, h in zip(*(c.tolist() for c in b), strict=True)}
        assert found == expected and sum(len(b[0]) for b in blocks) == len(found)


def test_matrix_of_scattered_edges(spark):
    """Nearly all blocks hold a bit, so that multiplying every two that meet would take 200,000 products of bitmaps."""
    from pathq.operators import matrix
    from pathq.store import Store

    at = np.random.default_rng(5).permutation(30_000)
    chains = [(int(at[i]), int(at[i + 1])) for i in range(29_999) if i % 3 != 2]
    found = matrix.matrix_closure(spark.createDataFrame(chains, "src long, dst long"), Store(spark, "test"))
    assert sorted(tuple(r) for r in found.collect()) == sorted(chains + [(int(at[i]), int(at[i + 2])) for i in range(0, 30_000, 3)])


@pytest.mark.parametrize("block", [5, 64])
def test_matrix_of_lists_and_bitmaps(spark, block):
    from pathq.operators import matrix
    from pathq.store import Store

    rng, n = np.random.default_rng(6), 5 * block // 2
    a, b = (rng.random((n, n)) < np.where(np.arange(n) < block, d, 0.004)[:, None] for d in (0.5, 0.3))
    frame = lambda m: spark.createDataFrame([tuple(map(int, p)) for p in zip(*np.nonzero(m), strict=True)], "i long, j long")
    one, two = (matrix.to_blocks(frame(m), block) for m in (a, b))
    product = matrix.multiply(one, two, block)
    if block == 64:
        assert one.filter("bits is null").count() and one.filter("at is null").count() and product.filter("at is null").count()
    assert sorted(tuple(r) for r in matrix.to_pairs(product, block).collect()) == [tuple(p) for p in np.argwhere((a.astype(int) @ b.astype(int)) > 0).tolist()]
    assert product.agg({"ones": "sum"}).first()[0] == ((a.astype(int) @ b.astype(int)) > 0).sum()


def test_sketched_degrees_are_counted_in_one_pass(spark, monkeypatch):
    from pathq import workloads

    edges = random_graph(random.Random(11), 30, 90, ("1-URGENT", "3-MEDIUM", "5-LOW"))
    monkeypatch.setattr(workloads, "handoff", lambda spark, d, above: from_triples(spark, edges))
    monkeypatch.setattr(workloads, "degrees", lambda found: pytest.fail("answers are read again"))
    found = workloads.degrees_sketched(spark, "")
    assert [tuple(r) for r in found.collect()] == [(len({s for s, _ in answers(edges, workloads.SHORT)}), 0)]


@pytest.mark.parametrize("method", ["two-ended", "fused"])
def test_other_searches_of_deep_chains_take_few_jobs(spark, method):
    n, took = jobs(spark, lambda: evaluate(from_triples(spark, CHAIN), "x x* x", method).count())
    assert n == 149 * 150 // 2 and took < 60


def test_two_ended_in_arrays_has_a_bound():
    rng = np.random.default_rng(12)
    for _ in range(20):
        parts = [tuple(np.unique(rng.integers(0, 20, (k, 2)), axis=0).T) for k in (8, 30, 8)]
        written, two = (Local.build(*parts) for _ in range(2))
        assert sorted(zip(*(c.tolist() for c in local.flat(two.two_ended())), strict=True)) == sorted(zip(*(c.tolist() for c in local.flat(written.search())), strict=True))
        visits = Local.build(*parts)
        assert list(visits.two_ended(0)) == [None]
