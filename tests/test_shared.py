"""Capped lists that vertices share, and the whole method inside tasks, without its answers being written."""

import random
from dataclasses import replace

import numpy as np
import pytest
from brute import answers, random_graph
from test_large import jobs

from pathq import workloads
from pathq.operators import kernels, local
from pathq.operators.capped_split import evaluate_capped_split
from pathq.operators.local import Local
from pathq.plans.planner import canonical_of, evaluate, evaluate_with_report, report_only
from pathq.sources.builders import from_triples
from pathq.store import Store


@pytest.mark.parametrize("piece,small", [(1, 0), (7, 4096), (1 << 22, 0)])
def test_shared_lists_are_those_of_rounds(monkeypatch, piece, small):
    monkeypatch.setattr(local, "PIECE", piece)
    monkeypatch.setattr(local, "SMALL", small)
    rng = random.Random(9)
    for _ in range(40):
        n = rng.choice([5, 30, 80])
        e = np.array(sorted({(rng.randrange(n), rng.randrange(n)) for _ in range(int(n * rng.choice([0.7, 1.2, 2])))}))
        ends = np.unique([(rng.randrange(n), 100 + rng.randrange(12)) for _ in range(rng.choice([1, 10, 25]))], axis=0)
        for cap in (1, 3, None):
            one, two, whole = (Local.build((e[:5, 0], e[:5, 0]), tuple(e.T), tuple(ends.T)) for _ in range(3))
            rounds, shared, complete = one.lists(cap), two.shared(cap), whole.lists(None)
            assert np.diff(rounds.at).tolist() == shared.size[shared.which].tolist()
            for v in range(one.n):
                at = shared.begin[shared.which[v]]
                own = shared.held[at : at + shared.size[shared.which[v]]].tolist()
                assert len(set(own)) == len(own) and set(own) <= set(complete.of(v).tolist())
            assert one.counters == two.counters and two.counters.inspect_reach == sum(two.looks)
            assert sum(two.new_rows) == len(rounds.to)


def test_strongly_connected_parts():
    rng = random.Random(10)
    for _ in range(40):
        n = rng.randrange(2, 40)
        e = np.array(sorted({(rng.randrange(n), rng.randrange(n)) for _ in range(rng.randrange(1, 3 * n))}))
        g = Local.build((e[:1, 0], e[:1, 0]), tuple(e.T), (e[:1, 1], e[:1, 1]))
        met = np.eye(g.n, dtype=bool)
        met[np.repeat(np.arange(g.n), np.diff(g.middle.at)), g.middle.to] = True
        for k in range(g.n):
            met |= met[:, k : k + 1] & met[k : k + 1, :]
        assert ((met & met.T) == (g.parts[:, None] == g.parts[None, :])).all()


def test_full_lists_are_held_once():
    n = 50_000
    at = np.arange(n)
    g = Local.build((at, at), (at[:-1], at[1:]), (at, at))
    lists = g.shared(20, 1000)
    assert lists is not None and len(lists.held) < 1000 and lists.size[lists.which].sum() == 20 * n - 190
    assert g.lists(20, 1000) is None


@pytest.mark.parametrize("expr,cap", [("a b* c", 4), ("(a b)* (b|c) a*", 1)])
def test_method_without_its_answers(spark, expr, cap):
    edges = random_graph(random.Random(12), 12, 40, "abc")
    g, expected = from_triples(spark, edges), answers(edges, expr)
    assert sorted(tuple(r) for r in evaluate(g, expr, "capped-split", later=True, cap=cap).collect()) == expected
    found, one = evaluate_with_report(g, expr, "capped-split", cap=cap)
    told, run = report_only(g, expr, "capped-split", cap=cap), dict.fromkeys(("seconds", "shuffle_bytes", "peak_rows"), 0)
    assert sorted(tuple(r) for r in found.collect()) == expected and told.out == len(expected)
    assert replace(told, **run) == replace(one, **run)


def test_sources_with_light_and_heavy_starts(spark):
    """0 begins at 1, whose list is full, and at 4, whose list is not; both lead to 6."""
    e = [(0, "a", 1), (0, "a", 4), (1, "b", 2), (1, "c", 6), (2, "c", 7), (2, "c", 8), (4, "c", 6)]
    from pathq.operators.product import direct

    canon, store = direct(from_triples(spark, e)), Store(spark, "test")
    for only in (None, "answers"):
        found, told = evaluate_capped_split(canon, store, cap=3, only=only)
        assert sorted(tuple(r) for r in found.collect()) == [(0, 6), (0, 7), (0, 8)] and told["n_heavy"] == 1
    found, told = evaluate_capped_split(canon, store, cap=3, only="counters")
    assert found is None and told["out"] == 3


@pytest.mark.parametrize("name", ["handoff_split_rounds", "cost_report", "bound_checks", "run_costs"])
def test_whole_method_writes_no_answers(spark, monkeypatch, name):
    """Answers are counted, or found when they are read."""
    n = 30
    ring = [(i, "3-MEDIUM", (i + 1) % n) for i in range(n)] + [(i, x, (7 * i) % n) for i in range(n) for x in ("1-URGENT", "5-LOW")]
    monkeypatch.setattr(workloads, "handoff", lambda spark, d, above: from_triples(spark, ring))
    monkeypatch.setattr(Store, "finish", lambda *a: pytest.fail("answers are written"))
    found, took = jobs(spark, lambda: [tuple(r) for r in workloads.QUERIES[name](spark, "").collect()])
    assert took < 80
    if name == "handoff_split_rounds":
        assert sorted(found) == answers(ring, workloads.SHORT)
    elif name == "cost_report":
        told = dict(zip(workloads.REPORTED, found[0], strict=True))
        assert (told["out"], told["n_heavy"] > 0) == (len(answers(ring, workloads.SHORT)), True)
    else:
        assert all(r[1] for r in found)


@pytest.mark.parametrize("limit", [0, 20, 30])
def test_looks_of_ways_beyond_a_task(spark, monkeypatch, limit):
    """In rounds by doubling, in a task of twice the rows, and on ways that come back to themselves."""
    from pathq.operators.search import forward_looks

    monkeypatch.setattr(kernels, "LIMIT", limit)
    chain = [(7 * i % 17, "b", 7 * (i + 1) % 17) for i in range(16)]
    for edges, expected in ((chain, 16 * 17 // 2), ([(0, "b", 1), (1, "b", 0), (2, "b", 1)], None)):
        if expected is None and limit:
            continue
        store = Store(spark, "test")
        canon = canonical_of(from_triples(spark, edges), "b* c", store)[0]
        assert forward_looks(canon, store) == (expected or 2 + 2 + 3)
