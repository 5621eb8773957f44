"""SQL front: path queries as table functions and scalar tests."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from pathq.operators.local import Local, flat
from pathq.plans.automaton import Automaton, compile_path
from pathq.sources.graph import PathGraph

LIMIT = 5_000_000


def local_answers(src: np.ndarray, label: np.ndarray, dst: np.ndarray, expr: str) -> tuple[np.ndarray, np.ndarray]:
    """Distinct answers over the edges of one component, in memory; the empty path answers for every end of an edge."""
    a = compile_path(expr)
    n = a.n_states
    names, src, dst = np.unique(np.concatenate((src, dst))), np.asarray(src, np.int64), np.asarray(dst, np.int64)
    u, v = np.searchsorted(names, src), np.searchsorted(names, dst)  # dense, so that product vertices fit a number
    moves = [np.empty((0, 2), np.int64)]
    for q, symbol, p in a.transitions:
        at = np.array([symbol.matches(x) for x in label], bool)
        here, there = (v[at], u[at]) if symbol.backward else (u[at], v[at])
        moves.append(np.stack((here * n + q, there * n + p), axis=1))
    m = np.unique(np.concatenate(moves), axis=0)
    starts = np.unique(m[np.isin(m[:, 0] % n, sorted(a.initial)), 0])
    ends = np.unique(m[np.isin(m[:, 1] % n, sorted(a.accepting)), 1])
    found = flat(Local.build((starts // n, starts), (m[:, 0], m[:, 1]), (ends, ends // n)).capped_split()) if len(starts) and len(ends) else (starts[:0], starts[:0])
    own = np.arange(len(names) if a.nullable else 0)
    pairs = np.unique(np.stack((np.append(found[0], own), np.append(found[1], own)), axis=1).astype(np.int64), axis=0)
    return names[pairs[:, 0]], names[pairs[:, 1]]


class PathQuery:
    """UDTF body: gathers a partition's edges as Arrow batches, answers when it ends. One partition is one component of the graph.

    Edges with a null end or label are no edges.
    """

    def __init__(self) -> None:
        self.held: list[pa.Table] = []
        self.n, self.expr = 0, None

    def eval(self, edges: pa.RecordBatch, expr: pa.Array) -> Iterator[pa.Table]:
        if edges.num_rows:
            self.expr = self.expr or expr[0].as_py()
            whole = pa.table({c: edges[c] for c in ("src", "label", "dst")}).drop_null()
            self.held.append(whole)
            self.n += whole.num_rows
            if self.n > LIMIT:
                raise ValueError(f"a component has more than {LIMIT} edges; use pathq.plans.planner.evaluate")
        return iter(())

    def terminate(self) -> Iterator[pa.Table]:
        if self.n:
            whole = pa.concat_tables(self.held)
            src, dst = local_answers(whole["src"].to_numpy(), whole["label"].to_numpy(), whole["dst"].to_numpy(), self.expr)
            yield pa.table({"src": pa.array(src, pa.int64()), "dst": pa.array(dst, pa.int64())})


def matches(automaton: Automaton, words: pd.Series) -> pd.Series:
    """Whether each array of labels is a word of the automaton; null arrays give null."""
    step: dict[tuple[frozenset, str], frozenset] = {}

    def move(states: frozenset, label: str) -> frozenset:
        key = (states, label)
        if key not in step:
            step[key] = frozenset(p for q, s, p in automaton.transitions if q in states and not s.backward and s.matches(label))
        return step[key]

    def accepts(word) -> bool | None:
        if word is None:
            return None
        now = automaton.initial
        for label in word:
            now = move(now, label)
        return bool(now & automaton.accepting)

    return words.map(accepts).astype("boolean")


def matcher(expr: str):
    """A column function: does an ARRAY<STRING> of labels match the expression?"""
    automaton = compile_path(expr)

    @F.pandas_udf("boolean")
    def test(words: pd.Series) -> pd.Series:
        return matches(automaton, words)

    return test


def capped_set(column, cap: int):
    """Aggregate: the ``cap`` smallest distinct values."""
    return F.slice(F.array_sort(F.collect_set(column)), 1, cap)


def register(spark: SparkSession, graph: PathGraph | None = None, name: str = "edges") -> None:
    """The table function ``path_query(TABLE(...) PARTITION BY (...), expr)``, the scalar ``path_matches(labels, expr)`` and, with a graph, views of it."""
    spark.udtf.register("path_query", F.arrow_udtf(PathQuery, returnType="src bigint, dst bigint"))

    @F.pandas_udf("boolean")
    def path_matches(words: pd.Series, exprs: pd.Series) -> pd.Series:
        out = pd.Series([None] * len(words), dtype="boolean")
        for expr in exprs.dropna().unique():
            at = (exprs == expr).to_numpy()
            out[at] = matches(compile_path(expr), words[at]).to_numpy()
        return out

    spark.udf.register("path_matches", path_matches)
    if graph is not None:
        graph.edges.createOrReplaceTempView(name)
        graph.vertices.createOrReplaceTempView(f"{name}_vertices")


def answers_view(answers: DataFrame, name: str) -> None:
    answers.createOrReplaceTempView(name)
