"""Product of a graph and an automaton, and the canonical form ``a b* c`` that every query reduces to."""

from __future__ import annotations

import math
from dataclasses import dataclass

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from pathq.plans.automaton import Automaton
from pathq.sources.graph import PathGraph
from pathq.store import Store


@dataclass(frozen=True)
class Packing:
    """How a vertex and a state become one product vertex: one BIGINT, or, where ids leave no room for that, a pair (id, q)."""

    n_states: int
    wide: bool = False

    @classmethod
    def of(cls, graph: PathGraph, n_states: int) -> Packing:
        """The BIGINT where every id of the graph times the number of states fits it. Reads the edges once, but for one state."""
        return cls.within(graph.id_range(), n_states) if n_states > 1 else cls(n_states)

    @classmethod
    def within(cls, ids: tuple[int, int], n_states: int) -> Packing:
        return cls(n_states, ids[0] * n_states < -(1 << 63) or (ids[1] + 1) * n_states > (1 << 63) - 1)

    def pack(self, vertex: Column, state: Column | int) -> Column:
        q = F.lit(state) if isinstance(state, int) else state
        if self.wide:
            return F.struct(vertex.alias("id"), q.cast("int").alias("q"))
        return vertex * F.lit(self.n_states).cast("long") + q

    def state(self, packed: Column) -> Column:
        return packed["q"] if self.wide else F.pmod(packed, F.lit(self.n_states).cast("long"))

    def vertex(self, packed: Column) -> Column:
        """Exact for negative ids too: what is divided is a multiple."""
        if self.wide:
            return packed["id"]
        whole = packed - self.state(packed)
        return whole if self.n_states == 1 else F.call_function("div", whole, F.lit(self.n_states).cast("long"))


def transitions(graph: PathGraph, automaton: Automaton) -> DataFrame:
    """(q, label, p, turned): a row per transition, as many as the query has."""
    rows = [(q, s.label, p, s.backward) for q, s, p in sorted(automaton.transitions, key=lambda t: (t[0], t[1].label, t[2]))]
    return graph.spark.createDataFrame(rows, "q int, label string, p int, turned boolean")


def product_edges(graph: PathGraph, automaton: Automaton, packing: Packing | None = None) -> DataFrame:
    """(src, dst) packed: an edge of the graph and a transition under the same label. Two labels may give one product edge."""
    packing = packing or Packing.of(graph, automaton.n_states)
    joined = graph.edges.join(F.broadcast(transitions(graph, automaton)), "label")
    ahead, behind = F.when(F.col("turned"), F.col("dst")).otherwise(F.col("src")), F.when(F.col("turned"), F.col("src")).otherwise(F.col("dst"))
    return joined.select(packing.pack(ahead, F.col("q")).alias("src"), packing.pack(behind, F.col("p")).alias("dst")).distinct()


@dataclass(frozen=True)
class Canonical:
    """``a b* c`` over three relations: starts (s, x), middle edges (src, dst), ends (x, y).

    s and y are ids of answers, x and the middle's columns are ids of the graph that is searched. ``identity`` holds the
    pairs (v, v) of the empty path, if the query has it. ``n_edges`` is the count that sets the default cap.
    """

    starts: DataFrame
    middle: DataFrame
    ends: DataFrame
    identity: DataFrame | None = None
    packing: Packing = Packing(1)

    def n_edges(self) -> int:
        return self.middle.count() + self.starts.count() + self.ends.count()

    def reversed(self) -> Canonical:
        turn = lambda df, a, b: df.select(F.col(b).alias(a), F.col(a).alias(b))
        return Canonical(self.ends.select(F.col("y").alias("s"), "x"), turn(self.middle, "src", "dst"), self.starts.select("x", F.col("s").alias("y")), turn(self.identity, "src", "dst") if self.identity is not None else None, self.packing)

    def seeded(self, sources: DataFrame | None = None, targets: DataFrame | None = None) -> Canonical:
        """Only answers from some sources (id) into some targets (id); both cut the relations before any search."""
        starts, ends, identity = self.starts, self.ends, self.identity
        if sources is not None:
            starts = starts.join(sources.select(F.col("id").alias("s")), "s", "left_semi")
            identity = identity.join(sources.select(F.col("id").alias("src")), "src", "left_semi") if identity is not None else None
        if targets is not None:
            ends = ends.join(targets.select(F.col("id").alias("y")), "y", "left_semi")
            identity = identity.join(targets.select(F.col("id").alias("dst")), "dst", "left_semi") if identity is not None else None
        return Canonical(starts, self.middle, ends, identity, self.packing)


def to_canonical(graph: PathGraph, automaton: Automaton, middle: DataFrame | None = None, initial: frozenset[int] | None = None, accepting: frozenset[int] | None = None, packing: Packing | None = None) -> Canonical:
    """The reduction, with its loops kept to product vertices that an edge leaves or enters.

    An answer by a non-empty path leaves an initial state and enters an accepting one, so starts come from the sources of
    product edges and ends from their targets; the empty path is ``identity``. End states are projected away at once.
    """
    packing = packing or Packing.of(graph, automaton.n_states)
    initial, accepting = initial if initial is not None else automaton.initial, accepting if accepting is not None else automaton.accepting
    middle = product_edges(graph, automaton, packing) if middle is None else middle
    at = lambda c, states: middle.filter(packing.state(F.col(c)).isin(sorted(states)) if states else F.lit(False)).select(F.col(c).alias("x")).distinct()
    starts, ends = at("src", initial), at("dst", accepting)
    identity = None
    if initial & accepting:
        v = graph.vertices
        identity = v.select(F.col("id").alias("src"), F.col("id").alias("dst"))
    return Canonical(starts.select(packing.vertex(F.col("x")).alias("s"), "x"), middle, ends.select("x", packing.vertex(F.col("x")).alias("y")), identity, packing)


def stored_loops(graph: PathGraph, automaton: Automaton) -> DataFrame:
    """The reduction with every loop as a row: (src, label, dst) packed, labels a, b and c."""
    packing = Packing(automaton.n_states)  # rows with one BIGINT per end are what the direct route takes

    def loops(states: frozenset[int], label: str) -> DataFrame:
        # one row per vertex and state; there are as many states as the query has
        spread = graph.vertices.withColumn("q", F.explode(F.array(*[F.lit(q) for q in sorted(states)])))
        return spread.select(packing.pack(F.col("id"), F.col("q")).alias("src"), F.lit(label).alias("label"), packing.pack(F.col("id"), F.col("q")).alias("dst"))

    b = product_edges(graph, automaton, packing).select("src", F.lit("b").alias("label"), "dst")
    return b.unionByName(loops(automaton.initial, "a")).unionByName(loops(automaton.accepting, "c"))


def direct(graph: PathGraph, a: str = "a", b: str = "b", c: str = "c") -> Canonical:
    """A graph that already has the three labels, without an automaton."""
    part = lambda label: graph.edges.filter(F.col("label") == label)
    return Canonical(
        part(a).select(F.col("src").alias("s"), F.col("dst").alias("x")),
        part(b).select("src", "dst"),
        part(c).select(F.col("src").alias("x"), F.col("dst").alias("y")),
    )


def default_cap(n_edges: int) -> int:
    return math.isqrt(n_edges) + 1


def stored(canon: Canonical, store: Store) -> tuple[Canonical, int]:
    """(the same relations as tables, their number of rows)."""
    (starts, a), (middle, b), (ends, c) = (store.counted(df, name) for df, name in ((canon.starts.distinct(), "starts"), (canon.middle, "middle"), (canon.ends.distinct(), "ends")))
    return Canonical(starts, middle, ends, canon.identity, canon.packing), a + b + c
