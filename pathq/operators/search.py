"""Searches over (start, vertex) pairs: the product search with its variants, and the walk from heavy vertices."""

from __future__ import annotations

import uuid

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from pathq.operators import kernels
from pathq.operators.fixpoint import Meter, Parts, RoundLog, iterate
from pathq.operators.product import Canonical, Packing, stored, to_canonical, transitions
from pathq.plans.automaton import Automaton
from pathq.sources.graph import PathGraph
from pathq.store import Store


def walk(seed: DataFrame, middle: DataFrame, store: Store, name: str = "walk", naive: bool = False) -> tuple[DataFrame, RoundLog]:
    """(s, x) closed under middle edges at x. Only pairs found in the last round are extended; with ``naive`` all are.

    Where the middle edges fit a task, the rounds are made inside tasks, which deal the seeds among them.
    """
    if not naive:
        told = kernels.walk_in_tasks(seed.distinct(), middle, store, name)
        if told is not None:
            return told

    def step(newest: DataFrame, total: DataFrame, meter: Meter) -> DataFrame:
        moved = (total if naive else newest).join(middle, F.col("x") == F.col("src")).select("s", F.col("dst").alias("x"))
        return meter.watch(moved).distinct().join(total, ["s", "x"], "left_anti")

    return iterate(seed.distinct(), step, store, name)


def arrivals(walked: DataFrame, ends: DataFrame) -> DataFrame:
    return walked.join(ends, "x").select(F.col("s").alias("src"), F.col("y").alias("dst"))


def with_identity(answers: DataFrame, canon: Canonical) -> DataFrame:
    """Distinct (src, dst), with the pairs of the empty path."""
    return (answers if canon.identity is None else answers.unionByName(canon.identity)).distinct()


def product_search(canon: Canonical, store: Store, direction: str = "forward", naive: bool = False) -> tuple[DataFrame, dict[str, int]]:
    """Distinct (src, dst) and counters of ``searched``."""
    return searched(canon, store, direction, naive)[:2]


def forward_looks(canon: Canonical, store: Store) -> int:
    """Edges that searches from all starts look at: counted inside tasks, or, where the edges exceed these, in rounds.

    Without ends, where ways do not fork, looks are the lengths of the ways, by doubling: one task holds twice as many rows for
    this, as no start needs a row of its own, and beyond it a round joins each way with what lies ahead of it.
    """
    canon, n = stored(canon, store)
    tasks = store.spark.sparkContext.defaultParallelism
    if not canon.packing.wide and n <= kernels.LIMIT:
        return kernels.in_tasks(canon, store, "search", tasks=tasks, only="counters")[1]["inspect_search"]
    one = lambda df, c: df.groupBy(c).count().filter("count > 1").isEmpty()
    if canon.ends.isEmpty() and one(canon.middle, "src") and one(canon.starts, "s"):
        if not canon.packing.wide and n <= 2 * kernels.LIMIT:
            return kernels.in_tasks(canon, store, "search", limit=n, only="counters")[1]["inspect_search"]
        looks = _way_looks(canon, store)
        if looks is not None:
            return looks
    return product_search(canon, store)[1]["inspect_search"]


def _way_looks(canon: Canonical, store: Store) -> int | None:
    """The lengths of the ways from all starts, where ways do not fork; None where one comes back to itself."""
    ways, n = store.counted(canon.middle.select(F.col("src").alias("v"), F.col("dst").alias("ahead"), F.lit(1).cast("long").alias("far")), "ways")
    for _ in range(n.bit_length() + 1):
        further = ways.select(F.col("v").alias("at"), F.col("ahead").alias("beyond"), F.col("far").alias("more"))
        joined = ways.join(further, F.col("ahead") == F.col("at"), "left")
        ways = store.table(joined.select("v", F.col("beyond").alias("ahead"), (F.col("far") + F.coalesce("more", F.lit(0))).alias("far")), "ways")
        if ways.filter("ahead is not null").isEmpty():
            return canon.starts.join(ways, F.col("x") == F.col("v")).agg(F.sum("far")).first()[0] or 0
    return None


def searched(canon: Canonical, store: Store, direction: str = "forward", naive: bool = False) -> tuple[DataFrame, dict[str, int], DataFrame | None]:
    """(answers, counters, visited (s, x), None for two-ended searches in a task): one search per start over the stored product; all searches advance together.

    ``backward`` starts at the ends on turned edges. ``both`` lets the side with fewer new pairs advance; the side that
    comes to its end first knows all answers.
    """
    if direction == "both":
        told = kernels.two_ended_in_task(canon, store)
        if told is not None:
            return with_identity(told[0], canon), {"inspect_search": told[1].inspected, "rounds": told[1].rounds}, None
        return _two_ended(canon, store)
    side = canon if direction == "forward" else canon.reversed()
    walked, log = walk(side.starts.select("s", "x"), side.middle, store, direction, naive)
    found = arrivals(walked, side.ends)
    if direction == "backward":
        found = found.select(F.col("dst").alias("src"), F.col("src").alias("dst"))
    return with_identity(found, canon), {"inspect_search": log.inspected, "rounds": log.rounds}, walked


def _two_ended(canon: Canonical, store: Store) -> tuple[DataFrame, dict[str, int], DataFrame]:
    class Side:
        def __init__(self, c: Canonical, name: str):
            self.c, self.name, self.meter, self.inspected, self.rounds = c, name, Meter(), 0, 0
            self.newest, self.n = store.counted(c.starts.select("s", "x").distinct(), name)
            self.parts = Parts(store, name)
            self.parts.add(self.newest)

        def advance(self) -> None:
            moved = self.newest.join(self.c.middle, F.col("x") == F.col("src")).select("s", F.col("dst").alias("x"))
            new = self.meter.watch(moved).distinct().join(self.parts.all(), ["s", "x"], "left_anti")
            self.newest, self.n = store.counted(new, self.name)
            self.inspected += self.meter.take()
            self.rounds += 1
            if self.n:
                self.parts.add(self.newest)

    front, rear = Side(canon, "front"), Side(canon.reversed(), "rear")
    while front.n and rear.n:
        (front if front.n <= rear.n else rear).advance()
    done = front if not front.n else rear
    found = arrivals(done.parts.all(), done.c.ends)
    if done is rear:
        found = found.select(F.col("dst").alias("src"), F.col("src").alias("dst"))
    return with_identity(found, canon), {"inspect_search": front.inspected + rear.inspected, "rounds": front.rounds + rear.rounds}, done.parts.all()


def recursive_sql(canon: Canonical, store: Store, hops: int = 8, most: int = 96) -> tuple[DataFrame, int]:
    """(answers, levels): a recursive query of SQL. It cannot remove repeats between its levels, so their number is bounded,
    and the bound doubled until the last level holds no pair that was not there before. Raises above ``most`` levels."""
    spark = canon.middle.sparkSession
    names = {k: f"pathq_{k}_{uuid.uuid4().hex}" for k in ("starts", "middle")}
    store.table(canon.starts.select("s", "x").distinct(), "starts").createOrReplaceTempView(names["starts"])
    store.table(canon.middle, "middle").createOrReplaceTempView(names["middle"])
    while True:
        walked = store.table(
            spark.sql(f"""
            WITH RECURSIVE walk(s, x, h) AS (
              SELECT s, x, 0 FROM {names["starts"]} UNION ALL SELECT s, dst, h + 1 FROM walk JOIN {names["middle"]} ON x = src WHERE h < {hops})
            SELECT s, x, min(h) AS h FROM walk GROUP BY s, x"""),
            "walked",
        )
        if walked.filter(F.col("h") == hops).isEmpty():
            break
        if 2 * hops > most:
            raise RuntimeError(f"more than {most} levels")
        hops *= 2
    for name in names.values():
        spark.catalog.dropTempView(name)
    return with_identity(arrivals(walked.select("s", "x"), canon.ends), canon), hops


def fused_search(graph: PathGraph, automaton: Automaton, store: Store) -> tuple[DataFrame, dict[str, int]]:
    """The search without a stored product: every round joins new pairs with the graph's edges and the transitions. Where the product
    fits a task, the rounds are made inside tasks, to which its edges are dealt as they are made."""
    packing = Packing.of(graph, automaton.n_states)
    if not packing.wide and all(s.but is None for _, s, _ in automaton.transitions):
        canon = to_canonical(graph, automaton, packing=packing)
        told = kernels.walk_in_tasks(canon.starts, canon.middle, store, "fused")
        if told is not None:
            return with_identity(arrivals(told[0], canon.ends), canon), {"inspect_search": told[1].inspected, "rounds": told[1].rounds}
    moves = F.broadcast(transitions(graph, automaton).withColumnRenamed("q", "state"))
    both = graph.edges.select(F.col("src").alias("here"), F.col("label").alias("by"), F.col("dst").alias("there"), F.lit(False).alias("turn")).unionByName(
        graph.edges.select(F.col("dst").alias("here"), F.col("label").alias("by"), F.col("src").alias("there"), F.lit(True).alias("turn"))
    )
    if not any(s.backward for _, s, _ in automaton.transitions):
        both = both.filter(~F.col("turn"))

    def step(newest: DataFrame, total: DataFrame, meter: Meter) -> DataFrame:
        moved = newest.join(moves, F.col("q") == F.col("state")).join(both, (F.col("v") == F.col("here")) & (F.col("label") == F.col("by")) & (F.col("turned") == F.col("turn")))
        return meter.watch(moved.select("s", F.col("there").alias("v"), F.col("p").alias("q"))).distinct().join(total, ["s", "v", "q"], "left_anti")

    starts = both.select(F.col("here").alias("s")).distinct().withColumn("q", F.explode(F.array(*[F.lit(q) for q in sorted(automaton.initial)])))
    walked, log = iterate(starts.select("s", F.col("s").alias("v"), "q"), step, store, "fused")
    # a start in an accepting state answers itself only by the empty path, which identity adds for every vertex
    found = walked.filter(F.col("q").isin(sorted(automaton.accepting))).select(F.col("s").alias("src"), F.col("v").alias("dst"))
    if automaton.nullable:
        found = found.unionByName(graph.vertices.select(F.col("id").alias("src"), F.col("id").alias("dst")))
    return found.distinct(), {"inspect_search": log.inspected, "rounds": log.rounds}
