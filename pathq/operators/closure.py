"""Transitive closure by rounds over new pairs."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from pathq.operators import kernels
from pathq.operators.fixpoint import Meter, RoundLog, iterate
from pathq.store import Store


def transitive_closure(edges: DataFrame, store: Store, rule: str = "delta", reflexive: DataFrame | None = None, patience: int = 24) -> tuple[DataFrame, RoundLog]:
    """Distinct (src, dst) joined by one edge or more; with ``reflexive`` (id) also every (v, v).

    ``delta`` extends each pair once, in the round after it was found, by the edges at its end: the join with the edges
    comes first, then distinct, then the test against all pairs. ``right`` puts an edge in front instead. ``squaring`` joins
    new pairs with all pairs, which takes a logarithmic number of rounds but may do more work. ``deep`` starts as ``delta``
    and goes on by squaring after ``patience`` rounds: what delta rounds have found by then are all pairs up to a distance,
    and the newest those at it, so every farther pair has a shortest path that a newest pair begins. ``tasks`` makes the
    rounds of ``delta`` inside tasks, where the edges fit one, and is ``deep`` elsewhere.
    """
    if rule == "tasks":
        told = closure_in_tasks(edges, store, reflexive)
        if told is not None:
            return told
        rule = "deep"
    e = store.table(edges.select("src", "dst").distinct(), "edges")
    hop = e.select(F.col("src").alias("here"), F.col("dst").alias("there"))

    def delta(newest: DataFrame, total: DataFrame, meter: Meter) -> DataFrame:
        moved = newest.join(hop, F.col("dst") == F.col("here")).select("src", F.col("there").alias("dst"))
        return meter.watch(moved).distinct().join(total, ["src", "dst"], "left_anti")

    def right(newest: DataFrame, total: DataFrame, meter: Meter) -> DataFrame:
        moved = newest.join(hop, F.col("src") == F.col("there")).select(F.col("here").alias("src"), "dst")
        return meter.watch(moved).distinct().join(total, ["src", "dst"], "left_anti")

    def squaring(newest: DataFrame, total: DataFrame, meter: Meter) -> DataFrame:
        other = total.select(F.col("src").alias("here"), F.col("dst").alias("there"))
        ahead = newest.join(other, F.col("dst") == F.col("here")).select("src", F.col("there").alias("dst"))
        behind = newest.join(other, F.col("src") == F.col("there")).select(F.col("here").alias("src"), "dst")
        return meter.watch(ahead.unionByName(behind)).distinct().join(total, ["src", "dst"], "left_anti")

    steps = {"delta": delta, "left": delta, "right": right, "squaring": squaring, "deep": delta}
    found, log = iterate(e, steps[rule], store, f"closure-{rule}", change=(patience, squaring) if rule == "deep" else None)
    if reflexive is not None:
        found = found.unionByName(reflexive.select(F.col("id").alias("src"), F.col("id").alias("dst"))).distinct()
    return found, log


def closure_in_tasks(edges: DataFrame, store: Store, reflexive: DataFrame | None = None, only: str | None = None) -> tuple[DataFrame | None, RoundLog] | None:
    """The closure by a walk from every edge, dealt by its source; with ``only="answers"`` pairs are found when they are read, with
    "counters" they are counted only. None where the edges do not fit a task."""
    e = store.table(edges.select("src", "dst").distinct(), "edges")
    seed = e.select(F.col("src").alias("s"), F.col("dst").alias("x"))
    if reflexive is not None:
        seed = seed.unionByName(reflexive.select(F.col("id").alias("s"), F.col("id").alias("x"))).distinct()
    told = kernels.walk_in_tasks(seed, e, store, "closure", only)
    if told is None:
        return None
    return told[0].select(F.col("s").alias("src"), F.col("x").alias("dst")) if told[0] is not None else None, told[1]


def delta_sizes(edges: DataFrame, store: Store) -> DataFrame:
    """(round, new_pairs): round 0 are the edges; round i the pairs at distance i + 1."""
    e = edges.select("src", "dst").distinct()
    n = e.count()
    _, log = transitive_closure(e, store)
    rows = [(0, n), *((i + 1, k) for i, k in enumerate(log.new_rows) if k)]
    return edges.sparkSession.createDataFrame([(i, k) for i, k in rows if k], "round long, new_pairs long")


def class_pairs(classes: DataFrame, store: Store, chunk: int = 1024) -> DataFrame:
    """(src, dst) of all pairs of one class, from (id, class); found when they are read.

    Members are held in chunks, and any two chunks of a class are a row of their own, so no task has to make the pairs of
    a whole class, and pairs are neither shuffled nor written.
    """
    sized = classes.join(classes.groupBy("class").agg(F.ceil(F.count(F.lit(1)) / chunk).alias("chunks")), "class")
    held = store.table(sized.groupBy("class", F.pmod(F.xxhash64("id"), F.col("chunks")).alias("chunk")).agg(F.collect_list("id").alias("ids")), "chunks")
    met = held.select("class", F.col("ids").alias("a")).join(held.select("class", F.col("ids").alias("b")), "class").select("a", "b")
    dealt = met.repartition(8 * classes.sparkSession.sparkContext.defaultParallelism)
    return dealt.select(F.explode("a").alias("src"), "b").select("src", F.explode("b").alias("dst"))
