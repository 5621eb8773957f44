"""What is asked of single vertices: reachable sets, degrees, decisions, shortest lengths."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from pathq.operators import kernels
from pathq.operators.fixpoint import Parts
from pathq.operators.product import Canonical
from pathq.operators.reach import capped_reach
from pathq.operators.search import arrivals, walk, with_identity
from pathq.store import Store


def reachable(canon: Canonical, sources: DataFrame, store: Store) -> DataFrame:
    """(src, dst) for the sources (id) only: the search starts there and nowhere else."""
    part = canon.seeded(sources=sources)
    middle = store.table(canon.middle, "middle")
    walked, _ = walk(part.starts.select("s", "x"), middle, store, "reachable")
    return with_identity(arrivals(walked, canon.ends), part)


def answers_into(canon: Canonical, targets: DataFrame, store: Store) -> DataFrame:
    """(src, dst) for the targets (id) only, searched backwards from them."""
    turned = canon.seeded(targets=targets).reversed()
    found = reachable(turned, targets, store)
    return found.select(F.col("dst").alias("src"), F.col("src").alias("dst"))


def degrees(answers: DataFrame) -> DataFrame:
    """(v, deg): number of answers per source."""
    return answers.groupBy(F.col("src").alias("v")).agg(F.count(F.lit(1)).alias("deg"))


def approximate_degrees(answers: DataFrame, error: float = 0.05) -> DataFrame:
    """(v, deg) by distinct-count sketches, for answers that may repeat."""
    return sketched(answers, error=error).withColumnRenamed("about", "deg")


def sketched(answers: DataFrame, *beside: Column, error: float = 0.05) -> DataFrame:
    """(v, about) by distinct-count sketches, with further aggregates ``beside`` them of the same pass over the answers."""
    return answers.groupBy(F.col("src").alias("v")).agg(F.approx_count_distinct("dst", error).alias("about"), *beside)


def capped_degrees(canon: Canonical, cap: int, store: Store) -> DataFrame:
    """(x, deg) with deg = min(number of ends reached, cap)."""
    reach, _ = capped_reach(Canonical(canon.starts, store.table(canon.middle, "middle"), canon.ends, None, canon.packing), cap, store)
    return reach.groupBy("x").agg(F.count(F.lit(1)).alias("deg"))


def connected(canon: Canonical, source: int, target: int, store: Store) -> bool:
    """Whether (source, target) is an answer: a walk from the source that stops at the first hit."""
    spark = canon.middle.sparkSession
    part = canon.seeded(spark.createDataFrame([(source,)], "id long"), spark.createDataFrame([(target,)], "id long"))
    if part.identity is not None and not part.identity.isEmpty():
        return True
    middle, ends = store.table(canon.middle, "middle"), store.table(part.ends, "ends")
    newest, n = store.counted(part.starts.select("x").distinct(), "seed")
    seen = Parts(store, "seen")
    while n:
        seen.add(newest)
        if not newest.join(ends, "x", "left_semi").isEmpty():
            return True
        moved = newest.join(middle, F.col("x") == F.col("src")).select(F.col("dst").alias("x")).distinct()
        newest, n = store.counted(moved.join(seen.all(), "x", "left_anti"), "front")
    return False


def decide(canon: Canonical, pairs: DataFrame, store: Store) -> DataFrame:
    """(src, dst, connected) for given pairs (src, dst): whether each is an answer.

    Walks from the sources asked for, and leaves a source alone once all its pairs are decided; the end side is cut to
    the targets asked for before the first round.
    """
    pairs = store.table(pairs.select("src", "dst").dropna().distinct(), "pairs")
    part = canon.seeded(pairs.select(F.col("src").alias("id")).distinct(), pairs.select(F.col("dst").alias("id")).distinct())
    middle, ends = store.table(canon.middle, "middle"), store.table(part.ends.distinct(), "ends")
    hit = lambda walked: walked.join(ends, "x").select(F.col("s").alias("src"), F.col("y").alias("dst")).distinct().join(pairs, ["src", "dst"], "left_semi")
    known = pairs.filter("src = dst").join(part.identity.select("src"), "src", "left_semi") if part.identity is not None else pairs.limit(0)
    open_, left = store.counted(pairs.join(known, ["src", "dst"], "left_anti"), "open")
    newest, n = store.counted(part.starts.select("s", "x").distinct(), "seed")
    seen = Parts(store, "seen")
    while n and left:
        seen.add(newest)
        open_, left = store.counted(open_.join(hit(newest), ["src", "dst"], "left_anti"), "open")
        live = newest.join(open_.select(F.col("src").alias("s")).distinct(), "s", "left_semi")
        moved = live.join(middle, F.col("x") == F.col("src")).select("s", F.col("dst").alias("x")).distinct()
        newest, n = store.counted(moved.join(seen.all(), ["s", "x"], "left_anti"), "front")
    return pairs.join(open_.withColumn("missed", F.lit(True)), ["src", "dst"], "left").select("src", "dst", F.col("missed").isNull().alias("connected"))


def shortest_length(canon: Canonical, store: Store) -> DataFrame:
    """(src, dst, hops): middle edges on a shortest answer path, however long; 0 for the empty path.

    Where the relations fit a task, the rounds are made inside tasks, which deal the starts among them.
    """
    found = kernels.hops_in_tasks(canon, store)
    if found is None:
        found = _hops_in_rounds(canon, store)
    elif canon.identity is None:
        return found
    if canon.identity is not None:
        found = found.unionByName(canon.identity.withColumn("hops", F.lit(0).cast("long")))
    return found.groupBy("src", "dst").agg(F.min("hops").alias("hops"))


def _hops_in_rounds(canon: Canonical, store: Store) -> DataFrame:
    """(src, dst, hops), where a pair may repeat."""
    middle = store.table(canon.middle, "middle")
    newest, n = store.counted(canon.starts.select("s", "x").distinct().withColumn("hops", F.lit(0).cast("long")), "seed")
    parts, depth = Parts(store, "walked"), 0
    parts.add(newest)
    while n:
        depth += 1
        moved = newest.join(middle, F.col("x") == F.col("src")).select("s", F.col("dst").alias("x")).distinct()
        fresh = moved.join(parts.all().select("s", "x"), ["s", "x"], "left_anti").withColumn("hops", F.lit(depth).cast("long"))
        newest, n = store.counted(fresh, "front")
        parts.add(newest)
    return parts.all().join(canon.ends, "x").select(F.col("s").alias("src"), F.col("y").alias("dst"), "hops")
