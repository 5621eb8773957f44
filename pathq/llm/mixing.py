"""Mixing sources to target weights by temperature.

Token shares of the sources are raised to an exponent and normalised. The exponent is found by bisection: for
a target entropy (a share of the largest possible one) or for a limit on how often any source repeats within
the budget. The weights are then realised: every source's documents are dealt into blocks, blocks are permuted
anew for every epoch by a hash, and whole blocks are taken until the source's part of the budget is met; the
block at the edge gives its leading documents.

Every step is a DataFrame operation over sources or blocks; the driver sees only sums over sources. A pass
over the small table of sources evaluates 31 points at once and so does five bisection steps.

Edge cases: a null source is a source of its own. Documents of length 0 have no share and are taken in epoch
0 only. One source gets weight 1 whatever the exponent. With no tokens at all every document is taken once.
Repeated rows are rows of their own. A target outside the reachable range gives the nearest end. An empty table
gives an empty result. Columns that clash with the added ones are replaced.
"""

from __future__ import annotations

import math

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from pathq.llm.common import Workspace
from pathq.llm.packing import word_length

ADDED = ("n_tokens", "weight", "epoch", "block", "position")


def source_totals(measured: DataFrame) -> DataFrame:
    return measured.groupBy("source").agg(F.sum("n_tokens").alias("tokens"), F.count(F.lit(1)).alias("docs"))


def _at(totals: DataFrame, alphas: list[float], budget: float) -> list[tuple[float, float]]:
    """(entropy, most repeats) at each exponent, in one pass over the sources."""
    logs = F.log(F.col("tokens").cast("double"))
    live = totals.filter("tokens > 0")
    top = live.agg(F.max(logs)).first()[0]
    shift = logs - F.lit(top)
    sums = []
    for a in alphas:
        z = F.exp(shift * a)
        sums += [F.sum(z), F.sum(z * shift * a), F.max(z / F.col("tokens"))]
    row = live.agg(*[s.alias(f"s{i}") for i, s in enumerate(sums)]).first()
    out = []
    for i in range(len(alphas)):
        total, weighted, rate = row[3 * i], row[3 * i + 1], row[3 * i + 2]
        out.append((math.log(total) - weighted / total, budget * rate / total))
    return out


def exponent(totals: DataFrame, budget: float, target_entropy: float | None = None, max_repeats: float | None = None, lowest: float = 0.0, highest: float = 1.0, passes: int = 6) -> float:
    """The exponent in [lowest, highest] at which entropy comes down to the target, or repeats come down to the limit.

    Both fall as the exponent rises, so the sought point is the smallest exponent that meets the condition.
    """
    n = totals.filter("tokens > 0").count()
    if n <= 1 or target_entropy is None and max_repeats is None:
        return highest
    wanted = None if target_entropy is None else target_entropy * math.log(n)

    def met(point: tuple[float, float]) -> bool:
        return (wanted is None or point[0] <= wanted) and (max_repeats is None or point[1] <= max_repeats + 1e-12)

    lo, hi = lowest, highest
    ends = _at(totals, [lo, hi], budget)
    if met(ends[0]):
        return lo
    if not met(ends[1]):
        return hi
    for _ in range(passes):
        grid = [lo + (hi - lo) * k / 32 for k in range(1, 32)]
        marks = [met(x) for x in _at(totals, grid, budget)]
        first = next((k for k, m in enumerate(marks) if m), 31)
        lo, hi = ([lo] + grid)[first], (grid + [hi])[first]
    return hi


def weights(totals: DataFrame, alpha: float) -> DataFrame:
    """(source, tokens, docs, weight): normalised powers of the token shares."""
    logs = F.log(F.when(F.col("tokens") > 0, F.col("tokens")).cast("double"))
    top = totals.agg(F.max(logs)).first()[0]
    powered = F.coalesce(F.exp((logs - F.lit(top or 0.0)) * alpha), F.lit(0.0))
    total = totals.agg(F.sum(powered)).first()[0]
    return totals.select("source", "tokens", "docs", (powered / F.lit(total) if total else F.lit(0.0)).alias("weight"))


def mix(
    docs: DataFrame,
    length: Column | None = None,
    target_entropy: float | None = 0.97,
    max_repeats: float | None = None,
    budget_share: float = 1.0,
    block_tokens: int = 1 << 18,
    seed: int = 11,
) -> DataFrame:
    """The mixed stream: a row for every time a document is taken, with n_tokens, weight of its source, epoch, block and position.

    ``position`` in [0, 1) orders the stream; sources are spread evenly in it. The budget is ``budget_share`` of
    all tokens. A source of weight w gets w times the budget: whole epochs first, then blocks of the next
    permutation, then leading documents of the block at the edge, as long as they fit.
    """
    spark = docs.sparkSession
    work = Workspace(spark, "mixing")
    kept = docs.drop(*ADDED)
    measured = kept.withColumn("n_tokens", word_length(F.col("text")) if length is None else length)
    totals = work.table(source_totals(measured.select("source", "n_tokens")), "sources")
    corpus = totals.agg(F.coalesce(F.sum("tokens"), F.lit(0)).alias("t")).first()["t"]
    budget = corpus * budget_share
    alpha = exponent(totals, budget, target_entropy, max_repeats) if corpus else 1.0
    plan = weights(totals, alpha).select(
        F.col("source").alias("__s"),
        "weight",
        F.greatest(F.lit(1), F.ceil(F.col("tokens") / block_tokens)).cast("long").alias("__blocks"),
        F.when(F.col("tokens") > 0, F.col("weight") * budget / F.col("tokens")).otherwise(1.0).alias("__rate"),
        F.greatest(F.col("weight") * budget, F.lit(0.0)).alias("__budget"),
        F.col("tokens").alias("__tokens"),
    )
    plan = work.table(plan.withColumn("__full", F.floor(F.col("__rate") + 1e-9).cast("long")), "weights")
    ids = [c for c in ("doc_id",) if c in kept.columns] or kept.columns[:1]
    tie = F.xxhash64(F.lit(seed), *[F.col(c) for c in ids])
    dealt = measured.join(plan, F.col("source").eqNullSafe(F.col("__s"))).withColumn("__tie", tie)
    dealt = dealt.withColumn("block", F.pmod(F.col("__tie"), F.col("__blocks")))
    order = F.xxhash64(F.lit(seed), F.col("__full"), F.col("block"))  # of blocks, in the epoch that is taken in part
    blocks = dealt.groupBy("__s", "block", "__full", "__budget", "__tokens").agg(F.sum("n_tokens").alias("__size"))
    running = Window.partitionBy("__s").orderBy("__order", "block").rowsBetween(Window.unboundedPreceding, -1)
    rest = F.col("__budget") - F.col("__full") * F.col("__tokens")
    edges = (
        blocks.withColumn("__order", order)
        .withColumn("__before", F.coalesce(F.sum("__size").over(running), F.lit(0)))
        .select(F.col("__s").alias("__bs"), F.col("block").alias("__b"), (rest - F.col("__before")).alias("__room"), "__size")
    )
    edges = work.table(edges, "blocks")
    placed = dealt.join(edges, F.col("__s").eqNullSafe(F.col("__bs")) & (F.col("block") == F.col("__b")))
    inside = Window.partitionBy("__s", "block").orderBy("__tie", *ids).rowsBetween(Window.unboundedPreceding, 0)
    edge = (F.col("__room") > 0) & (F.col("__room") < F.col("__size"))
    whole, cut = placed.filter(~edge).withColumn("__upto", F.lit(0).cast("long")), placed.filter(edge).withColumn("__upto", F.sum("n_tokens").over(inside))
    takes = F.col("__full") + F.when(F.col("__room") <= 0, 0).when(F.col("__room") >= F.col("__size"), 1).otherwise(F.when(F.col("__upto") <= F.col("__room"), 1).otherwise(0))
    takes = F.when(F.col("n_tokens") > 0, takes).otherwise(1)
    if not corpus:
        takes = F.lit(1).cast("long")
    taken = whole.unionByName(cut).withColumn("__takes", takes.cast("int")).filter("__takes > 0")
    out = taken.withColumn("epoch", F.explode(F.sequence(F.lit(0), F.col("__takes") - 1)))
    spread = lambda *c: F.pmod(F.xxhash64(F.lit(seed), *c), F.lit(1 << 30)) / float(1 << 30)
    # within an epoch blocks come in the order of their hash, documents in the order of theirs
    place = (F.col("epoch") + spread(F.col("epoch"), F.col("block"), F.col("__s")) + spread(F.col("__tie"), F.col("epoch")) / (F.col("__blocks") + 1)) / (F.greatest(F.col("__rate"), F.lit(1.0)) + 1)
    return out.withColumn("position", place).select(*kept.columns, *ADDED)


def op4_mixing(spark, sf_dir: str) -> DataFrame:
    """A row per document: how often it is taken, with its source's weight; texts are not carried along."""
    work = Workspace(spark, "mixing-lengths")
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet").select("doc_id", "source", word_length(F.col("text")).alias("__len"))
    docs = work.table(docs, "lengths")  # texts are read once
    mixed = mix(docs, length=F.col("__len"), target_entropy=0.97, max_repeats=4.0)
    return work.finish(mixed.select("doc_id", "source", "n_tokens", F.round("weight", 9).alias("weight"), "epoch", "block", F.round("position", 9).alias("position")))
