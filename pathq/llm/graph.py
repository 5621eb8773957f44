"""Connected components over a table of links, in rounds of joins; nothing is gathered on the driver."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from pathq.llm.common import Workspace


def forest(a: np.ndarray, b: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """A star forest with the same components as the links (a, b): every vertex but the smallest, with its component's smallest."""
    ids, where = np.unique(np.concatenate((a, b)), return_inverse=True)
    x, y = where[: len(a)], where[len(a) :]
    label = np.arange(len(ids))
    while True:
        p, q = label[x], label[y]
        if np.array_equal(p, q):
            break
        low = np.minimum(p, q)
        np.minimum.at(label, p, low)
        np.minimum.at(label, q, low)
        while not np.array_equal(label, deeper := label[label]):
            label = deeper
    inner = label != np.arange(len(ids))
    return ids[inner], ids[label[inner]]


def _contract(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    held: list[tuple[np.ndarray, np.ndarray]] = []
    n = 0
    for batch in batches:
        held.append((batch["a"].to_numpy(), batch["b"].to_numpy()))
        n += batch.num_rows
        if n > 1_000_000:
            held = [forest(*map(np.concatenate, zip(*held, strict=True)))]
            n = len(held[0][0])
            if n > 500_000:  # little to contract here; pass it on
                yield pa.RecordBatch.from_arrays([pa.array(held[0][0]), pa.array(held[0][1])], names=["a", "b"])
                held, n = [], 0
    if held:
        a, b = forest(*map(np.concatenate, zip(*held, strict=True)))
        yield pa.RecordBatch.from_arrays([pa.array(a), pa.array(b)], names=["a", "b"])


def components(links: DataFrame, work: Workspace, max_rounds: int = 60) -> DataFrame:
    """(id, component): for every id in the links (a, b), the smallest id that it reaches.

    Each task first contracts its own links to stars. Then large-star and small-star rounds alternate: neighbours
    larger than a vertex move to its smallest neighbour, then smaller neighbours do. A hub's links are
    aggregated before the shuffle, and joins on hubs are plain, so that adaptive execution can split them.
    """
    e = work.table(links.select(F.col("a").cast("long"), F.col("b").cast("long")).filter("a <> b").mapInArrow(_contract, "a long, b long"), "links")
    shape = None
    for _ in range(max_rounds):
        both = e.select(F.col("a").alias("u"), F.col("b").alias("v")).union(e.select("b", "a"))
        least = work.table(both.groupBy("u").agg(F.least(F.min("v"), F.col("u")).alias("m")), "least")
        large = both.filter("v > u").join(least, "u").select(F.col("v").alias("u"), F.col("m").alias("v")).filter("u <> v").distinct()
        large = work.table(large, "large")
        down = large.select(F.greatest("u", "v").alias("u"), F.least("u", "v").alias("v"))
        least = work.table(down.groupBy("u").agg(F.min("v").alias("m")), "least")
        small = down.join(least, "u").select(F.explode(F.array(F.struct(F.col("v").alias("u"), F.col("m").alias("v")), F.struct(F.col("u"), F.col("m").alias("v")))).alias("x"))
        e = work.table(small.select(F.col("x.u").alias("a"), F.col("x.v").alias("b")).filter("a <> b").distinct(), "small")
        # stars stay stars: done once every vertex has one link and no centre is a leaf
        now = e.agg(F.count(F.lit(1)), F.countDistinct("a"), F.sum(F.hash("a", "b").cast("long"))).first()
        if shape == tuple(now):
            return e.select(F.col("a").alias("id"), F.col("b").alias("component")).union(e.select("b", "b").distinct())
        shape = tuple(now)
    raise RuntimeError(f"components did not settle in {max_rounds} rounds")
