"""Near duplicates of vectors by p-stable hashing of their directions.

Normalised vectors are projected on random Gaussian directions; projections are shifted, divided by a width and
floored, and several of them make the bucket of a table. At distance ``c`` one quantised projection agrees
with probability ``p(c)``; the number of projections follows the number of vectors, so that buckets of unrelated
vectors keep a constant expected size, and the number of tables follows the target recall for pairs at the
threshold. All pairs of a bucket are checked by exact cosine in double precision, in blocks.

A pair that shares several tables counts in the first of them only, which each task finds out by itself: codes are
computed in integer arithmetic, so every task gets the same ones. Pairs are never written out. A block yields
counts per vector and a spanning forest of its links. Buckets above ``tile`` vectors are dealt into tiles, and
pairs of tiles are compared in tasks of their own; equal vectors are one vector with a multiplicity.

Edge cases: vectors that are null, empty, zero or hold null or non-finite components link with nothing and are
components of their own. Vectors of different length never link. Rows that repeat a vec_id with the same vector are
copies of each other. A null vec_id gets a null component and kept = false, and no links. An empty table gives an
empty result. Extra columns are ignored.
"""

from __future__ import annotations

import math
from collections.abc import Iterator
from statistics import NormalDist

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from pathq.llm.common import Workspace
from pathq.llm.graph import components, forest

GRID = 1 << 14  # directions are quantised to this many steps a unit for hashing, never for comparing


def usable(vector: Column) -> Column:
    """True for vectors with a direction: not null, no null or non-finite component, not all zero."""
    bad = lambda x: x.isNull() | F.isnan(x) | (F.abs(x) == float("inf"))
    return F.coalesce(vector.isNotNull() & ~F.exists(vector, bad) & F.exists(vector, lambda x: x != 0), F.lit(False))


def agree(c: float, width: float) -> float:
    """Probability that one quantised projection agrees for two points at distance c."""
    r = width / c
    return 1 - 2 * NormalDist().cdf(-r) - 2 / (math.sqrt(2 * math.pi) * r) * (1 - math.exp(-r * r / 2))


class Hashing:
    """Tables of quantised projections for directions of one length. Arithmetic is exact, in integers below 2**53."""

    def __init__(self, n: int, threshold: float = 0.9, recall: float = 0.999, width: float = 2.0, bucket: float = 200.0, seed: int = 5):
        near, far = agree(math.sqrt(2 - 2 * threshold), width), agree(math.sqrt(2.0), width)
        self.width, self.seed = width, seed
        self.m = max(4, math.ceil(math.log(max(n / bucket, 1.0)) / -math.log(far)))
        self.tables = max(1, math.ceil(math.log(1 - recall) / math.log(1 - near**self.m)))
        self._made: dict[int, tuple[np.ndarray, np.ndarray, np.ndarray]] = {}

    def codes(self, unit: np.ndarray) -> np.ndarray:
        """(rows, tables) hashes of the buckets of unit vectors."""
        dim = unit.shape[1]
        if dim not in self._made:
            rng = np.random.default_rng([self.seed, dim])
            k = self.m * self.tables
            steps = self.width * GRID * 1024
            self._made[dim] = (np.rint(rng.standard_normal((dim, k)) * 1024), np.floor(rng.uniform(0, steps, k)), rng.integers(1, 2**62, k, dtype=np.uint64) * np.uint64(2) + np.uint64(1))
        directions, shifts, odd = self._made[dim]
        cells = np.floor_divide(np.rint(unit * GRID) @ directions + shifts, self.width * GRID * 1024).astype(np.int64).astype(np.uint64)
        mixed = ((cells + np.uint64(0x5851F42D)) * odd).reshape(len(unit), self.tables, self.m).sum(axis=2, dtype=np.uint64)
        mixed ^= mixed >> np.uint64(29)
        return (mixed * np.uint64(0xBF58476D1CE4E5B9)).view(np.int64)


def matrix(column) -> np.ndarray:
    """Rows of an Arrow list column of one length, in double precision."""
    flat = column.flatten().to_numpy(zero_copy_only=False)
    return flat.astype(np.float64).reshape(len(column), -1)


def _bucketed(hashing: Hashing):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            if not batch.num_rows:
                continue
            dims = np.asarray(batch["dim"])
            for dim in np.unique(dims):
                rows = batch.take(pa.array(np.flatnonzero(dims == dim)))
                for at in range(0, rows.num_rows, 2048):
                    part = rows.slice(at, 2048)
                    x = matrix(part["embedding"])
                    codes = hashing.codes(x / np.linalg.norm(x, axis=1)[:, None])
                    n, t = codes.shape
                    yield pa.RecordBatch.from_arrays([pa.array(np.tile(np.arange(t, dtype=np.int32), n)), pa.array(codes.ravel()), pa.array(np.repeat(np.asarray(part["rep"]), t)), pa.array(np.repeat(np.full(n, dim, np.int32), t))], names=["t", "code", "rep", "dim"])

    return run


def _compare(hashing: Hashing, threshold: float):
    """Rows (t, code, i, j, side, rep, times, embedding), sorted by block -> per-vector counts and forest links."""

    def pairs(t: int, a, b) -> Iterator[tuple[np.ndarray, np.ndarray]]:
        ids_a, x_a, ids_b, x_b, same = a[0], a[1], b[0], b[1], a is b
        norm_a, norm_b = np.linalg.norm(x_a, axis=1), np.linalg.norm(x_b, axis=1)
        codes_a = codes_b = None
        for at in range(0, len(ids_a), 512):
            cos = (x_a[at : at + 512] @ x_b.T) / (norm_a[at : at + 512, None] * norm_b[None, :])
            p, q = np.nonzero(cos >= threshold)
            p += at
            if same:
                upper = p < q
                p, q = p[upper], q[upper]
            if not len(p):
                continue
            if codes_a is None:
                codes_a = hashing.codes(x_a / norm_a[:, None])
                codes_b = codes_a if same else hashing.codes(x_b / norm_b[:, None])
            for lo in range(0, len(p), 65536):
                pp, qq = p[lo : lo + 65536], q[lo : lo + 65536]
                first = np.argmax(codes_a[pp] == codes_b[qq], axis=1) == t
                if first.any():
                    yield pp[first], qq[first]

    def block(key, rows: list) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
        t, _, i, j = key
        side = np.concatenate([r[0] for r in rows])
        ids, times = np.concatenate([r[1] for r in rows]), np.concatenate([r[2] for r in rows])
        x = np.concatenate([r[3] for r in rows])
        left = (ids[side == 0], x[side == 0], times[side == 0])
        right = left if i == j else (ids[side == 1], x[side == 1], times[side == 1])
        n_left, n_right, fa, fb = np.zeros(len(left[0]), np.int64), np.zeros(len(right[0]), np.int64), [], []
        for p, q in pairs(t, left, right):
            n_left += np.bincount(p, weights=right[2][q], minlength=len(n_left)).astype(np.int64)
            n_right += np.bincount(q, weights=left[2][p], minlength=len(n_right)).astype(np.int64)
            f = forest(left[0][p], right[0][q])
            fa.append(f[0])
            fb.append(f[1])
        if not fa:
            none = np.empty(0, np.int64)
            return none, none, none, none
        links = forest(np.concatenate(fa), np.concatenate(fb))
        who, n = np.concatenate((left[0], right[0])), np.concatenate((n_left, n_right))
        return who[n > 0], n[n > 0], links[0], links[1]

    def out(found) -> pa.RecordBatch:
        who, n, a, b = found
        count = len(who) + len(a)
        kind = np.concatenate((np.zeros(len(who), np.int32), np.ones(len(a), np.int32)))
        return pa.RecordBatch.from_arrays([pa.array(kind), pa.array(np.concatenate((who, a))[:count]), pa.array(np.concatenate((n, b))[:count])], names=["kind", "rep", "value"])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        key, held = None, []
        for batch in batches:
            if not batch.num_rows:
                continue
            t, code, i, j = (np.asarray(batch[c]) for c in ("t", "code", "i", "j"))
            turn = np.flatnonzero((np.diff(t) != 0) | (np.diff(code) != 0) | (np.diff(i) != 0) | (np.diff(j) != 0)) + 1
            edges = [0, *turn.tolist(), batch.num_rows]
            side, rep, times = (np.asarray(batch[c]) for c in ("side", "rep", "times"))
            for lo, hi in zip(edges[:-1], edges[1:], strict=True):
                k = (int(t[lo]), int(code[lo]), int(i[lo]), int(j[lo]))
                if k != key:
                    if len(held) > 1 or held and len(held[0][0]) > 1:
                        found = block(key, held)
                        if len(found[0]):
                            yield out(found)
                    key, held = k, []
                held.append((side[lo:hi], rep[lo:hi], times[lo:hi], matrix(batch["embedding"].slice(lo, hi - lo))))
        if held and (len(held) > 1 or len(held[0][0]) > 1):
            found = block(key, held)
            if len(found[0]):
                yield out(found)

    return run


def near_vectors(vectors: DataFrame, threshold: float = 0.9, recall: float = 0.999, tile: int = 1024) -> DataFrame:
    """Per row of ``vectors`` (vec_id, embedding): vec_id, n_links, component_id, kept."""
    work = Workspace(vectors.sparkSession, "near-vectors")
    rows = vectors.select(F.col("vec_id").cast("long").alias("vec_id"), "embedding")
    good = rows.filter(usable(F.col("embedding")) & F.col("vec_id").isNotNull())
    # equal vectors are one, named by their smallest id
    print_ = F.xxhash64("embedding")
    single = work.table(good.groupBy("embedding").agg(F.min("vec_id").alias("rep"), F.count(F.lit(1)).alias("times")).withColumn("dim", F.size("embedding")).withColumn("h", print_), "distinct")
    n = single.count()
    hashing = Hashing(n, threshold, recall)
    codes = work.table(single.select("rep", "dim", "embedding").mapInArrow(_bucketed(hashing), "t int, code long, rep long, dim int"), "codes")
    sizes = work.table(codes.groupBy("t", "code", "dim").agg(F.count(F.lit(1)).alias("size")).filter("size > 1").withColumn("tiles", F.ceil(F.col("size") / tile).cast("int")), "sizes")
    shared = codes.join(sizes, ["t", "code", "dim"]).withColumn("own", F.pmod(F.xxhash64("rep"), F.col("tiles")).cast("int"))
    # a vector of tile o meets the tiles before it as the right side and those after it as the left side
    meet = F.explode(F.sequence(F.lit(0), F.col("tiles") - 1))
    dealt = shared.withColumn("other", meet).select("t", "code", "dim", "rep", F.least("own", "other").alias("i"), F.greatest("own", "other").alias("j"), (F.col("own") > F.col("other")).cast("int").alias("side"))
    full = dealt.join(single.select("rep", "times", "embedding"), "rep")
    mixed = F.xxhash64("code", "dim").alias("code")
    blocks = full.select("t", mixed, "i", "j", "side", "rep", "times", "embedding").repartition("t", "code", "i", "j").sortWithinPartitions("t", "code", "i", "j")
    found = work.table(blocks.mapInArrow(_compare(hashing, threshold), "kind int, rep long, value long"), "found")
    counts = found.filter("kind = 0").groupBy("rep").agg(F.sum("value").alias("links"))
    near = components(found.filter("kind = 1").select(F.col("rep").alias("a"), F.col("value").alias("b")), work)
    told = work.table(single.select("rep", "times", "h", "dim").join(counts, "rep", "left").join(near.withColumnRenamed("id", "rep"), "rep", "left"), "told")
    classes = told.select(F.col("h").alias("__h"), F.col("dim").alias("__dim"), (F.coalesce("links", F.lit(0)) + F.col("times") - 1).alias("n_links"), F.coalesce("component", "rep").alias("component"))
    live = usable(F.col("embedding")) & F.col("vec_id").isNotNull()
    keyed = rows.select("vec_id", F.when(live, print_).alias("h"), F.when(live, F.size("embedding")).alias("dim"))
    joined = keyed.join(classes, (F.col("h") == F.col("__h")) & (F.col("dim") == F.col("__dim")), "left")
    component = F.coalesce("component", "vec_id")
    return work.finish(joined.select("vec_id", F.coalesce("n_links", F.lit(0)).cast("long").alias("n_links"), component.alias("component_id"), F.coalesce(F.col("vec_id") == component, F.lit(False)).alias("kept")))


def op9_near_vectors(spark, sf_dir: str) -> DataFrame:
    return near_vectors(spark.read.parquet(f"{sf_dir}/embeddings.parquet").select("vec_id", "embedding"))
