"""Approximate nearest neighbours by inner product: an inverted file with product-quantised residuals.

Coarse centroids divide the vectors into lists. What remains of a vector after its centroid is cut into subspaces and
each part replaced by the nearest of 256 codewords. A query visits the lists whose centroids have the largest inner
product with it, and scores their codes with a table of inner products per subspace. It does so twice. The first pass
takes the nearest few of its lists, reranks the best of each by the original vectors in double precision, and so knows a
score that the k-th neighbour has at least. The second pass takes all its lists: every row whose rough score, plus the
most that its own quantisation error can add, reaches that score is reranked. So within the lists visited nothing is
lost to the codes, and rows that cannot be neighbours cost a few table lookups.

Equal vectors are one entry with their smallest ids, one more than a query asks for: whatever the size of a group of
copies, a query's best of them are among these. Queries are not collapsed, as each leaves out itself.

Centroids and codewords are fitted on a bounded sample (``max_train``), on the driver; every row is indexed. There are as
many lists as the root of the number of vectors, up to ``max_lists``. How many of them a query visits (``probes``) is set
by measuring on the sample, against brute force, which lists hold true neighbours; spread-out vectors need many lists,
clustered ones few. Long lists are split into blocks and the queries of a list into groups, so no task holds a whole
list; a block answers with its best exact results only.

Edge cases: vectors that are null, empty, zero or hold null or non-finite components take no part, as query or
candidate; so do rows with a null vec_id. Vectors of each length form an index of their own, however few they are. Rows
that repeat are one vector. Ties go to the smaller vec_id. Fewer candidates than asked are all returned. An empty table
gives an empty result. Extra columns are ignored.
"""

from __future__ import annotations

import math
from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from pathq.llm.common import Workspace
from pathq.llm.vectors import usable

CODEWORDS = 256


def _own(x: np.ndarray, centres: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(nearest centre, squared distance less the row's own square) of every row, in strips."""
    square = (centres**2).sum(1)[None, :]
    own, gap = np.empty(len(x), np.int64), np.empty(len(x))
    for at in range(0, len(x), 4096):
        d = square - 2 * x[at : at + 4096] @ centres.T
        own[at : at + 4096] = d.argmin(1)
        gap[at : at + 4096] = d.min(1)
    return own, gap


def kmeans(x: np.ndarray, k: int, rng: np.random.Generator, rounds: int = 10) -> np.ndarray:
    """Centroids by Lloyd's rounds from distinct starting rows; an empty cluster takes the row farthest from its centre."""
    k = min(k, len(x))
    centres = x[rng.choice(len(x), k, replace=False)].copy()
    for _ in range(rounds):
        own, gap = _own(x, centres)
        n = np.bincount(own, minlength=k)
        sums = np.stack([np.bincount(own, weights=c, minlength=k) for c in x.T], axis=1)
        full = n > 0
        centres[full] = sums[full] / n[full, None]
        if not full.all():
            far = np.argsort(-(gap + (x**2).sum(1)))[: int((~full).sum())]
            centres[~full] = x[far]
    return centres


class Index:
    """Centroids, codewords and the number of probes; at most a few megabytes, whatever the corpus."""

    def __init__(self, sample: np.ndarray, lists: int, k: int, recall: float, seed: int = 3):
        rng = np.random.default_rng(seed)
        self.dim = sample.shape[1]
        self.lists = min(lists, len(sample))
        self.centres = kmeans(sample, self.lists, rng)
        own = self.assign(sample)
        rest = sample - self.centres[own]
        self.width = 2 if self.dim % 2 == 0 else 1
        self.parts = self.dim // self.width
        some = rest[rng.choice(len(rest), min(len(rest), 20_000), replace=False)]
        self.words = [kmeans(some[:, i * self.width : (i + 1) * self.width], CODEWORDS, rng, 6) for i in range(self.parts)]
        self.probes = self._probes(sample, own, k, recall, rng)

    def assign(self, x: np.ndarray) -> np.ndarray:
        return _own(x, self.centres)[0]

    def encode(self, x: np.ndarray, own: np.ndarray) -> np.ndarray:
        rest = x - self.centres[own]
        return np.stack([_own(rest[:, i * self.width : (i + 1) * self.width], words)[0].astype(np.uint8) for i, words in enumerate(self.words)], axis=1)

    def order(self, q: np.ndarray) -> np.ndarray:
        """Lists by falling inner product of their centroids."""
        return np.argsort(-(q @ self.centres.T), axis=1, kind="stable")

    def scores(self, q: np.ndarray, own: int, codes: np.ndarray) -> np.ndarray:
        """(queries, rows) approximate inner products of the rows of one list, by tables."""
        total = np.repeat((q @ self.centres[own])[:, None], len(codes), axis=1)
        for i, words in enumerate(self.words):
            total += (q[:, i * self.width : (i + 1) * self.width] @ words.T).take(codes[:, i], axis=1)
        return total

    def errors(self, x: np.ndarray, own: int, codes: np.ndarray) -> np.ndarray:
        """Lengths of what the codes of the rows of one list leave out."""
        kept = np.concatenate([words[codes[:, i]] for i, words in enumerate(self.words)], axis=1)
        return np.sqrt(((x - self.centres[own] - kept) ** 2).sum(1))

    def _probes(self, sample: np.ndarray, own: np.ndarray, k: int, recall: float, rng: np.random.Generator) -> int:
        """The fewest lists that hold the target share of the sample queries' true neighbours in the sample."""
        picked = rng.choice(len(sample), min(400, len(sample)), replace=False)
        exact = sample[picked] @ sample.T
        exact[np.arange(len(picked)), picked] = -np.inf
        k = min(k, len(sample) - 1)
        if k < 1 or self.lists == 1:
            return self.lists
        best = np.argpartition(-exact, k - 1, axis=1)[:, :k]
        rank = np.argsort(self.order(sample[picked]), axis=1)
        needed = np.sort(np.take_along_axis(rank, own[best], axis=1).ravel()) + 1
        return int(needed[min(len(needed) - 1, math.ceil(recall * len(needed)))])


def _stack(column: pd.Series) -> np.ndarray:
    return np.stack(column.to_numpy()).astype(np.float64)


def _assigned(index: Index):
    def run(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for frame in frames:
            if not len(frame):
                continue
            x = _stack(frame["embedding"])
            own = index.assign(x)
            yield pd.DataFrame({"ids": frame["ids"], "list": own.astype(np.int32), "codes": [c.tobytes() for c in index.encode(x, own)], "embedding": frame["embedding"]})

    return run


def _probed(index: Index):
    def run(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for frame in frames:
            if not len(frame):
                continue
            order = index.order(_stack(frame["embedding"]))[:, : index.probes]
            yield pd.DataFrame({"query_id": frame["vec_id"], "embedding": frame["embedding"], "lists": list(order.astype(np.int32))})

    return run


def _answers(index: Index, k: int, all_: bool):
    """Best k of one block for its queries, reranked in double precision: of all its rows that can reach ``least``, or,
    unless ``all_``, of the k that score best by their codes."""

    def best_of(score: np.ndarray, who: np.ndarray, ids: np.ndarray) -> np.ndarray:
        """Places of the k best of every query, ties to the smaller id."""
        order = np.lexsort((ids, -score, who))
        first = np.concatenate(([0], np.flatnonzero(np.diff(who[order])) + 1)) if len(order) else np.empty(0, np.int64)
        run = np.repeat(first, np.diff(np.append(first, len(order))))
        return order[np.arange(len(order)) - run < k]

    def run(queries: pd.DataFrame, rows: pd.DataFrame) -> pd.DataFrame:
        out = [(np.empty(0, np.int64), np.empty(0, np.int64), np.empty(0))]
        if len(queries) and len(rows):
            x = _stack(rows["embedding"])
            size = rows["ids"].map(len).to_numpy()
            ids, start = np.concatenate(rows["ids"].to_numpy()).astype(np.int64), np.concatenate(([0], np.cumsum(size)[:-1]))
            codes = np.frombuffer(b"".join(rows["codes"]), np.uint8).reshape(len(rows), -1)
            own = int(rows["list"].iloc[0])
            errors = index.errors(x, own, codes) + 1e-9 * np.sqrt((x**2).sum(1))  # and what rounding may add
            strip = max(1, min(256, 4_000_000 // len(rows)))
            for at in range(0, len(queries), strip):
                part = queries.iloc[at : at + strip]
                q, who = _stack(part["embedding"]), part["query_id"].to_numpy()
                rough = index.scores(q, own, codes)
                length = np.sqrt((q**2).sum(1))
                if all_:
                    least = np.nan_to_num(part["least"].to_numpy(dtype=np.float64), nan=-np.inf)
                    i, j = np.nonzero(~(rough + length[:, None] * errors[None, :] < least[:, None]))
                else:
                    most = min(k + 1, len(rows))  # one of them may hold nothing but the query
                    j = np.argpartition(-rough, most - 1, axis=1)[:, :most].ravel()
                    i = np.repeat(np.arange(len(q)), most)
                for lo in range(0, len(i), 200_000):
                    a, b = i[lo : lo + 200_000], j[lo : lo + 200_000]
                    score = (x[b] * q[a]).sum(axis=1)  # the same for equal vectors wherever they stand, unlike a matrix product
                    if all_:
                        reach = score >= least[a]
                        a, b, score = a[reach], b[reach], score[reach]
                    n = size[b]
                    spots = np.repeat(start[b] - np.concatenate(([0], np.cumsum(n)[:-1])), n) + np.arange(n.sum()) if len(b) else b
                    asker, found, score = np.repeat(who[a], n), ids[spots], np.repeat(score, n)
                    other = asker != found
                    asker, found, score = asker[other], found[other], score[other]
                    top = best_of(score, asker, found)
                    out.append((asker[top], found[top], score[top]))
        who, found, score = (np.concatenate(c) for c in zip(*out, strict=True))
        top = best_of(score, who, found)
        return pd.DataFrame({"query_id": who[top], "vec_id": found[top], "score": score[top]})

    return run


def _collapsed(rows: DataFrame, most: int) -> DataFrame:
    """(ids, embedding, dim): distinct vectors with their ``most`` smallest ids, ascending. The bound applies before the shuffle."""
    same = [F.xxhash64("embedding").alias("h"), "embedding", "dim"]
    order = Window.partitionBy("h", "embedding", "dim").orderBy("vec_id")
    kept = rows.select("vec_id", *same).withColumn("r", F.row_number().over(order)).filter(F.col("r") <= most)
    return kept.groupBy("h", "embedding", "dim").agg(F.sort_array(F.collect_list("vec_id")).alias("ids")).select("ids", "embedding", "dim")


def _cut(counts: DataFrame, key: str, most: int) -> dict:
    return {r[key]: -(-r["count"] // most) for r in counts.collect()}


def _lookup(parts: dict, column: Column) -> Column:
    return F.element_at(F.create_map(*[F.lit(v) for kv in parts.items() for v in kv]), column)


def nearest(vectors: DataFrame, is_query: Column, k: int = 20, recall: float = 0.96, max_train: int = 131_072, max_lists: int = 8192, block: int = 4096, group: int = 2048) -> DataFrame:
    """(query_id, rank, vec_id, score): the k best found for every row that ``is_query`` selects, among all other rows."""
    spark = vectors.sparkSession
    work = Workspace(spark, "nearest")
    kind = vectors.schema["embedding"].dataType.simpleString()
    exact = vectors if kind in ("array<float>", "array<double>") else vectors.withColumn("embedding", F.col("embedding").cast("array<double>"))
    good = exact.filter(usable(F.col("embedding")) & F.col("vec_id").isNotNull())
    rows = work.table(good.select(F.col("vec_id").cast("long").alias("vec_id"), "embedding").distinct().withColumn("dim", F.size("embedding")), "rows")
    entries = work.table(_collapsed(rows, k + 1), "entries")
    found = None
    for r in sorted(entries.groupBy("dim").count().collect()):  # one row per vector length
        own, asked = entries.filter(F.col("dim") == r["dim"]), rows.filter((F.col("dim") == r["dim"]) & is_query)
        lists = int(min(max_lists, max(1, round(math.sqrt(r["count"])))))
        part = _indexed(work, own, asked, r["count"], lists, k, recall, max_train, block, group)
        found = part if found is None else found.unionByName(part)
    if found is None:
        return spark.createDataFrame([], "query_id long, rank int, vec_id long, score double")
    return work.finish(_ranked(work.table(found, "found"), k).select("query_id", "rank", "vec_id", "score"))


def _ranked(found: DataFrame, k: int) -> DataFrame:
    order = Window.partitionBy("query_id").orderBy(F.desc("score"), "vec_id")
    return found.withColumn("rank", F.row_number().over(order)).filter(F.col("rank") <= k)


def _indexed(work: Workspace, entries: DataFrame, asked: DataFrame, n: int, lists: int, k: int, recall: float, max_train: int, block: int, group: int) -> DataFrame:
    train = min(max_train, max(20_000, 16 * lists))
    first, kind = F.col("ids")[0], entries.schema["embedding"].dataType.simpleString()
    drawn = entries.filter(F.pmod(F.xxhash64(first), F.lit(1 << 20)) <= int(min(1.0, train / n) * (1 << 20))).orderBy(first).limit(train).select("embedding").toPandas()
    index = Index(_stack(drawn["embedding"]), lists, k, recall)
    filed = work.table(entries.select("ids", "embedding").mapInPandas(_assigned(index), f"ids array<long>, list int, codes binary, embedding {kind}"), "lists")
    asked = asked.select("vec_id", "embedding").mapInPandas(_probed(index), f"query_id long, embedding {kind}, lists array<int>")
    asked = work.table(asked, "asked")
    blocks = _cut(filed.groupBy("list").count(), "list", block)  # a row per list

    def met(queries: DataFrame, all_: bool) -> DataFrame:
        """Queries with their ``list`` against its blocks; groups and blocks of a list meet in a task of their own."""
        groups = _cut(queries.groupBy("list").count(), "list", group)
        both = sorted(blocks.keys() & groups.keys())
        if not both:
            return work.spark.createDataFrame([], "query_id long, vec_id long, score double")
        b, g = {x: blocks[x] for x in both}, {x: groups[x] for x in both}
        every = lambda parts, name: F.explode(F.sequence(F.lit(0), _lookup(parts, F.col("list")) - 1)).alias(name)
        one = lambda parts, who, name: F.pmod(F.xxhash64(who), _lookup(parts, F.col("list"))).cast("int").alias(name)
        key, live = ["list", "b", "g"], F.col("list").isin(both)
        right = filed.filter(live).select("ids", "codes", "embedding", "list", one(b, F.col("ids")[0], "b"), every(g, "g"))
        left = queries.filter(live).select("query_id", "embedding", "least", "list", one(g, "query_id", "g"), every(b, "b"))
        return left.groupBy(*key).cogroup(right.groupBy(*key)).applyInPandas(_answers(index, k, all_), "query_id long, vec_id long, score double")

    few = F.slice("lists", 1, max(1, min(8, index.probes // 4)))
    begun = met(asked.select("query_id", "embedding", F.lit(None).cast("double").alias("least"), F.explode(few).alias("list")), False)
    kth = work.table(_ranked(begun, k).filter(F.col("rank") == k).select(F.col("query_id").alias("id"), F.col("score").alias("least")), "kth")
    every = asked.join(kth, F.col("query_id") == F.col("id"), "left").select("query_id", "embedding", "least", F.explode("lists").alias("list"))
    return met(every, True)


def op2_nearest(spark, sf_dir: str) -> DataFrame:
    return nearest(spark.read.parquet(f"{sf_dir}/embeddings.parquet").select("vec_id", "embedding"), F.col("vec_id") % 20 == 0)
