"""Graphs from ordinary tables and files."""

from __future__ import annotations

from collections.abc import Sequence

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from pathq.sources.graph import PathGraph
from pathq.store import Store


def from_parquet(spark: SparkSession, path: str, src: str = "src", label: str = "label", dst: str = "dst") -> PathGraph:
    return PathGraph.from_edges(spark.read.parquet(path), src, label, dst)


def from_table(spark: SparkSession, name: str, src: str = "src", label: str = "label", dst: str = "dst") -> PathGraph:
    return PathGraph.from_edges(spark.table(name), src, label, dst)


def from_csv(spark: SparkSession, path: str, header: bool = True, sep: str = ",") -> PathGraph:
    """Columns src, label, dst, in this order."""
    return PathGraph.from_edges(spark.read.schema("src long, label string, dst long").csv(path, header=header, sep=sep))


def from_json(spark: SparkSession, path: str) -> PathGraph:
    return PathGraph.from_edges(spark.read.schema("src long, label string, dst long").json(path))


def from_triples(spark: SparkSession, rows: Sequence[tuple[int, str, int]], vertices: Sequence[int] = ()) -> PathGraph:
    """A literal graph; for fixtures and tests."""
    e = spark.createDataFrame(list(rows), "src long, label string, dst long")
    wider = None
    if vertices:
        ends = sorted({*vertices, *(r[0] for r in rows), *(r[2] for r in rows)})
        wider = spark.createDataFrame([(v,) for v in ends], "id long")
    return PathGraph.from_edges(e, vertices=wider)


def from_sequence(df: DataFrame, partition: Sequence[str], order: Sequence[str], vertex: str | Column, label: str | Column, width: int | None = None) -> PathGraph:
    """Each row leads to the next one of its partition, under the label of the earlier row.

    With an empty ``partition`` the order is global. A window over everything would be one task, so rows are sorted by
    range; each range's rows get their successor within it, and the few range borders are linked apart. A null vertex
    keeps its place in the order: no edge leads to it or from it, and none leads past it.
    """
    col = lambda c: F.col(c) if isinstance(c, str) else c
    rows = df.select(*{*partition, *order}, col(vertex).alias("__v"), col(label).alias("__l"))
    if partition:
        w = Window.partitionBy(*partition).orderBy(*order)
        return PathGraph.from_edges(rows.withColumn("__n", F.lead("__v").over(w)), "__v", "__l", "__n")
    n = width or int(df.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    ranged = rows.repartitionByRange(n, *order).withColumn("__p", F.spark_partition_id())
    w = Window.partitionBy("__p").orderBy(*order)
    # written once: ranges that are drawn anew for every use need not be the same
    numbered = ranged.withColumn("__n", F.lead("__v").over(w)).withColumn("__r", F.row_number().over(w)).withColumn("__last", F.lead(F.lit(1)).over(w).isNull())
    placed = Store(df.sparkSession, "sequence").table(numbered, "ranges")
    inner = placed.filter("not __last").select("__v", "__l", "__n")
    # first vertex of each range, by range; one row per range
    first = placed.filter("__r = 1").select(F.col("__p").alias("__q"), F.col("__v").alias("__f"))
    last = placed.filter("__last").select("__p", "__v", "__l")
    following = Window.orderBy("__q")
    nexts = first.withColumn("__g", F.lead("__f").over(following)).select("__q", "__g")
    border = last.join(F.broadcast(nexts), F.col("__p") == F.col("__q")).select("__v", "__l", F.col("__g").alias("__n"))
    return PathGraph.from_edges(inner.unionByName(border), "__v", "__l", "__n")


KINDS = ("customer", "order", "part", "supplier", "nation", "region")


def typed(kind: str, key: str | Column) -> Column:
    """A vertex id that keeps its kind: key * number of kinds + kind."""
    return (F.col(key) if isinstance(key, str) else key).cast("long") * len(KINDS) + KINDS.index(kind)


def from_foreign_keys(parts: Sequence[tuple[DataFrame, Column, Column, str]]) -> PathGraph:
    """One edge per row of each (table, source id, target id, label)."""
    out = None
    for df, src, dst, label in parts:
        e = df.select(src.alias("src"), F.lit(label).alias("label"), dst.alias("dst"))
        out = e if out is None else out.unionByName(e)
    return PathGraph.from_edges(out)


def intern(strings: DataFrame, column: str) -> DataFrame:
    """(column, id): ids of strings by a 64-bit hash, which needs no global numbering."""
    return strings.select(column).distinct().withColumn("id", F.xxhash64(column))


def from_links(pages: DataFrame, page: str = "page_id", html: str = "html", label: str = "links") -> PathGraph:
    """page -> link target; targets are interned strings with the lowest bit set, pages have it clear."""
    target = F.explode(F.array_distinct(F.regexp_extract_all(F.col(html), F.lit('href="([^"]*)"'), F.lit(1))))
    e = pages.select((F.col(page) * 2).alias("src"), target.alias("t"))
    return PathGraph.from_edges(e.select("src", F.lit(label).alias("label"), (F.xxhash64("t").bitwiseAND(F.lit((1 << 62) - 1)) * 2 + 1).alias("dst")))


def from_knn(neighbours: DataFrame, query: str = "query_id", near: str = "vec_id", label: str = "near") -> PathGraph:
    """Edges of a table of nearest neighbours."""
    return PathGraph.from_edges(neighbours.select(F.col(query).alias("src"), F.lit(label).alias("label"), F.col(near).alias("dst")))


def from_stream(spark: SparkSession, path: str, schema: str = "src long, label string, dst long") -> DataFrame:
    """A stream of edges from parquet files that arrive in a folder."""
    return spark.readStream.schema(schema).parquet(path)


def write_bucketed(graph: PathGraph, table: str, buckets: int = 64) -> None:
    """Edges as a table bucketed by source, so that rounds join it without another shuffle."""
    graph.edges.write.mode("overwrite").bucketBy(buckets, "src").sortBy("src").saveAsTable(table)


def write_parquet(answers: DataFrame, path: str, partitions: int | None = None) -> None:
    out = answers.repartition(partitions, "src") if partitions else answers
    out.write.mode("overwrite").parquet(path)


def nearest_by_cosine(vectors: DataFrame, k: int = 3, block: int = 2048) -> DataFrame:
    """(query_id, vec_id, rank): the k vectors with the largest cosine (to six digits, then the smaller id).

    Rows are dealt into blocks by a hash of their id, and every two blocks meet in one task, which answers with its best
    k of each query: a task holds two blocks, whatever the table. The work is quadratic, as an exact answer asks; for a
    large table take neighbours from an index, as a table for ``from_knn``. Null, empty and zero vectors take no part.
    """
    live = F.exists("embedding", lambda x: x != 0) & ~F.exists("embedding", lambda x: x.isNull())
    rows = vectors.select(F.col("vec_id").cast("long").alias("vec_id"), F.col("embedding").cast("array<double>").alias("embedding")).dropna().filter(live)
    n = -(-rows.count() // block)
    if not n:
        return vectors.sparkSession.createDataFrame([], "query_id long, vec_id long, rank long")
    own, every = F.pmod(F.xxhash64("vec_id"), F.lit(n)), F.explode(F.sequence(F.lit(0).cast("long"), F.lit(n - 1).cast("long")))
    asked, held = rows.withColumn("i", own).withColumn("j", every), rows.withColumn("j", own).withColumn("i", every)
    order = Window.partitionBy("query_id").orderBy(F.desc("near"), "vec_id")
    met = asked.groupBy("i", "j").cogroup(held.groupBy("i", "j")).applyInPandas(_nearest_of(k), "query_id long, vec_id long, near double")
    return met.withColumn("rank", F.row_number().over(order).cast("long")).filter(F.col("rank") <= k).select("query_id", "vec_id", "rank")


def _nearest_of(k: int):
    import numpy as np
    import pandas as pd

    def unit(frame):
        x = np.stack(frame["embedding"].to_numpy())
        return x / np.linalg.norm(x, axis=1)[:, None]

    def run(asked: pd.DataFrame, held: pd.DataFrame) -> pd.DataFrame:
        if not len(asked) or not len(held):
            return pd.DataFrame({"query_id": pd.Series(dtype="int64"), "vec_id": pd.Series(dtype="int64"), "near": pd.Series(dtype="float64")})
        held = held.sort_values("vec_id")
        who, ids = asked["vec_id"].to_numpy(), held["vec_id"].to_numpy()
        near = np.round(unit(asked) @ unit(held).T, 6)
        near[who[:, None] == ids[None, :]] = -np.inf
        best = np.argsort(-near, axis=1, kind="stable")[:, :k]
        score = np.take_along_axis(near, best, axis=1)
        query, found, score = np.repeat(who, best.shape[1]), ids[best].ravel(), score.ravel()
        real = score > -np.inf
        return pd.DataFrame({"query_id": query[real], "vec_id": found[real], "near": score[real]})

    return run


def occurrences(docs: DataFrame, items: DataFrame, words: int = 5) -> DataFrame:
    """(doc_id, item_id) where the item's whole text occurs in the document's.

    Runs of ``words`` words inside the items meet equal runs in the documents; the texts of a match are then compared.
    Items of fewer than ``words + 2`` words are met on their longest inner word.
    """
    tokens = lambda c: F.split(c, r"\s+")
    inner = F.slice(tokens(F.col("text")), 2, words)
    short = F.size(tokens(F.col("text"))) < words + 2
    keyed = items.filter("text is not null and text <> ''").select("item_id", F.col("text").alias("passage"), F.when(short, F.lit(None)).otherwise(F.xxhash64(F.concat_ws(" ", inner))).alias("k"))
    w = tokens(F.col("text"))
    runs = docs.filter("text is not null").select("doc_id", "text", w.alias("w")).select("doc_id", "text", F.explode(F.array_distinct(F.transform("w", lambda x, i: F.xxhash64(F.concat_ws(" ", F.slice(F.col("w"), i + 1, words)))))).alias("k"))
    # items without an inner run are few; each meets all documents
    few = keyed.filter("k is null").select("item_id", "passage")
    met = runs.join(keyed.filter("k is not null"), "k").filter(F.col("text").contains(F.col("passage"))).select("doc_id", "item_id")
    if few.isEmpty():
        return met.distinct()
    return met.unionByName(docs.join(F.broadcast(few), F.col("text").contains(F.col("passage"))).select("doc_id", "item_id")).distinct()
