"""The data model: an edge-labelled directed graph as two DataFrames."""

from __future__ import annotations

from collections.abc import Iterable
from dataclasses import dataclass

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F


@dataclass(frozen=True)
class PathGraph:
    """``edges`` (src, label, dst) without repeats or nulls, ``vertices`` (id).

    Vertices matter to queries that match the empty path only; by default they are the endpoints of all edges,
    taken before any label is dropped.
    """

    edges: DataFrame
    wider: DataFrame | None = None
    base: DataFrame | None = None  # edges before labels were dropped

    @classmethod
    def from_edges(cls, df: DataFrame, src: str | Column = "src", label: str | Column = "label", dst: str | Column = "dst", vertices: DataFrame | None = None, distinct: bool = True) -> PathGraph:
        """Rows with a null endpoint or label are dropped; repeats are one edge."""
        col = lambda c: F.col(c) if isinstance(c, str) else c
        e = df.select(col(src).cast("long").alias("src"), col(label).cast("string").alias("label"), col(dst).cast("long").alias("dst")).dropna()
        return cls(e.distinct() if distinct else e, vertices)

    @property
    def spark(self):
        return self.edges.sparkSession

    @property
    def vertices(self) -> DataFrame:
        if self.wider is not None:
            return self.wider.select(F.col("id").cast("long").alias("id")).dropna().distinct()
        e = self.base if self.base is not None else self.edges
        return e.select(F.explode(F.array("src", "dst")).alias("id")).distinct()

    def restrict_labels(self, labels: Iterable[str] | None) -> PathGraph:
        """Only edges that the query can use; the filter reaches the scan. The vertices stay what they were."""
        if labels is None:
            return self
        return PathGraph(self.edges.filter(F.col("label").isin(sorted(labels))), self.wider, self.base if self.base is not None else self.edges)

    def reversed(self) -> PathGraph:
        turn = lambda e: e.select(F.col("dst").alias("src"), "label", F.col("src").alias("dst"))
        return PathGraph(turn(self.edges), self.wider, turn(self.base) if self.base is not None else None)

    def labels(self) -> list[str]:
        """The alphabet; its size does not depend on the data's."""
        return sorted(r[0] for r in self.edges.select("label").distinct().collect())

    def label_histogram(self) -> DataFrame:
        return self.edges.groupBy("label").agg(F.count(F.lit(1)).alias("n_edges"))

    def degree_histogram(self) -> DataFrame:
        """Out-degree -> number of vertices with at least one outgoing edge."""
        return self.edges.groupBy("src").agg(F.count(F.lit(1)).alias("degree")).groupBy("degree").agg(F.count(F.lit(1)).alias("n_vertices"))

    def id_range(self) -> tuple[int, int]:
        """The smallest and the largest id that an edge holds; (0, 0) without edges."""
        r = self.edges.agg(F.min(F.least("src", "dst")).alias("lo"), F.max(F.greatest("src", "dst")).alias("hi")).first()
        return (0, 0) if r["lo"] is None else (r["lo"], r["hi"])

    def sizes(self) -> dict[str, int]:
        e = self.edges.agg(F.count(F.lit(1)).alias("e"), F.countDistinct("label").alias("l")).first()
        return {"n_vertices": self.vertices.count(), "n_edges": e["e"], "n_labels": e["l"]}
