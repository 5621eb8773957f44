"""Evaluation of star-free expressions: words as path joins, by capped lists per position; unions of words; layered automata."""

from __future__ import annotations

from collections.abc import Sequence

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from pathq.operators.capped_split import FIRST_CAP, evaluate_capped_split
from pathq.operators.fixpoint import Meter, union_of
from pathq.operators.product import to_canonical
from pathq.plans.automaton import compile_path, resolve
from pathq.plans.classify import Word, expand_words
from pathq.plans.expr import Expr
from pathq.sources.graph import PathGraph
from pathq.store import Store


def relations(graph: PathGraph, word: Word) -> list[DataFrame]:
    """One relation (p, q) per symbol of the word."""
    out = []
    for s in word:
        e = graph.edges if s.but is not None and not s.but else graph.edges.filter(~F.col("label").isin(sorted(s.but))) if s.but is not None else graph.edges.filter(F.col("label") == s.label)
        a, b = ("dst", "src") if s.backward else ("src", "dst")
        out.append(e.select(F.col(a).alias("p"), F.col(b).alias("q")).distinct())
    return out


def plain_join(parts: Sequence[DataFrame]) -> DataFrame:
    """All relations joined, repeats removed at the end: the baseline, whose intermediate results may be large."""
    out = parts[0].select(F.col("p").alias("src"), F.col("q").alias("at"))
    for r in parts[1:]:
        out = out.join(r, F.col("at") == F.col("p")).select("src", F.col("q").alias("at"))
    return out.select("src", F.col("at").alias("dst")).distinct()


def eager_join(parts: Sequence[DataFrame]) -> DataFrame:
    """All relations joined from the left, with inner vertices projected away and repeats removed after every join."""
    out = parts[0].select(F.col("p").alias("src"), F.col("q").alias("dst")).distinct()
    for r in parts[1:]:
        out = out.join(r, F.col("dst") == F.col("p")).select("src", F.col("q").alias("dst")).distinct()
    return out


def path_join(parts: Sequence[DataFrame], store: Store, cap: int | str = "adaptive") -> tuple[DataFrame, dict[str, int]]:
    """Distinct (src, dst) over a chain of relations, by capped lists.

    From the last position to the second, every vertex gets a list of at most ``cap`` ends, made from the lists of the next
    position; a list below the cap is complete. First-position edges into light vertices answer from lists; those
    into heavy vertices walk forward, position by position, pruned to vertices that have a list. ``adaptive`` raises the cap
    fourfold until no more sources are heavy than the cap. Inspections are the rows that the joins with edges make.
    """
    meter = Meter()
    parts = [store.table(r, f"position-{i}") for i, r in enumerate(parts)]
    told = {"inspect_reach": 0, "inspect_trail": 0, "heavy_sources": 0, "cap": 0}
    if len(parts) == 1:
        return parts[0].select(F.col("p").alias("src"), F.col("q").alias("dst")).distinct(), told
    size = FIRST_CAP if cap == "adaptive" else cap
    while True:
        lists: list[DataFrame] = []
        following = parts[-1].select(F.col("p").alias("x"), F.col("q").alias("y"))
        first = True
        for i in range(len(parts) - 1, 0, -1):
            if not first:
                following = meter.watch(parts[i].join(following, F.col("q") == F.col("x")).select(F.col("p").alias("x"), "y"))
            first = False
            w = Window.partitionBy("x").orderBy("y")
            following = store.table(following.distinct().withColumn("rank", F.row_number().over(w)).filter(F.col("rank") <= size).select("x", "y"), f"lists-{i}")
            told["inspect_reach"] += meter.take()
            lists.append(following)
        lists.reverse()  # lists[i] belongs to position i + 1
        sizes = store.table(lists[0].groupBy("x").agg(F.count(F.lit(1)).alias("n")), "sizes")
        heavy = sizes.filter(F.col("n") >= size).select("x")
        into = parts[0].join(heavy, F.col("q") == F.col("x"), "left_semi")
        sources = into.select("p").distinct().count()
        if cap != "adaptive" or sources <= size:
            break
        size *= 4
    told |= {"heavy_sources": sources, "cap": size}
    light = lists[0].join(heavy, "x", "left_anti")
    out = parts[0].join(light, F.col("q") == F.col("x")).select(F.col("p").alias("src"), F.col("y").alias("dst"))
    if sources:
        at = into.select(F.col("p").alias("src"), F.col("q").alias("dst"))
        for i, r in enumerate(parts[1:], 1):
            step = r if i + 1 == len(parts) else r.join(lists[i].select("x").distinct(), F.col("q") == F.col("x"), "left_semi")
            at = store.table(meter.watch(at.join(step, F.col("dst") == F.col("p")).select("src", F.col("q").alias("dst"))).distinct(), f"trail-{i}")
            told["inspect_trail"] += meter.take()
        out = out.unionByName(at)
    return out.distinct(), told


def evaluate_star_free(graph: PathGraph, expr: Expr | str, store: Store, limit: int = 64, cap: int | str = "adaptive", plain: bool = False) -> tuple[DataFrame, dict[str, int]]:
    """Union over the words of the expression; each word by ``path_join`` (or, with ``plain``, by joins alone)."""
    words, empty = expand_words(expr, limit)
    told: dict[str, int] = {"words": len(words), "inspect_reach": 0, "inspect_trail": 0}
    found: list[DataFrame] = []
    for w in words:
        if plain:
            found.append(eager_join(relations(graph, w)))
            continue
        df, own = path_join(relations(graph, w), store, cap)
        found.append(df)
        for k in ("inspect_reach", "inspect_trail"):
            told[k] += own[k]
    if empty:
        found.append(graph.vertices.select(F.col("id").alias("src"), F.col("id").alias("dst")))
    if not found:
        return graph.spark.createDataFrame([], "src long, dst long"), told
    return union_of(found).distinct(), told


def evaluate_layered(graph: PathGraph, expr: Expr | str, store: Store, cap: int | str = "adaptive") -> tuple[DataFrame, dict[str, int]]:
    """The acyclic automaton as it is, without listing words: for expressions with too many of them."""
    automaton = resolve(compile_path(expr), graph.labels())
    return evaluate_capped_split(to_canonical(graph, automaton), store, cap)
