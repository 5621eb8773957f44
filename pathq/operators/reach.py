"""Reach lists: for every vertex up to ``cap`` of the ends it reaches through middle edges; and their split by size."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from pathq.operators import kernels
from pathq.operators.fixpoint import Meter, RoundLog, iterate
from pathq.operators.product import Canonical
from pathq.store import Store


def _full(lists: DataFrame, cap: int) -> DataFrame:
    """Vertices whose list is full: those with an entry at the last place. A filter that reaches the scan, one row per vertex."""
    return lists.filter(F.col("n") == cap).select("x")


def _added(offered: DataFrame, total: DataFrame, cap: int) -> DataFrame:
    """(x, y, n) of what lists gain from what they are offered: as far as there is room, smallest y first, so that a retried task picks the same.

    n is the place of the entry in its list. Full lists refuse before anything is shuffled. Old and new entries of the
    others meet in one shuffle by x, where old ones come first: an offer counts if it is not old and its place is within the cap.
    """
    open_ = offered.join(_full(total, cap), "x", "left_anti")
    both = open_.select("x", "y", F.lit(0).alias("old")).unionByName(total.select("x", "y", F.lit(1).alias("old")))
    each = both.repartition("x").groupBy("x", "y").agg(F.max("old").alias("old"))
    place = F.row_number().over(Window.partitionBy("x").orderBy(F.desc("old"), "y"))
    return each.withColumn("n", place).filter((F.col("old") == 0) & (F.col("n") <= cap)).select("x", "y", "n")


def capped_reach(canon: Canonical, cap: int | None, store: Store, smaller: tuple[int, DataFrame] | None = None) -> tuple[DataFrame, RoundLog]:
    """(x, y) with at most ``cap`` rows per x, and n, the place of y in x's list; all of them, without places, where cap is None.

    A round offers each new entry of a list to the vertices one middle edge before. Entries go to lists with room only;
    a list that is full stays full, so what it refuses is never needed again. A list below the cap is complete. With
    ``smaller`` (its cap, its lists) only lists that were full there are offered again what they refused. Where edges and
    lists fit a task, the rounds are made inside one.
    """
    middle = canon.middle

    def offers(entries: DataFrame, edges: DataFrame, meter: Meter) -> DataFrame:
        return meter.watch(entries.select(F.col("x").alias("via"), "y").join(edges, F.col("via") == F.col("dst")).select(F.col("src").alias("x"), "y"))

    def complete(newest: DataFrame, total: DataFrame, meter: Meter) -> DataFrame:
        return offers(newest, middle, meter).distinct().join(total, ["x", "y"], "left_anti").withColumn("n", F.lit(0))

    def capped(newest: DataFrame, total: DataFrame, meter: Meter) -> DataFrame:
        return _added(offers(newest, middle, meter), total, cap)

    told = kernels.lists_in_tasks(canon, cap, store)
    if told is not None:
        return spread(told[0], cap), told[1]
    ends = canon.ends.distinct()
    if cap is None:
        return iterate(ends.withColumn("n", F.lit(0)), complete, store, "reach")
    if smaller is None:
        # the bound reaches below the shuffle
        seed = ends.withColumn("n", F.row_number().over(Window.partitionBy("x").orderBy("y"))).filter(F.col("n") <= cap)
        return iterate(seed, capped, store, "reach")
    before, lists = smaller
    meter = Meter()
    full = _full(lists, before)
    again = offers(lists, middle.join(full.select(F.col("x").alias("src")), "src", "left_semi"), meter)
    first = store.table(_added(again.unionByName(ends.join(full, "x", "left_semi")), lists, cap), "again")
    looked = meter.take()
    found, log = iterate(first, capped, store, "reach", known=lists)
    log.inspections.insert(0, looked)
    return found, log


def spread(lists: DataFrame, cap: int | None) -> DataFrame:
    """(x, y, n) of lists as a task gives them."""
    each = lists.select(F.explode("src").alias("x"), "dst", "at").select("x", "at", F.posexplode("dst").alias("place", "y"))
    return each.select("x", "y", (F.lit(0) if cap is None else (F.col("at") + F.col("place") + 1).cast("int")).alias("n"))


def split_shared(lists: DataFrame, cap: int | None) -> tuple[DataFrame, DataFrame, dict[str, int]]:
    """What ``split`` gives, of lists as a task gives them; light lists stay in pieces (x, ys)."""
    full = F.col("size") >= cap if cap is not None else F.lit(False)
    of = F.when(F.col("at") == 0, F.size("src")).otherwise(0)  # vertices, once
    n = lists.agg(F.sum(of).alias("lists"), F.sum(F.when(full, of)).alias("heavy"), F.sum(of * F.col("size")).alias("rows")).first()
    light = lists.filter(~full).select(F.explode("src").alias("x"), F.col("dst").alias("ys"))
    heavy = lists.filter(full & (F.col("at") == 0)).select(F.explode("src").alias("x"))
    heavies = n["heavy"] or 0
    return light, heavy, {"n_light": (n["lists"] or 0) - heavies, "n_heavy": heavies, "reach_rows": n["rows"] or 0}


def array_reach(canon: Canonical, cap: int, store: Store) -> tuple[DataFrame, RoundLog]:
    """The same lists, one ARRAY row per vertex: (x, ys). For caps that fit a row.

    A vertex whose list grew sends the whole list on; arrays are united and cut, so distinct and anti join fall away.
    """
    middle, log, meter = canon.middle, RoundLog(), Meter()
    cut = lambda ys: F.slice(F.array_sort(ys), 1, cap)
    total, n = store.counted(canon.ends.groupBy("x").agg(cut(F.collect_set("y")).alias("ys")), "lists")
    newest = total
    while n:
        sent = newest.join(middle, F.col("x") == F.col("dst")).select(F.col("src").alias("x"), F.explode("ys").alias("y"))
        gathered = meter.watch(sent).groupBy("x").agg(F.collect_set("y").alias("more"))
        both = gathered.join(total.withColumnRenamed("ys", "old"), "x", "left")
        old = F.coalesce("old", F.array().cast("array<long>"))
        # a full list refuses; others take what is new, as far as there is room
        fresh = F.slice(F.array_sort(F.array_except("more", old)), F.lit(1), F.greatest(F.lit(cap) - F.size(old), F.lit(0)))
        grown = both.select("x", old.alias("old"), fresh.alias("fresh")).filter(F.size("fresh") > 0)
        newest, n = store.counted(grown.select("x", F.concat("old", "fresh").alias("ys"), "fresh"), "grown")
        log.new_rows.append(n)
        log.inspections.append(meter.take())
        if n:
            total = store.table(total.join(newest, "x", "left_anti").unionByName(newest.select("x", "ys")), "lists")
            newest = newest.select("x", F.col("fresh").alias("ys"))
    return total.select("x", F.posexplode("ys").alias("n", "y")).select("x", "y", (F.col("n") + 1).alias("n")), log


def split(reach: DataFrame, cap: int | None, store: Store) -> tuple[DataFrame, DataFrame, dict[str, int]]:
    """(light pairs (x, y), heavy vertices (x), counts). Light: list below the cap, hence complete. Places tell it in one scan."""
    pairs = reach.select("x", "y")
    if cap is None:
        n = reach.agg(F.countDistinct("x").alias("lists"), F.count(F.lit(1)).alias("rows")).first()
        return pairs, reach.select("x").limit(0), {"n_light": n["lists"], "n_heavy": 0, "reach_rows": n["rows"]}
    n = reach.agg(F.count_if(F.col("n") == 1).alias("lists"), F.count_if(F.col("n") == cap).alias("heavy"), F.count(F.lit(1)).alias("rows")).first()
    heavy = _full(reach, cap)
    return pairs.join(heavy, "x", "left_anti") if n["heavy"] else pairs, heavy, {"n_light": n["lists"] - n["heavy"], "n_heavy": n["heavy"], "reach_rows": n["rows"]}
