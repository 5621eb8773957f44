"""The output-sensitive evaluator: capped reach lists, light and heavy vertices, and a walk from heavy starts only."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from pathq.operators import kernels
from pathq.operators.product import Canonical, default_cap, stored
from pathq.operators.reach import array_reach, capped_reach, split, split_shared, spread
from pathq.operators.search import arrivals, walk, with_identity
from pathq.store import Store

Cap = int | str | None
#: Where the adaptive cap starts: lists of this size cost little more than none, and a smaller start only adds rounds.
FIRST_CAP = 16


def light_answers(starts: DataFrame, light: DataFrame) -> DataFrame:
    """Answers whose first middle vertex has a complete list; lists are pairs (x, y) or come in pieces (x, ys)."""
    if "ys" in light.columns:
        return starts.join(light, "x").select(F.col("s").alias("src"), F.explode("ys").alias("dst"))
    return arrivals(starts, light)


def heavy_sources(starts: DataFrame, heavy: DataFrame) -> DataFrame:
    return starts.join(heavy, "x", "left_semi").select("s").distinct()


def heavy_seed(starts: DataFrame, heavy: DataFrame) -> DataFrame:
    return starts.join(heavy, "x", "left_semi").select("s", "x")


def heavy_walk(starts: DataFrame, middle: DataFrame, heavy: DataFrame, store: Store, listed: DataFrame | None = None, light: DataFrame | None = None) -> tuple[DataFrame, DataFrame | None, object]:
    """(pairs walked, answers by shortcut or None, log).

    The walk begins at heavy vertices and then follows every middle edge. ``listed`` (x) prunes it to vertices with a list: the
    others have no answers. With ``light`` it stops where a complete list answers for the rest of the way.
    """
    if listed is not None:
        middle = middle.join(listed.select(F.col("x").alias("dst")).distinct(), "dst", "left_semi").select("src", "dst")
    if light is None:
        walked, log = walk(heavy_seed(starts, heavy), middle, store, "trail")
        return walked, None, log
    into = middle.join(heavy.select(F.col("x").alias("dst")), "dst", "left_semi").select("src", "dst")
    walked, log = walk(heavy_seed(starts, heavy), into, store, "trail")
    rest = walked.join(middle, F.col("x") == F.col("src")).select("s", F.col("dst").alias("x")).distinct()
    return walked, arrivals(rest, light), log


def evaluate_capped_split(canon: Canonical, store: Store, cap: Cap = "sqrt", prune: bool = False, shortcut: bool = False, layout: str = "rows", most_rows: int | None = None, only: str | None = None) -> tuple[DataFrame | None, dict[str, int]]:
    """Distinct (src, dst) and counters.

    Where edges and lists fit a task, lists are made in one and vertices share those that they have in common, and the searches
    from heavy starts are dealt among tasks. With ``only="answers"`` answers are then found when they are read, and not counted
    (``read_later`` of the store tells it); with "counters" they are counted, as ``out``, and none are given.

    ``cap``: "sqrt" for the integer root of the edge count plus one, "adaptive" for 16, 64, 256, ... until heavy sources are no
    more than the cap, a number, or None for complete lists. The answer does not depend on it. ``most_rows`` lowers the
    cap so that lists of all vertices with a middle edge into them hold no more rows than that.
    """
    canon, n_edges = stored(canon, store)
    starts, middle, ends = canon.starts, canon.middle, canon.ends
    told: dict[str, int] = {"canonical_edges": n_edges, "inspect_reach": 0, "rounds": 0}
    size = default_cap(n_edges) if cap == "sqrt" else FIRST_CAP if cap == "adaptive" else cap
    if most_rows is not None and size is not None:
        size = max(1, min(size, most_rows // max(1, n_edges)))
    smaller = None
    while True:
        plain = layout == "rows" or size is None
        shared = kernels.lists_in_tasks(canon, size, store) if plain and not prune and not shortcut else None
        if shared is not None:
            (lists, log), reach = shared, spread(shared[0], size)
            light, heavy, counts = split_shared(lists, size)
        else:
            reach, log = capped_reach(canon, size, store, smaller) if plain else array_reach(canon, size, store)
            light, heavy, counts = split(reach, size, store)
        told["inspect_reach"] += log.inspected
        told["rounds"] += log.rounds
        sources = heavy_sources(starts, heavy).count() if counts["n_heavy"] else 0
        if cap != "adaptive" or sources <= size:
            break
        smaller = (size, reach) if layout == "rows" else None
        size *= 4
    told |= counts | {"cap": size or 0, "heavy_sources": sources, "inspect_trail": 0, "trail_rows": 0}
    if shared is not None and (only is not None or sources) and starts.groupBy("s").count().filter("count > 1").isEmpty():
        # a start is light or heavy, so that answers come once
        searched = kernels.searches_in_tasks(heavy_seed(starts, heavy), canon, store, only) if sources else (None, {})
        if searched is not None:
            return _once(canon, store, light_answers(starts, light), *searched, told, only)
    found, n_light = store.counted(light_answers(starts, light).distinct(), "light-answers")
    told |= {"light_rows": n_light, "heavy_rows": 0}
    if sources:
        walked, short, log = heavy_walk(starts, middle, heavy, store, reach.select("x") if prune else None, light if shortcut else None)
        answers = arrivals(walked, ends)
        more, n_heavy = store.counted((answers if short is None else answers.unionByName(short)).distinct(), "heavy-answers")
        told |= {"inspect_trail": log.inspected, "trail_rows": sum(log.new_rows) + log.seeds, "heavy_rows": n_heavy}
        told["rounds"] += log.rounds
        found = found.unionByName(more)
    found = with_identity(found, canon)
    return (None, told | {"out": found.count()}) if only == "counters" else (found, told)


def _once(canon: Canonical, store: Store, found: DataFrame, more: DataFrame | None, searched: dict[str, int], told: dict[str, int], only: str | None) -> tuple[DataFrame | None, dict[str, int]]:
    """Light answers and those of searches in tasks, where none comes twice, and counters."""
    if only == "answers":
        store.read_later = True
    elif only == "counters":
        told |= {"light_rows": found.count()}
    else:
        found, told["light_rows"] = store.counted(found, "light-answers")
    heavy = {"inspect_trail": "inspect_search", "trail_rows": "trail_rows", "heavy_rows": "out"}
    told |= {name: searched.get(c, 0) for name, c in heavy.items()}
    told["rounds"] += searched.get("rounds", 0)
    if only == "counters" and canon.identity is None:
        return None, told | {"out": told["light_rows"] + told["heavy_rows"]}
    found = found if more is None else found.unionByName(more)
    return (found if canon.identity is None else with_identity(found, canon)), told
