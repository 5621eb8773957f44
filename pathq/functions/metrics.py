"""One row of counters per evaluation."""

from __future__ import annotations

import time
from dataclasses import asdict, dataclass, fields

from pyspark.sql import DataFrame, SparkSession

from pathq.functions import bounds


@dataclass(frozen=True)
class RunReport:
    """Sizes, counters and bounds of one evaluation; see the README for each column."""

    query: str = ""
    method: str = ""
    n_vertices: int = 0
    n_edges: int = 0
    n_labels: int = 0
    automaton_size: int = 0
    product_vertices: int = 0
    product_edges: int = 0
    canonical_edges: int = 0
    out: int = 0
    out_states: int = 0
    cap: int = 0
    reach_rows: int = 0
    n_light: int = 0
    n_heavy: int = 0
    n_absent: int = 0
    heavy_sources: int = 0
    light_rows: int = 0
    trail_rows: int = 0
    heavy_rows: int = 0
    inspect_reach: int = 0
    inspect_trail: int = 0
    inspect_search: int = 0
    inspect_closure: int = 0
    rounds: int = 0
    seconds: float = 0.0
    shuffle_bytes: int = 0
    peak_rows: int = 0

    @property
    def inspected(self) -> int:
        return self.inspect_reach + self.inspect_trail

    def gain_over(self, search: RunReport) -> float | None:
        """Inspections of a search of the same query per inspection of this run; None where this run made none."""
        return search.inspect_search / self.inspected if self.inspected else None

    @property
    def bound_search(self) -> float:
        return bounds.bound_search(self.n_vertices, self.n_edges)

    @property
    def bound_combined(self) -> float:
        """The search bound with its factor for the automaton."""
        return self.bound_search * max(1, self.automaton_size)

    @property
    def bound_split(self) -> float:
        return bounds.bound_split(self.n_vertices, self.n_edges, self.out)

    def invariants(self) -> dict[str, bool]:
        """What has to hold of a capped run whatever the data; product vertices stand for vertices."""
        v = self.n_light + self.n_heavy
        return {
            "lists_within_cap": self.cap == 0 or self.reach_rows <= v * self.cap,
            "reach_within_bound": self.cap == 0 or self.inspect_reach <= self.canonical_edges * self.cap,
            "trail_within_bound": self.inspect_trail <= self.heavy_sources * self.canonical_edges,
            # every heavy source has as many answers as the cap, at least
            "few_heavy_sources": self.heavy_sources * self.cap <= self.out,
        }

    def to_df(self, spark: SparkSession) -> DataFrame:
        kinds = {"int": "long", "str": "string", "float": "double"}
        return spark.createDataFrame([tuple(asdict(self).values())], ", ".join(f"{f.name} {kinds[f.type]}" for f in fields(self)))


class Probe:
    """What Spark's own counters say of the stages that run between its making and ``read``: time, shuffled bytes, and the
    most rows that one task read from a shuffle. Other work of the session in that time counts too."""

    def __init__(self, spark: SparkSession):
        self.context, self.began = spark.sparkContext, time.perf_counter()
        self.last = max((s.stageId() for s in self._newest(-1)[:1]), default=-1)

    def _newest(self, after: int) -> list:
        """Stages with a larger id, newest first."""
        none = self.context._gateway.new_array(self.context._jvm.double, 0)
        found = self.context._jsc.sc().statusStore().stageList(None, False, False, none, None)
        n = found.size()
        turn = range(n) if n < 2 or found.apply(0).stageId() > found.apply(n - 1).stageId() else range(n - 1, -1, -1)
        out = []
        for i in turn:
            s = found.apply(i)
            if s.stageId() <= after:
                break
            out.append(s)
            if after < 0:
                break
        return out

    def read(self) -> dict[str, float | int]:
        seconds, shuffled, peak = time.perf_counter() - self.began, 0, 0
        store, top = self.context._jsc.sc().statusStore(), self.context._gateway.new_array(self.context._jvm.double, 1)
        top[0] = 1.0
        for s in self._newest(max(self.last, 0)):
            shuffled += s.shuffleWriteBytes()
            if s.shuffleReadRecords() > peak:  # its largest task may have read more than the largest so far
                told = store.taskSummary(s.stageId(), s.attemptId(), top)
                if told.isDefined():
                    peak = max(peak, int(told.get().shuffleReadMetrics().readRecords().apply(0)))
        return {"seconds": round(seconds, 3), "shuffle_bytes": shuffled, "peak_rows": peak}
