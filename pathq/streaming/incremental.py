"""Streams of edges and events: incremental closure, windowed graphs, sessions and stepping automata.

All of it is insert-only: an edge that goes away cannot be taken back from a closure cheaply, so deletes are refused.
"""

from __future__ import annotations

from collections.abc import Iterator

import pandas as pd
from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

from pathq.operators.fixpoint import Meter, iterate
from pathq.plans.automaton import compile_path
from pathq.store import Store


class IncrementalClosure:
    """A transitive closure that grows with micro-batches of edges; any order of batches gives the closure of all edges.

    New edges are extended on both sides by what was known, and new pairs by all pairs, until nothing is new.
    """

    def __init__(self, spark: SparkSession):
        self.spark, self.store = spark, Store(spark, "incremental")
        self.pairs = self.store.table(spark.createDataFrame([], "src long, dst long"), "pairs")

    def add(self, edges: DataFrame, batch: int | None = None) -> None:
        fresh = edges.select("src", "dst").dropna().distinct().join(self.pairs, ["src", "dst"], "left_anti")
        fresh, n = self.store.counted(fresh, "fresh")
        if not n:
            return
        known = self.pairs

        def step(newest: DataFrame, total: DataFrame, meter: Meter) -> DataFrame:
            every = total.unionByName(known)
            hop = every.select(F.col("src").alias("here"), F.col("dst").alias("there"))
            ahead = newest.join(hop, F.col("dst") == F.col("here")).select("src", F.col("there").alias("dst"))
            behind = newest.join(hop, F.col("src") == F.col("there")).select(F.col("here").alias("src"), "dst")
            return meter.watch(ahead.unionByName(behind)).distinct().join(every, ["src", "dst"], "left_anti")

        grown, _ = iterate(fresh, step, self.store, "grown")
        self.pairs = self.store.table(known.unionByName(grown), "pairs")

    def follow(self, stream: DataFrame, checkpoint: str):
        """Starts a query that feeds the closure with every micro-batch that is there, then stops."""
        return stream.writeStream.foreachBatch(lambda df, i: self.add(df, i)).option("checkpointLocation", checkpoint).trigger(availableNow=True).start()


def window_edges(events: DataFrame, length: str = "1 hour", slide: str | None = None, late: str = "10 minutes") -> DataFrame:
    """(start, label, n): number of events of each type per window. Works on streams and tables."""
    timed = events.withColumn("ts", F.col("ts").cast("timestamp"))
    timed = timed.withWatermark("ts", late) if events.isStreaming else timed
    w = F.window("ts", length, slide) if slide else F.window("ts", length)
    return timed.groupBy(w.alias("w"), "event_type").agg(F.count(F.lit(1)).alias("n")).select(F.unix_seconds("w.start").alias("start"), F.col("event_type").alias("label"), "n")


def session_paths(events: DataFrame, gap: str = "30 minutes", late: str = "10 minutes") -> DataFrame:
    """Sessions of a user: start, number of events and number of purchases."""
    timed = events.withColumn("ts", F.col("ts").cast("timestamp"))
    timed = timed.withWatermark("ts", late) if events.isStreaming else timed
    grouped = timed.groupBy("user_id", F.session_window("ts", gap).alias("w"))
    return grouped.agg(F.count(F.lit(1)).alias("n_events"), F.count_if(F.col("event_type") == "purchase").alias("n_purchases")).select("user_id", F.unix_seconds("w.start").alias("start"), "n_events", "n_purchases")


def _steps(events: DataFrame, late: str) -> DataFrame:
    """Events with a time, late ones to be dropped on a stream; and what a path needs of each."""
    timed = events.withColumn("ts", F.col("ts").cast("timestamp"))
    timed = timed.withWatermark("ts", late) if events.isStreaming else timed
    return timed.withColumn("step", F.struct("ts", "event_id", "event_type"))


def _walks(expr: str):
    """A column function: (src, dst) of all runs of an array of steps, in order of time, whose types match."""
    a = compile_path(expr)
    labels = sorted({s.label for _, s, _ in a.transitions})
    moves = {label: [(q, p) for q, s, p in a.transitions if s.matches(label)] for label in labels}

    @F.pandas_udf("array<struct<src:long,dst:long>>")
    def walks(steps: pd.Series) -> pd.Series:
        out = []
        for row in steps:
            ordered = sorted(((x["ts"], x["event_id"], x["event_type"]) for x in row), key=lambda x: x[:2])
            found: list[dict[str, int]] = []
            open_: dict[tuple[int, int], None] = {}  # (start, state) of runs that still match
            for i, (_, here, label) in enumerate(ordered):
                if a.nullable:
                    found.append({"src": here, "dst": here})
                if i + 1 == len(ordered):
                    break
                for q in a.initial:
                    open_[here, q] = None
                open_ = {(s, p): None for s, state in open_ for q, p in moves.get(label, ()) if q == state}
                there = ordered[i + 1][1]
                found += [{"src": s, "dst": there} for s in dict.fromkeys(s for s, q in open_ if q in a.accepting)]
            out.append(found)
        return pd.Series(out)

    return walks


def window_paths(events: DataFrame, expr: str, length: str = "1 day", slide: str | None = None, late: str = "10 minutes") -> DataFrame:
    """(start, user_id, src, dst): answers of a path query over each window's own graph.

    In a window each event of a user leads to the user's next event in the window, under the type of the earlier. On a
    stream a window is answered anew with every batch that adds to it, and events behind the watermark are dropped.
    A task holds the events of one user in one window.
    """
    steps = _steps(events, late)
    w = F.window("ts", length, slide) if slide else F.window("ts", length)
    held = steps.groupBy(w.alias("w"), "user_id").agg(F.collect_list("step").alias("steps"))
    return held.select(F.unix_seconds("w.start").alias("start"), "user_id", _walks(expr)("steps").alias("pairs"))


def session_answers(events: DataFrame, expr: str, gap: str = "30 minutes", late: str = "10 minutes") -> DataFrame:
    """(start, user_id, pairs): the same over sessions, which end where a user rests for ``gap``."""
    held = _steps(events, late).groupBy("user_id", F.session_window("ts", gap).alias("w")).agg(F.collect_list("step").alias("steps"))
    return held.select(F.unix_seconds("w.start").alias("start"), "user_id", _walks(expr)("steps").alias("pairs"))


def spread_pairs(told: DataFrame) -> DataFrame:
    """(start, user_id, src, dst) of windows or sessions with their ``pairs``."""
    return told.select("start", "user_id", F.explode("pairs").alias("p")).select("start", "user_id", "p.src", "p.dst")


def step_automaton(events: DataFrame, expr: str, idle: str | None = None) -> DataFrame:
    """(user_id, matched): how many events of a user end a path of the user's events that matches ``expr``.

    Per user, the state holds how many open paths are in each state of the automaton. Events of a user have to arrive in
    order; within a batch they are sorted by time and id. With ``idle``, which also is how late an event may come, a user's
    state is dropped once the watermark is that far past the user's last event; a later event starts anew.
    """
    a = compile_path(expr)
    labels = sorted({s.label for _, s, _ in a.transitions})
    moves = {label: [(q, p) for q, s, p in a.transitions if s.matches(label)] for label in labels}
    initial, accepting, n = sorted(a.initial), sorted(a.accepting), a.n_states
    rest = pd.Timedelta(idle) if idle else None

    def run(key, frames: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        if state.hasTimedOut:
            state.remove()
            return
        now, matched = (list(state.get[0]), state.get[1]) if state.exists else ([0] * n, 0)
        latest = None
        for frame in frames:
            frame = frame.sort_values(["ts", "event_id"])
            for label in frame["event_type"]:
                for q in initial:
                    now[q] = 1  # a path may start at every event
                after = [0] * n
                for q, p in moves.get(label, ()):
                    after[p] = max(after[p], now[q])
                now = after
                matched += any(now[q] for q in accepting)
            if len(frame):
                latest = max(latest or frame["ts"].iloc[-1], frame["ts"].iloc[-1])
        state.update((now, matched))
        if rest is not None and latest is not None:
            due = int((latest + rest).tz_localize("UTC").timestamp() * 1000) if latest.tzinfo is None else int((latest + rest).timestamp() * 1000)
            state.setTimeoutTimestamp(max(due, state.getCurrentWatermarkMs() + 1))
        yield pd.DataFrame({"user_id": [key[0]], "matched": [matched]})

    timed = events.withColumn("ts", F.col("ts").cast("timestamp"))
    timed = timed.withWatermark("ts", idle) if idle else timed
    out = timed.groupBy("user_id")
    return out.applyInPandasWithState(run, "user_id long, matched long", "open array<int>, matched long", "update", GroupStateTimeout.EventTimeTimeout if idle else GroupStateTimeout.NoTimeout)


def replay(spark: SparkSession, d: str, table: str = "events", time: str = "ts", batches: int = 4) -> DataFrame:
    """A table as a bounded stream of ``batches`` micro-batches in order of time."""
    return sliced(spark.read.parquet(f"{d}/{table}.parquet"), F.col(time).cast("timestamp").cast("double"), batches)


def sliced(df: DataFrame, key: Column, batches: int) -> DataFrame:
    """A table as a stream of so many micro-batches by ascending ``key``: a slice is one file, and files are taken in the
    order in which they were written. For showing streams on tables at hand; a real stream comes by ``from_stream``."""
    spark, where = df.sparkSession, f"{Store(df.sparkSession, 'replay').root}"
    cuts = df.select(F.percentile_approx(key, [i / batches for i in range(1, batches)], 10_000).alias("c")).first()["c"] or []
    slot = F.coalesce(sum(((key > c).cast("int") for c in cuts), F.lit(0)), F.lit(0))
    for i in range(len(cuts) + 1):
        df.filter(slot == i).repartition(1).write.mode("append").parquet(where)
    return spark.readStream.schema(df.schema).option("maxFilesPerTrigger", 1).parquet(where)


def drain(stream: DataFrame, name: str, mode: str = "append", keys: tuple[str, ...] = ()) -> DataFrame:
    """Runs a stream to the end of what is there and returns what it says then.

    In append mode that is all it emitted; in complete mode the last emission; in update mode the last row of each key.
    """
    spark = stream.sparkSession
    store = Store(spark, name)
    out, at = f"{store.root}/out", f"{store.root}/checkpoint"
    seen: list[int] = []

    def keep(df: DataFrame, batch: int) -> None:
        # a batch that is run again overwrites what it wrote before
        df.withColumn("__batch", F.lit(batch)).write.mode("overwrite").parquet(f"{out}/{batch:09d}")
        seen.append(batch)

    query = stream.writeStream.outputMode(mode).foreachBatch(keep).option("checkpointLocation", at).trigger(availableNow=True).start()
    query.awaitTermination()
    if not seen:
        return spark.createDataFrame([], stream.schema)
    parts = [max(seen)] if mode == "complete" else sorted(set(seen))
    told = spark.read.parquet(*[f"{out}/{b:09d}" for b in parts])
    if mode == "update":
        last = Window.partitionBy(*keys).orderBy(F.desc("__batch"))
        told = told.withColumn("__k", F.row_number().over(last)).filter("__k = 1").drop("__k")
    return told.drop("__batch")
