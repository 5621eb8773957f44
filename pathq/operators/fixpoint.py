"""Fixpoints by semi-naive rounds."""

from __future__ import annotations

from collections.abc import Callable, Sequence
from dataclasses import dataclass, field

from pyspark.sql import DataFrame, Observation
from pyspark.sql import functions as F

from pathq.store import Store, observed


@dataclass
class RoundLog:
    """What each round did: new rows, and rows that the step's join produced (edge inspections)."""

    new_rows: list[int] = field(default_factory=list)
    inspections: list[int] = field(default_factory=list)
    seeds: int = 0

    @property
    def rounds(self) -> int:
        return len(self.new_rows)

    @property
    def inspected(self) -> int:
        return sum(self.inspections)


class Meter:
    """Counts the rows that pass a point of a plan, within the action that runs anyway."""

    def __init__(self) -> None:
        self.seen: list[Observation] = []

    def watch(self, df: DataFrame) -> DataFrame:
        o = Observation()
        self.seen.append(o)
        return df.observe(o, F.count(F.lit(1)).alias("n"))

    def take(self) -> int:
        n = sum(map(observed, self.seen))
        self.seen = []
        return n


Step = Callable[[DataFrame, DataFrame, Meter], DataFrame]


class Parts:
    """A growing relation as a few tables. ``fan_in`` tables of one level become one of the next.

    So a row is written again once per level, of which there are as many as the logarithm of the number of rounds, and
    a plan over all rows stays short.
    """

    def __init__(self, store: Store, name: str, fan_in: int = 8):
        self.store, self.name, self.fan_in, self.levels = store, name, fan_in, [[]]

    def add(self, part: DataFrame) -> None:
        self.levels[0].append(part)
        for i, level in enumerate(self.levels):
            if len(level) < self.fan_in:
                break
            if i + 1 == len(self.levels):
                self.levels.append([])
            self.levels[i + 1].append(self.store.table(union_of(level), f"{self.name}-level-{i + 1}"))
            self.levels[i] = []

    def all(self) -> DataFrame:
        return union_of([p for level in reversed(self.levels) for p in level])


def iterate(seed: DataFrame, step: Step, store: Store, name: str, *, known: DataFrame | None = None, max_rounds: int = 100_000, change: tuple[int, Step] | None = None) -> tuple[DataFrame, RoundLog]:
    """Rows of ``seed`` and ``known`` and all that ``step(newest, all so far, meter)`` adds to them, until it adds none.

    The step returns rows that are not in ``all so far``; ``known`` are rows of earlier, which are not extended again. Each
    round is one action, which writes its new rows to the shared store and counts them. ``change`` (rounds, step) goes on
    with another step after so many rounds. Exceeding ``max_rounds`` raises.
    """
    log, meter, parts = RoundLog(), Meter(), Parts(store, name)
    if known is not None:
        parts.add(known)
    newest, n = store.counted(seed, f"{name}-seed")
    parts.add(newest)
    log.seeds = n
    while n:
        if log.rounds >= max_rounds:
            raise RuntimeError(f"{name}: no fixpoint after {max_rounds} rounds")
        if change is not None and log.rounds == change[0]:
            step = change[1]
        newest, n = store.counted(step(newest, parts.all(), meter), f"{name}-new")
        log.new_rows.append(n)
        log.inspections.append(meter.take())
        if n:
            parts.add(newest)
    return parts.all(), log


def union_of(parts: Sequence[DataFrame]) -> DataFrame:
    out = parts[0]
    for p in parts[1:]:
        out = out.unionByName(p)
    return out
