"""Costs of a run: rounds, rows alive, rows exchanged, load of the fullest task, seconds."""

from __future__ import annotations

import time
import weakref
from contextlib import contextmanager
from contextvars import ContextVar
from dataclasses import dataclass, field

from pyspark.sql import DataFrame, SparkSession
from spanweave.store import stash

_open: ContextVar[Ledger | None] = ContextVar("ledger", default=None)


@dataclass
class Ledger:
    """Rows (phase, round, live_rows, exchange_rows, max_rows_per_task, seconds) of the loops run while it is open.

    live_rows: rows of all written frames that something still holds. exchange_rows: records that the round's stages wrote to shuffles. max_rows_per_task: records that its fullest task read,
    from input and shuffles. The last two are Spark's own task metrics."""

    rows: list[tuple] = field(default_factory=list)
    _held: list[tuple] = field(default_factory=list)
    _stage: int = -1

    def enter(self, phase: str, turn: int, out: DataFrame, seconds: float) -> None:
        count = out.count()
        self._held = [(r, n) for r, n in self._held if r() is not None] + [(weakref.ref(out), count)]
        moved, most, last = _stage_metrics(out.sparkSession, self._stage)
        self._stage = last
        self.rows.append((phase, turn, sum(n for _, n in self._held), moved, max(most, 0), seconds))

    @contextmanager
    def open(self):
        token = _open.set(self)
        try:
            yield self
        finally:
            _open.reset(token)

    def rounds(self, phase: str | None = None) -> int:
        return sum(1 for r in self.rows if phase is None or r[0] == phase)

    def live_rows(self, phase: str | None = None) -> int:
        return max((r[2] for r in self.rows if phase is None or r[0] == phase), default=0)

    def frame(self, spark: SparkSession) -> DataFrame:
        return spark.createDataFrame(self.rows, "phase string, round int, live_rows long, exchange_rows long, max_rows_per_task long, seconds double")


@dataclass(frozen=True)
class Budget:
    """Space knobs: N**(1+gamma) rows in all, c * N**delta rows a task."""

    gamma: float = 0.0
    delta: float = 0.5
    c: float = 16.0

    def total(self, rows: int) -> int:
        return int(self.c * max(2, rows) ** (1 + self.gamma))

    def local(self, rows: int) -> int:
        return max(16, int(self.c * max(2, rows) ** self.delta))

    def partitions(self, rows: int) -> int:
        return max(1, -(-rows // self.local(rows)))


def settle(df: DataFrame, phase: str, turn: int = 0) -> DataFrame:
    """End a round: materialise `df` and, where a ledger is open, enter it."""
    ledger = _open.get()
    if ledger is not None:
        ledger._stage = _stage_metrics(df.sparkSession, ledger._stage)[2]  # what ran between rounds is not theirs
    began = time.time()
    out = stash(df)
    if ledger is not None:
        ledger.enter(phase, turn, out, time.time() - began)
    return out


def _stage_metrics(spark: SparkSession, after: int) -> tuple[int, int, int]:
    """(records written to shuffles, records read by the fullest task, last stage) of the stages numbered above `after`, from Spark's status store."""
    context = spark.sparkContext
    jvm = context._jvm
    context._jsc.sc().listenerBus().waitUntilEmpty()
    store = context._jsc.sc().statusStore()
    tops = context._gateway.new_array(jvm.double, 1)
    tops[0] = 1.0
    moved, most, last = 0, 0, after
    stages = store.stageList(None, False, False, context._gateway.new_array(jvm.double, 0), jvm.java.util.ArrayList())
    for k in range(stages.size()):  # newest first
        stage = stages.apply(k)
        if stage.stageId() <= after:
            break
        last = max(last, stage.stageId())
        moved += stage.shuffleWriteRecords()
        summary = store.taskSummary(stage.stageId(), stage.attemptId(), tops)
        if summary.isDefined():
            found = summary.get()
            most = max(most, int(found.inputMetrics().recordsRead().apply(0) + found.shuffleReadMetrics().readRecords().apply(0)))
    return moved, most, last
