"""Who is late in which round, and by how much; alike in Python and in SQL."""

from __future__ import annotations

from dataclasses import dataclass, field

import numpy as np
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import Window as W

from evenkeel import hashing


@dataclass(frozen=True)
class Delays:
    """Of one round: milliseconds added, factor on the computing time, and dead workers."""

    delay_ms: np.ndarray
    slowdown: np.ndarray
    dead: np.ndarray


@dataclass(frozen=True)
class Stragglers:
    """kind none, additive (``s`` others each round), slowdown (the same by a factor), sticky
    (the same ones all along), dead, or trace (milliseconds by round and worker)."""

    kind: str = "none"
    s: int = 0
    delay_ms: float = 0.0
    factor: float = 1.0
    fixed: tuple[int, ...] = ()
    seed: str = "delay"
    trace: np.ndarray | None = field(default=None, compare=False)

    def late(self, round_: int, n: int) -> list[int]:
        if self.kind in ("sticky", "dead"):
            return [w for w in self.fixed if w < n]
        if self.kind in ("additive", "slowdown"):
            order = sorted(range(n), key=lambda w: (hashing.md5_number_py(f"{self.seed}-{round_}-{w}"), w))
            return order[: self.s]
        return []

    def of_round(self, round_: int, n: int) -> Delays:
        delay, slow, dead, late = np.zeros(n), np.ones(n), np.zeros(n, dtype=bool), self.late(round_, n)
        if self.kind == "trace":
            delay = self.trace[round_ % len(self.trace), :n].astype(float)
        elif self.kind == "slowdown":
            slow[late] = self.factor
        elif self.kind == "dead":
            dead[late] = True
        else:
            delay[late], slow[late] = self.delay_ms, self.factor
        return Delays(delay, slow, dead)


def late_table(spark: SparkSession, rounds: int, n: int, s: int, seed: str = "delay") -> DataFrame:
    """round, worker, late for the additive kind."""
    cells = spark.range(rounds).select(F.col("id").cast("int").alias("round")).crossJoin(spark.range(n).select(F.col("id").cast("int").alias("worker")))
    h = hashing.md5_number(F.concat_ws("-", F.lit(seed), "round", "worker"))
    place = F.row_number().over(W.partitionBy("round").orderBy("h", "worker"))
    return cells.withColumn("h", h).withColumn("late", place <= s).select("round", "worker", "late")


def trace_from_events(events: DataFrame, n: int, most_rounds: int | None = None) -> DataFrame:
    """round, worker, delay_ms: ``value`` of the events of a worker's users in order of time.
    One row an event; with ``most_rounds``, of the first rounds only."""
    worker = F.pmod("user_id", F.lit(n)).cast("int")
    place = F.row_number().over(W.partitionBy("worker").orderBy("ts", "event_id"))
    return events.select(worker.alias("worker"), "ts", "event_id", "value").withColumn("round", place).where(F.lit(True) if most_rounds is None else F.col("round") <= most_rounds).select("round", "worker", F.col("value").alias("delay_ms"))
