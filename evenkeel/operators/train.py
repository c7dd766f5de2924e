"""Rounds of gradient, delay, decoding and step."""

from __future__ import annotations

from collections.abc import Sequence
from dataclasses import dataclass, field

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from evenkeel import hashing
from evenkeel.operators import gradient, placement
from evenkeel.operators.clock import Costs
from evenkeel.operators.optim import Optimizer
from evenkeel.operators.schemes import TwoStage
from evenkeel.operators.stragglers import Stragglers


@dataclass
class FitResult:
    beta: np.ndarray
    trace: list[dict]
    betas: list[np.ndarray] = field(default_factory=list)

    def trace_df(self, spark) -> DataFrame:
        return spark.createDataFrame(pd.DataFrame(self.trace))


def _combined(long: DataFrame, weights: np.ndarray, p: int, first: int) -> tuple[np.ndarray, np.ndarray]:
    """The weighted sum of block gradients, and the plain one: added up on executors, 2 p floats
    come to the driver whatever the number of blocks."""
    w = F.element_at(F.lit([float(x) for x in weights]), F.col("block") + 1)
    return _pair(long.groupBy("idx").agg(F.sum(w * F.col("g")).alias("g"), F.sum("g").alias("exact")), p, first)


def _pair(sums: DataFrame, p: int, first: int) -> tuple[np.ndarray, np.ndarray]:
    frame = sums.toPandas()
    out = np.zeros((2, p))
    at = frame["idx"].to_numpy(dtype=int) - first
    out[0, at], out[1, at] = frame["g"].to_numpy(), frame["exact"].to_numpy()
    return out[0], out[1]


def _matrix(long: DataFrame, k: int, p: int, first: int) -> np.ndarray:
    """Block gradients as k x p on the driver: the master's own part of the work."""
    out, frame = np.zeros((k, p)), long.toPandas()
    out[frame["block"].to_numpy(dtype=int), frame["idx"].to_numpy(dtype=int) - first] = frame["g"].to_numpy()
    return out


def _counts(samples: DataFrame, k: int) -> np.ndarray:
    out = np.zeros(k)
    if "counts" in samples.columns:
        samples = samples.select(F.posexplode("counts").alias("block", "n"))
        for r in samples.groupBy("block").agg(F.sum("n").alias("n")).collect():
            out[r["block"]] = r["n"]
        return out
    for r in samples.groupBy("block").count().collect():
        out[r["block"]] = r["count"]
    return out


def fit(samples: DataFrame, key: str, scheme, loss, optimizer: Optimizer, rounds: int, stragglers: Stragglers = Stragglers(), costs: Costs = Costs(), columns: Sequence[str] = (), kernel: str | None = None, batches: int = 1, allow_unstable: bool = False, keep_betas: bool = False, places: Sequence = ()) -> FitResult:
    """Train on ``samples`` (``key``, ``y``, features).

    Each round is one scan of the persisted samples; the model (p floats) goes out with the
    plan.  Who answers when does not depend on the gradients: the scheme tells beforehand with
    which weights the blocks come into the sum, and executors add them up.  ``batches`` > 1 takes
    one part of the samples a round, in turn.  The kernel "counted" takes samples that have their
    numbers by block (``gradient.combined_counted``); it needs no key and has no batches or stages.
    """
    if optimizer.needs_exact and not scheme.exact and not allow_unstable:
        raise ValueError(f"{type(optimizer).__name__} is unstable under the inexact gradients of {scheme.name}")
    p = len(optimizer.beta)
    kernel = kernel or gradient.kernel_for(p)
    counted, first = kernel == "counted", 0 if kernel in ("sparse", "counted") else 1
    if counted and (batches > 1 or isinstance(scheme, TwoStage)):
        raise ValueError("counted samples have neither batches nor stages")
    samples, staged = gradient.complete(samples, kernel, columns), isinstance(scheme, TwoStage)
    if staged:  # plain blocks first, then coded ones: both stages in one scan
        n, k = scheme.n, scheme.n + scheme.code.inner.k
        placed = placement.assign_two_stage(samples, F.col(key), scheme.code)
        placed = placed.withColumn("block", F.col("block") + F.when(F.col("stage") == "coded", n).otherwise(0)).drop("stage")
    else:
        n = k = scheme.k
        placed = samples if counted else placement.assign_blocks(samples, F.col(key), k)
    turn = None if counted else F.pmod(hashing.md5_number(F.concat(F.lit("batch-"), F.col(key).cast("string"))), F.lit(batches))
    held = [(placed if batches == 1 else placed.where(turn == b)).persist() for b in range(batches)]
    rows = [_counts(h, k) for h in held]
    trace, betas, total = [], [], 0.0
    try:
        for t in range(rounds):
            b = t % batches
            nothing = np.broadcast_to(np.zeros(1), (k, p))
            delays = stragglers.of_round(t, scheme.n)
            if staged:
                done = scheme.round(nothing[:n], nothing[n:], rows[b][:n], rows[b][n:], delays, costs)
                weights = np.append(np.ones(n), done.blocks)
            else:
                done = scheme.round(nothing, rows[b], delays, costs)
                weights = done.blocks
            if counted:
                g, exact = _pair(gradient.combined_counted(held[b], loss, optimizer.point(), weights, places), p, first)
            else:
                g, exact = _combined(gradient.partial_gradients(held[b], loss, optimizer.point(), kernel, columns), weights, p, first)
            optimizer.step(g / max(rows[b].sum() * (done.share or 1.0), 1.0))
            total += done.round_ms
            if keep_betas:
                betas.append(optimizer.beta.copy())
            trace.append({"scheme": scheme.name, "round": t + 1, "round_ms": done.round_ms, "cum_ms": total, "used": len(done.used), "vectors": done.vectors, "control": done.control, "share": done.share, "residual": done.residual, "gradient_error": float(np.linalg.norm(g - exact) / max(np.linalg.norm(exact), 1e-300))})
    finally:
        for h in held:
            h.unpersist()
    return FitResult(optimizer.beta, trace, betas)


def tune_rate(samples: DataFrame, loss, rates: Sequence[float], rounds: int, columns: Sequence[str], make) -> dict[float, float]:
    """Mean loss after ``rounds`` for each rate, all models in one scan a round.  ``make``
    (p, rate) gives an optimiser; samples need ``block`` and ``y``."""
    models = [make(len(columns), r) for r in rates]
    held = gradient.complete(samples, "wide", columns).select("block", "y", *columns).persist()
    d = held.count()
    try:
        for _ in range(rounds):
            row = gradient.batched_gradients(held, loss, [m.point() for m in models], columns).groupBy().sum().first().asDict()
            for i, m in enumerate(models):
                m.step(np.array([row[f"sum(g{i}_{j})"] for j in range(1, len(columns) + 1)]) / d)
        values = held.agg(*[F.avg(loss.value(gradient.margin_wide(m.beta, columns), F.col("y"))).alias(f"l{i}") for i, m in enumerate(models)]).first()
    finally:
        held.unpersist()
    return dict(zip(rates, values, strict=True))
