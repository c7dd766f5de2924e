"""A virtual clock: when answers arrive, and when a round ends."""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np

from evenkeel.operators.stragglers import Delays


@dataclass(frozen=True)
class Costs:
    row_ms: float = 0.001
    float_ms: float = 0.0001
    latency_ms: float = 1.0
    #: With a serial master every vector takes this long to be taken in.
    receive_ms: float = 0.0


def arrivals(rows: np.ndarray, vectors: int, p: int, delays: Delays, costs: Costs) -> np.ndarray:
    """Milliseconds at which each worker's answer is there; infinite for dead workers."""
    t = rows * costs.row_ms * delays.slowdown + vectors * p * costs.float_ms + costs.latency_ms + delays.delay_ms
    return drained(np.where(delays.dead, np.inf, t), costs.receive_ms)


def drained(t: np.ndarray, receive_ms: float) -> np.ndarray:
    """Arrivals behind a master that takes in one vector at a time."""
    if not receive_ms:
        return t
    out, free = t.copy(), 0.0
    for w in np.argsort(t, kind="stable"):
        free = max(free, t[w]) + receive_ms
        out[w] = free
    return out


def order(t: np.ndarray) -> list[int]:
    """Workers that answer, first come first."""
    return [int(w) for w in np.argsort(t, kind="stable") if np.isfinite(t[w])]


def kth(t: np.ndarray, k: int) -> float:
    """Time of the k-th answer (from 1)."""
    return float(np.sort(t)[k - 1])
