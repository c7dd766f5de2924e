"""Live rounds: one Spark job a worker, submitted together; the first answers that can be
decoded are used and the other jobs are cancelled.

One Spark stage ends only with its last task, so going on without late workers needs a
job for each.  Delays are slept in the submitting thread, as a worker's would be.
"""

from __future__ import annotations

import threading
import time
import uuid
from collections.abc import Sequence
from concurrent.futures import FIRST_COMPLETED, ThreadPoolExecutor, wait
from dataclasses import dataclass

import numpy as np
from pyspark.sql import SparkSession
from pyspark.sql import functions as F

from evenkeel.operators import gradient, messages
from evenkeel.operators.codes import Code
from evenkeel.operators.decode import Decoder


@dataclass(frozen=True)
class LiveRound:
    gradient: np.ndarray
    ms: float
    used: tuple[int, ...]
    cancelled: int


def run_round(spark: SparkSession, path: str, code: Code, loss, beta: np.ndarray, columns: Sequence[str], delays_s: Sequence[float] = (), decoder: Decoder | None = None, wait_for: int | None = None) -> LiveRound:
    """``wait_for`` answers are used as they are (for schemes that drop workers); without
    it, the first set that can be decoded."""
    sc, decoder = spark.sparkContext, decoder or Decoder(code)
    stop, tag = threading.Event(), f"evenkeel-{uuid.uuid4().hex}"

    def work(w: int) -> np.ndarray | None:
        if w < len(delays_s) and delays_s[w] and stop.wait(delays_s[w]):
            return None
        sc.addJobTag(tag)
        try:
            return messages.worker_message(spark, path, code, w, loss, beta, columns)
        except Exception:
            if stop.is_set():  # cancelled
                return None
            raise
        finally:
            sc.removeJobTag(tag)

    began, answers, a = time.perf_counter(), {}, None
    with ThreadPoolExecutor(code.n) as pool:
        running = {pool.submit(work, w): w for w in range(code.n)}
        while running and a is None:
            for f in wait(running, return_when=FIRST_COMPLETED).done:
                answers[running.pop(f)] = f.result()
                if wait_for is not None:
                    if len(answers) >= wait_for:
                        a = np.isin(np.arange(code.n), list(answers)).astype(float)
                        break
                else:
                    a = decoder.row(answers)
                    if a is not None:
                        break
        ms, left = (time.perf_counter() - began) * 1000, len(running)
        stop.set()
        sc.cancelJobsWithTag(tag)
    if a is None:
        raise RuntimeError("the answers can't be decoded")
    used = [int(w) for w in np.flatnonzero(a)]
    return LiveRound(sum(a[w] * answers[w] for w in used), ms, tuple(used), left)


def run_round_single_job(spark: SparkSession, path: str, loss, beta: np.ndarray, columns: Sequence[str]) -> LiveRound:
    """All in one job, whose slowest task sets the pace (what Spark's speculation, if the
    session has it on, can shorten only after the fact)."""
    began = time.perf_counter()
    s = spark.read.parquet(path)
    g = gradient.partial_wide(s, loss, beta, columns).agg(*[F.sum(f"g{j}") for j in range(1, len(columns) + 1)]).first()
    return LiveRound(np.array([v or 0.0 for v in g]), (time.perf_counter() - began) * 1000, (), 0)
