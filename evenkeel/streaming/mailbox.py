"""A stream of worker messages, decoded round by round as soon as enough are in."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

from evenkeel.operators.codes import Code
from evenkeel.operators import decode

MESSAGE = "round int, worker int, vec array<double>, sent_at timestamp"
RESULT = "round int, used array<int>, g array<double>, messages int"


def aggregate_rounds(messages: DataFrame, code: Code, watermark: str = "10 minutes", p: int | None = None) -> DataFrame:
    """``RESULT``: one row a round, at its first decodable set.

    Repeated messages of a worker count once, later ones are ignored; the state of a round
    is its vectors until it is decoded (at most n * p floats), then a mark that goes when
    the watermark passes it.
    """

    def on_messages(key: tuple, frames: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        if state.hasTimedOut:
            state.remove()
            return
        done, workers, flat, latest = (*state.get,) if state.exists else (False, [], [], 0)
        workers, flat = list(workers), list(flat)
        batch = pd.concat(list(frames)).sort_values(["sent_at", "worker"], kind="stable")
        latest = max(latest, int(batch["sent_at"].max().timestamp() * 1000))
        if not done:
            decoder = decode.shared(code)
            width = len(batch["vec"].iloc[0])
            for w, vec in zip(batch["worker"], batch["vec"], strict=True):
                if done or int(w) in workers:
                    continue
                workers.append(int(w))
                flat.extend(float(v) for v in vec)
                # a set may do before n - s have answered, for codes made of copies
                a = decoder.row(workers)
                if a is not None:
                    g = a[workers] @ np.array(flat).reshape(len(workers), width)
                    done, n = True, len(workers)
                    yield pd.DataFrame({"round": [key[0]], "used": [[w for w in workers if a[w] != 0]], "g": [g.tolist()], "messages": [n]})
                    workers, flat = [], []
        state.update((done, workers, flat, latest))
        state.setTimeoutTimestamp(max(latest, state.getCurrentWatermarkMs() + 1) + 60_000)

    grouped = messages.withWatermark("sent_at", watermark).groupBy("round")
    return grouped.applyInPandasWithState(on_messages, RESULT, "done boolean, workers array<int>, flat array<double>, latest bigint", "append", GroupStateTimeout.EventTimeTimeout)
