"""Python data sources: ``mixture_logistic`` (batch) and ``message_mailbox`` (stream)."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
from pyspark.sql import SparkSession
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition, SimpleDataSourceStreamReader


class _Mixture(DataSourceReader):
    def __init__(self, options: dict):
        self.d, self.p, self.seed = int(options.get("d", 1000)), int(options.get("p", 10)), int(options.get("seed", 1))
        self.parts = int(options.get("partitions", 4))

    def partitions(self) -> list[InputPartition]:
        return [InputPartition(i) for i in range(self.parts)]

    def read(self, partition: InputPartition) -> Iterator[tuple]:
        beta = np.random.default_rng(self.seed).standard_normal(self.p) / np.sqrt(self.p)
        block = 1024  # rows are drawn by fixed blocks: the same whatever the partitions are
        for b in range(partition.value, -(-self.d // block), self.parts):
            rng = np.random.default_rng([self.seed, b])
            n = min(block, self.d - b * block)
            side = rng.choice([-1.0, 1.0], block)
            x = rng.standard_normal((block, self.p)) + side[:, None] * 1.5 / self.p * beta
            y = (rng.random(block) < 1 / (1 + np.exp(2 * x @ beta))).astype(float)
            for i in range(n):
                yield b * block + i, x[i].tolist(), float(y[i])


class MixtureSource(DataSource):
    @classmethod
    def name(cls) -> str:
        return "mixture_logistic"

    def schema(self) -> str:
        return "key bigint, x array<double>, y double"

    def reader(self, schema) -> _Mixture:
        return _Mixture(self.options)


class _Mailbox(SimpleDataSourceStreamReader):
    """Made-up messages of rounds: worker w answers round t unless it is the late one, whose
    answer comes with the next round."""

    def __init__(self, options: dict):
        self.n, self.rounds, self.p = int(options.get("n", 6)), int(options.get("rounds", 4)), int(options.get("p", 3))

    def initialOffset(self) -> dict:
        return {"round": 0}

    def read(self, start: dict) -> tuple[Iterator[tuple], dict]:
        t = start["round"]
        if t > self.rounds:
            return iter(()), start
        return self._rows(t), {"round": t + 1}

    def readBetweenOffsets(self, start: dict, end: dict) -> Iterator[tuple]:
        return (row for t in range(start["round"], end["round"]) for row in self._rows(t))

    def _rows(self, t: int) -> Iterator[tuple]:
        late = t % self.n
        rows = [(t, w, [float(w + t)] * self.p) for w in range(self.n) if w != late] if t < self.rounds else []
        if t:
            rows.append((t - 1, (t - 1) % self.n, [float((t - 1) % self.n + t - 1)] * self.p))
        return iter(rows)


class MailboxSource(DataSource):
    @classmethod
    def name(cls) -> str:
        return "message_mailbox"

    def schema(self) -> str:
        return "round int, worker int, vec array<double>"

    def simpleStreamReader(self, schema) -> _Mailbox:
        return _Mailbox(self.options)


def register(spark: SparkSession) -> None:
    spark.dataSource.register(MixtureSource)
    spark.dataSource.register(MailboxSource)
