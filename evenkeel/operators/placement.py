"""Samples into blocks."""

from __future__ import annotations

import heapq
from collections.abc import Mapping

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from evenkeel import hashing
from evenkeel.operators.codes import TwoStageCode


def assign_blocks(samples: DataFrame, key: Column, blocks: int) -> DataFrame:
    """A ``block`` by hash of the key; no shuffle."""
    return samples.withColumn("block", hashing.block_of(key.cast("string"), blocks))


def assign_two_stage(samples: DataFrame, key: Column, code: TwoStageCode) -> DataFrame:
    """``stage`` (plain or coded) and ``block``: in the plain stage the worker that holds
    the sample, in the coded stage one of the inner code's blocks.  The split is by share,
    so any alpha will do."""
    h = hashing.md5_number(key.cast("string"))
    plain = h < int(code.plain_share * (1 << 32))
    other = hashing.md5_number(F.concat(F.lit("block-"), key.cast("string")))
    return samples.withColumn("stage", F.when(plain, "plain").otherwise("coded")).withColumn(
        "block", F.pmod(other, F.when(plain, code.n).otherwise(code.inner.k)).cast("int"))


def write_blocks(samples: DataFrame, path: str, blocks: int) -> None:
    """Block-partitioned Parquet: a worker's scan is pruned to its directories.  A block
    may be many files; the shuffle spreads each over several tasks."""
    spread = F.pmod(F.xxhash64(*samples.columns), F.lit(4))
    samples.repartition(F.col("block"), spread).write.mode("overwrite").partitionBy("block").parquet(path)


def pack_by_cost(costs: Mapping[int, float], blocks: int) -> dict[int, int]:
    """Sub-blocks to blocks of about equal cost: the costliest first, each to the block
    with the least so far."""
    heap = [(0.0, b) for b in range(blocks)]
    out = {}
    for part, cost in sorted(costs.items(), key=lambda x: (-x[1], x[0])):
        total, b = heapq.heappop(heap)
        out[part] = b
        heapq.heappush(heap, (total + cost, b))
    return out
