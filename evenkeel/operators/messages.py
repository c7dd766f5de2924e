"""Messages of workers from block gradients, and their combination."""

from __future__ import annotations

from collections.abc import Mapping, Sequence

import numpy as np
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from evenkeel.operators import gradient
from evenkeel.operators.codes import Code


def encode(partials: DataFrame, code_df: DataFrame) -> DataFrame:
    """worker, idx, v: each worker's weighted sum of its blocks' gradients.

    Blocks are summed before they are copied to workers: n (s + 1) p products, not
    (s + 1) scans."""
    both = partials.join(F.broadcast(code_df), "block")
    return both.groupBy("worker", "idx").agg(F.sum(F.col("coef") * F.col("g")).alias("v"))


def encode_wide(partials: DataFrame, code_df: DataFrame, p: int) -> DataFrame:
    """worker, v1..vp from g1..gp."""
    both = partials.join(F.broadcast(code_df), "block")
    return both.groupBy("worker").agg(*[F.sum(F.col("coef") * F.col(f"g{j}")).alias(f"v{j}") for j in range(1, p + 1)])


def combine(messages: DataFrame, weights: DataFrame) -> DataFrame:
    """pattern, idx, g from messages and decoding rows (pattern, worker, coef).

    Messages are n x p and travel on their idx; decoding rows are broadcast only while
    they are few."""
    both = messages.join(weights, "worker")
    return both.groupBy("pattern", "idx").agg(F.sum(F.col("coef") * F.col("v")).alias("g"))


def combine_wide(messages: DataFrame, weights: DataFrame, p: int) -> DataFrame:
    both = messages.join(weights, "worker")
    return both.groupBy("pattern").agg(*[F.sum(F.col("coef") * F.col(f"v{j}")).alias(f"g{j}") for j in range(1, p + 1)])


def weights_table(spark: SparkSession, rows: Mapping[int, np.ndarray]) -> DataFrame:
    """pattern, worker, coef of decoding rows on the driver."""
    flat = [(int(p), int(w), float(a[w])) for p, a in rows.items() for w in np.flatnonzero(a)]
    return spark.createDataFrame(flat, "pattern bigint, worker int, coef double")


def worker_message(spark: SparkSession, path: str, code: Code, worker: int, loss, beta: np.ndarray, columns: Sequence[str]) -> np.ndarray:
    """One worker's vector from block-partitioned Parquet: reads only its blocks, weighs
    every sample's gradient by its block and sums them in one go."""
    held = code.support(worker)
    samples = spark.read.parquet(path).where(F.col("block").isin([int(b) for b in held]))
    coef = F.lit(0.0)
    for b in held:
        coef = F.when(F.col("block") == int(b), float(code.matrix[worker, b])).otherwise(coef)
    slope = loss.slope(gradient.margin_wide(beta, columns), F.col("y")) * coef
    row = samples.select(slope.alias("w"), *columns).agg(*[F.sum(F.col("w") * F.col(c)) for c in columns]).first()
    return np.array([v or 0.0 for v in row])
