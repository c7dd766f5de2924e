"""Measures of cost and accuracy."""

from __future__ import annotations

import numpy as np
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import Window as W


def auc(scored: DataFrame, score: str = "score", label: str = "y", by: tuple[str, ...] = ()) -> DataFrame:
    """Exact area under the curve, ties at a half: ``by``, auc, positives, negatives.  A group
    of one class has a null auc; rows without score or label are left out.

    Scores are counted first; the running sum is over distinct scores of a group."""
    counts = scored.where(F.col(score).isNotNull() & F.col(label).isNotNull()).groupBy(*by, score).agg(F.sum(label).alias("pos"), F.sum(1 - F.col(label)).alias("neg"))
    below = F.sum("neg").over(W.partitionBy(*by).orderBy(score)) - F.col("neg")
    won = counts.withColumn("won", F.col("pos") * (below + F.col("neg") / 2))
    out = won.groupBy(*by).agg(F.sum("won").alias("w"), F.sum("pos").alias("positives"), F.sum("neg").alias("negatives"))
    return out.select(*by, F.try_divide("w", F.col("positives") * F.col("negatives")).alias("auc"), "positives", "negatives")


def auc_np(score: np.ndarray, y: np.ndarray) -> float:
    order = np.argsort(score, kind="stable")
    s, y = score[order], y[order].astype(float)
    start = np.concatenate(([True], s[1:] != s[:-1]))
    group = np.cumsum(start) - 1
    pos, neg = np.bincount(group, weights=y), np.bincount(group, weights=1 - y)
    below = np.cumsum(neg) - neg
    both = pos.sum() * neg.sum()
    return float((pos * (below + neg / 2)).sum() / both) if both else float("nan")


def mean_loss(samples: DataFrame, loss, margin: Column) -> DataFrame:
    """loss, accuracy, rows."""
    right = ((margin > 0) == (F.col("y") > 0.5)).cast("double")
    return samples.agg(F.avg(loss.value(margin, F.col("y"))).alias("loss"), F.avg(right).alias("accuracy"), F.count("*").alias("rows"))


def gradient_error(pairs: DataFrame, got: str, exact: str, by: tuple[str, ...] = ()) -> DataFrame:
    """Relative distance of two long vectors; null where the exact one is 0."""
    d = F.col(got) - F.col(exact)
    return pairs.groupBy(*by).agg(F.try_divide(F.sqrt(F.sum(d * d)), F.sqrt(F.sum(F.col(exact) * F.col(exact)))).alias("error"))


def representation(samples: DataFrame, used: Column, bucket: str) -> DataFrame:
    """bucket, rows, share of them that is used."""
    return samples.groupBy(bucket).agg(F.count("*").alias("rows"), F.avg(used.cast("double")).alias("share"))


def communication(trace: DataFrame) -> DataFrame:
    """worker, mean and standard deviation of its delays, and mean over the median mean.

    One row a worker reaches the window."""
    by = trace.groupBy("worker").agg(F.avg("delay_ms").alias("mean_ms"), F.stddev_samp("delay_ms").alias("std_ms"), F.count("*").alias("rounds"))
    typical = by.agg(F.expr("percentile(mean_ms, 0.5)").alias("typical"))
    return by.crossJoin(F.broadcast(typical)).withColumn("ratio", F.try_divide("mean_ms", F.col("typical"))).drop("typical")


def load(scheme: str, n: int, s: int, alpha: float = 1.0) -> dict[str, float]:
    """Share of the data on a worker, vectors a worker sends, coded share, plain share."""
    if scheme in ("uncoded", "drop_s"):
        return {"load": 1 / n, "vectors": 1, "coded_share": 0.0}
    if scheme == "full_copy":
        return {"load": 1.0, "vectors": 1, "coded_share": 1.0}
    if scheme.startswith("two_stage"):
        return {"load": (s + 1) / n * alpha / (s + alpha), "vectors": 2, "coded_share": (alpha - 1) / (s + alpha)}
    return {"load": (s + 1) / n, "vectors": 1, "coded_share": 1.0}


def bytes_on_wire(vectors: int, p: int, control: int = 0) -> int:
    return 8 * p * vectors + 16 * control
