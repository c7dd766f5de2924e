"""Queries of the coded-gradient engine and their DuckDB oracles.

The groups live in modules of their own; each gives ``QUERIES`` and ``ORACLES``.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from evenkeel.functions.losses import Logistic
from evenkeel.operators import optim, schemes, train
from evenkeel.operators.stragglers import Stragglers
from evenkeel.plans import code_queries, cost_queries, gradient_queries, operator_queries, run_queries, stream_queries, training_queries
from evenkeel.sources import datasets

_GROUPS = (code_queries, gradient_queries, training_queries, cost_queries, operator_queries, stream_queries, run_queries)


def flagship(spark: SparkSession, sf_dir: str) -> DataFrame:
    samples = datasets.lineitem_planted(spark, sf_dir).where("not holdout")
    scheme = schemes.build("ring", 12, 1)
    done = train.fit(samples, "key", scheme, Logistic(), optim.NAG(5, 4.0), 5, Stragglers("additive", s=1, delay_ms=500.0), columns=datasets.SCALED)
    return done.trace_df(spark)


def queries() -> dict:
    return {name: q for g in _GROUPS for name, q in g.QUERIES.items()}


def oracle_sql() -> dict[str, str]:
    return {name: q for g in _GROUPS for name, q in g.ORACLES.items()}
