"""Functions for plain SQL: ``register(spark)``, then e.g.
``select * from code_matrix('ring', 12, 2, 0)`` or ``select auc(score, y) from t``."""

from collections.abc import Iterator
from itertools import combinations
from math import comb

import numpy as np
import pandas as pd
from pyspark.sql import SparkSession
from pyspark.sql import functions as F

from evenkeel.functions.metrics import auc_np


def _code(kind: str, n: int, s: int, seed: int):
    from evenkeel.operators import codes

    return {"block": lambda: codes.block_code(n, s), "ring": lambda: codes.ring_code(n, s, seed), "full_copy": lambda: codes.full_copy_code(n), "uncoded": lambda: codes.identity_code(n), "ring_closed": lambda: codes.ring_code_closed(n, s)}[kind]()


class CodeMatrix:
    def eval(self, kind: str, n: int, s: int, seed: int) -> Iterator[tuple]:
        m = _code(kind, n, s, seed).matrix
        for i, j in zip(*np.nonzero(m), strict=True):
            yield int(i), int(j), float(m[i, j])


class Patterns:
    def eval(self, n: int, s: int) -> Iterator[tuple]:
        from evenkeel.operators.decode import MOST_PATTERNS

        if comb(n, s) > MOST_PATTERNS:
            raise ValueError(f"{comb(n, s)} patterns")
        for i, alive in enumerate(combinations(range(n), n - s)):
            yield i, list(alive)


def _decode_coef(kind: pd.Series, n: pd.Series, s: pd.Series, seed: pd.Series, alive: pd.Series) -> pd.Series:
    from evenkeel.operators.decode import Decoder

    made, out = {}, []
    for row in zip(kind, n, s, seed, alive, strict=True):
        if row[:4] not in made:
            made[row[:4]] = Decoder(_code(*row[:4]))
        a = made[row[:4]].row(int(w) for w in row[4])
        out.append(None if a is None else a.tolist())
    return pd.Series(out)


def _auc(score: pd.Series, y: pd.Series) -> float:
    return auc_np(score.to_numpy(dtype=float), y.to_numpy(dtype=float))


def _vec_sum(v: pd.Series) -> list[float]:
    return np.sum([np.asarray(x, dtype=float) for x in v], axis=0).tolist()


def _sigmoid(m: pd.Series) -> pd.Series:
    return 1 / (1 + np.exp(-m))


def register(spark: SparkSession) -> None:
    spark.udtf.register("code_matrix", F.udtf(CodeMatrix, returnType="worker int, block int, coef double"))
    spark.udtf.register("patterns", F.udtf(Patterns, returnType="pattern bigint, alive array<int>"))
    spark.udf.register("decode_coef", F.pandas_udf(_decode_coef, "array<double>"))
    spark.udf.register("sigmoid_margin", F.pandas_udf(_sigmoid, "double"))
    spark.udf.register("auc", F.pandas_udf(_auc, "double"))
    spark.udf.register("vec_sum", F.pandas_udf(_vec_sum, "array<double>"))
