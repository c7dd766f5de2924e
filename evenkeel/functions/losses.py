"""Losses as Spark columns and, alike, as numpy; regularisers belong to the optimiser."""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
from pyspark.sql import Column
from pyspark.sql import functions as F


@dataclass(frozen=True)
class Logistic:
    """log(1 + exp(m)) - y m for y in {0, 1}."""

    name = "logistic"
    curvature = 0.25

    def slope(self, margin: Column, y: Column) -> Column:
        return 1 / (1 + F.exp(-margin)) - y

    def value(self, margin: Column, y: Column) -> Column:
        # max(m, 0) + log(1 + exp(-|m|)) does not overflow
        return F.greatest(margin, F.lit(0.0)) + F.log1p(F.exp(-F.abs(margin))) - y * margin

    def slope_np(self, margin: np.ndarray, y: np.ndarray) -> np.ndarray:
        return 1 / (1 + np.exp(-np.clip(margin, -700, 700))) - y

    def value_np(self, margin: np.ndarray, y: np.ndarray) -> np.ndarray:
        return np.logaddexp(0, margin) - y * margin


@dataclass(frozen=True)
class Squared:
    """Half the squared difference."""

    name = "squared"
    curvature = 1.0

    def slope(self, margin: Column, y: Column) -> Column:
        return margin - y

    def value(self, margin: Column, y: Column) -> Column:
        return (margin - y) * (margin - y) / 2

    def slope_np(self, margin: np.ndarray, y: np.ndarray) -> np.ndarray:
        return margin - y

    def value_np(self, margin: np.ndarray, y: np.ndarray) -> np.ndarray:
        return (margin - y) ** 2 / 2


@dataclass(frozen=True)
class L2:
    weight: float

    def gradient(self, beta: np.ndarray) -> np.ndarray:
        return self.weight * beta

    def value(self, beta: np.ndarray) -> float:
        return self.weight / 2 * float(beta @ beta)


@dataclass(frozen=True)
class L1:
    weight: float

    def value(self, beta: np.ndarray) -> float:
        return self.weight * float(np.abs(beta).sum())

    def proximal(self, beta: np.ndarray, rate: float) -> np.ndarray:
        return np.sign(beta) * np.maximum(np.abs(beta) - rate * self.weight, 0)
