"""Objectives of linear models, as columns and over numpy blocks."""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
from pyspark.sql import Column
from pyspark.sql import functions as F


@dataclass(frozen=True)
class LogisticLoss:
    """log(1 + exp(-margin)) for labels -1 and 1; margin = label times score."""

    l2: float = 0.0
    convex = True

    def value(self, margin: Column) -> Column:
        return F.greatest(-margin, F.lit(0.0)) + F.log1p(F.exp(-F.abs(margin)))

    def slope(self, margin: Column) -> Column:
        """The derivative by the margin."""
        return F.lit(-1.0) / (F.lit(1.0) + F.exp(margin))

    def np_value(self, margin: np.ndarray) -> np.ndarray:
        return np.maximum(-margin, 0) + np.log1p(np.exp(-np.abs(margin)))

    def np_slope(self, margin: np.ndarray) -> np.ndarray:
        return -1.0 / (1.0 + np.exp(np.minimum(margin, 700)))


@dataclass(frozen=True)
class HingeLoss:
    """max(0, 1 - margin), or its square."""

    l2: float = 0.0
    squared: bool = False
    convex = True

    def value(self, margin: Column) -> Column:
        gap = F.greatest(F.lit(0.0), F.lit(1.0) - margin)
        return gap * gap if self.squared else gap

    def slope(self, margin: Column) -> Column:
        gap = F.greatest(F.lit(0.0), F.lit(1.0) - margin)
        return F.lit(-2.0) * gap if self.squared else F.when(margin < 1.0, F.lit(-1.0)).otherwise(F.lit(0.0))

    def np_value(self, margin: np.ndarray) -> np.ndarray:
        gap = np.maximum(0.0, 1.0 - margin)
        return gap * gap if self.squared else gap

    def np_slope(self, margin: np.ndarray) -> np.ndarray:
        return -2.0 * np.maximum(0.0, 1.0 - margin) if self.squared else np.where(margin < 1.0, -1.0, 0.0)
