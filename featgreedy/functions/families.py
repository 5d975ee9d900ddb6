"""Exponential families: cumulant, mean and negative log-likelihood, as Columns and for numpy."""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
from pyspark.sql import Column
from pyspark.sql import functions as F

from featgreedy.session import ship


@dataclass(frozen=True)
class Family:
    name: str

    def mean(self, g: np.ndarray) -> np.ndarray:
        if self.name == "gaussian":
            return g
        return 1 / (1 + np.exp(-np.clip(g, -700, 700))) if self.name == "logit" else np.exp(np.clip(g, -700, 50))

    def cumulant(self, g: np.ndarray) -> np.ndarray:
        if self.name == "gaussian":
            return g * g / 2
        return np.logaddexp(0, g) if self.name == "logit" else np.exp(np.clip(g, -700, 50))

    def variance(self, g: np.ndarray) -> np.ndarray:
        if self.name == "gaussian":
            return np.ones_like(g)
        m = self.mean(g)
        return m * (1 - m) if self.name == "logit" else m

    def loss(self, y: np.ndarray, g: np.ndarray) -> np.ndarray:
        """Negative log-likelihood up to terms in ``y`` alone."""
        return self.cumulant(g) - y * g

    def mean_column(self, g: Column) -> Column:
        if self.name == "gaussian":
            return g
        return 1 / (1 + F.exp(-g)) if self.name == "logit" else F.exp(g)

    def loss_column(self, y: Column, g: Column) -> Column:
        if self.name == "gaussian":
            return g * g / 2 - y * g
        top = F.log1p(F.exp(-F.abs(g))) + F.greatest(g, F.lit(0.0)) if self.name == "logit" else F.exp(g)
        return top - y * g


GAUSSIAN, LOGIT, POISSON = Family("gaussian"), Family("logit"), Family("poisson")
ship(__name__)
