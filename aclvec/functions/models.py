"""Analytical models of search cost and recall, as Column builders and as plain numbers.

Cost of a search is the log of the partition's size times a line in the search
depth. Recall grows in proportion to depth x selectivity / k and then saturates
along a sigmoid. Every cost model can take the place of another.
"""

from __future__ import annotations

import math
from dataclasses import dataclass

import numpy as np
from pyspark.sql import Column
from pyspark.sql import functions as F


def _c(x) -> Column:
    return x if isinstance(x, Column) else F.col(x) if isinstance(x, str) else F.lit(float(x))


def log_size(size) -> Column:
    return F.ln(F.greatest(_c(size).cast("double"), F.lit(2.0)))


@dataclass(frozen=True)
class GraphCost:
    """ln(size) * (a * ef + b)."""

    a: float = 1.0
    b: float = 20.0

    @classmethod
    def asymptotic(cls) -> GraphCost:
        """No fitted constants."""
        return cls(1.0, 0.0)

    def cost(self, size, ef) -> Column:
        return log_size(size) * (_c(ef) * self.a + self.b)

    def value(self, size, ef):
        return np.log(np.maximum(size, 2.0)) * (self.a * ef + self.b)


@dataclass(frozen=True)
class FilterGraphCost:
    """Search in a graph that walks permitted nodes only: (d + width) * ln(s * n) + ln(1 / s)."""

    d: float = 64.0
    width: float = 12.0

    def cost(self, size, selectivity) -> Column:
        s = F.greatest(_c(selectivity), F.lit(1e-9))
        return F.ln(F.greatest(s * _c(size), F.lit(2.0))) * (self.d + self.width) + F.ln(1 / s)

    def value(self, size, selectivity):
        s = np.maximum(selectivity, 1e-9)
        return (self.d + self.width) * np.log(np.maximum(s * size, 2.0)) + np.log(1 / s)


@dataclass(frozen=True)
class ScanCost:
    """Every vector is compared: size * d."""

    d: float = 64.0

    def cost(self, size, ef=0) -> Column:
        return _c(size) * self.d

    def value(self, size, ef=0):
        return np.asarray(size) * self.d


@dataclass(frozen=True)
class IvfCost:
    """Centroids, then the probed lists: nlist + nprobe * size / nlist."""

    nlist: int = 10
    nprobe: int = 2

    def cost(self, size, ef=0) -> Column:
        return _c(size) * self.nprobe / self.nlist + self.nlist

    def value(self, size, ef=0):
        return np.asarray(size) * self.nprobe / self.nlist + self.nlist


@dataclass(frozen=True)
class ShardedGraphCost:
    """A partition of several graphs of at most `shard` nodes: linear in the number of shards."""

    a: float = 1.0
    b: float = 20.0
    shard: int = 1_000_000

    def cost(self, size, ef) -> Column:
        return F.ceil(_c(size) / self.shard) * F.ln(F.greatest(F.least(_c(size).cast("double"), F.lit(float(self.shard))), F.lit(2.0))) * (_c(ef) * self.a + self.b)

    def value(self, size, ef):
        return np.ceil(np.asarray(size) / self.shard) * np.log(np.clip(size, 2.0, self.shard)) * (self.a * ef + self.b)


@dataclass(frozen=True)
class RecallModel:
    """With x = ef * s / k: x up to gamma, then a sigmoid of steepness beta, shifted so that it continues at gamma; within 0 and 1."""

    beta: float = 4.0
    gamma: float = 0.5

    def recall(self, ef, s, k) -> Column:
        x = _c(ef) * _c(s) / _c(k)
        late = 1 / (1 + F.exp((x - self.gamma) * -self.beta)) + (self.gamma - 0.5)
        return F.least(F.greatest(F.when(x <= self.gamma, x).otherwise(late), F.lit(0.0)), F.lit(1.0))

    def value(self, ef, s, k):
        x = np.asarray(ef, float) * s / k
        return np.clip(np.where(x <= self.gamma, x, 1 / (1 + np.exp(-self.beta * (x - self.gamma))) + self.gamma - 0.5), 0, 1)

    def reach(self, target: float) -> float:
        """The least x at which recall reaches the target."""
        if target <= self.gamma:
            return target
        p = target - self.gamma + 0.5
        if p >= 1:
            raise ValueError(f"recall {target} is out of reach: the model ends at {self.gamma + 0.5}")
        return self.gamma + math.log(p / (1 - p)) / self.beta

    def ef_for(self, target: float, s, k):
        """The least depth that reaches the target; Columns or numbers."""
        x = self.reach(target)
        if isinstance(s, (Column, str)) or isinstance(k, (Column, str)):
            return _c(k) * x / _c(s)
        return k * x / s


def fit_recall(ef, s, k, recall) -> tuple[RecallModel, float]:
    """Beta and gamma of least squares: a grid, then Gauss-Newton steps. Also the root mean square error."""
    ef, s, k, recall = (np.asarray(v, float) for v in (ef, s, k, recall))
    error = lambda b, g: RecallModel(b, g).value(ef, s, k) - recall
    best = min(((float((error(b, g) ** 2).sum()), b, g) for b in np.linspace(0.5, 12, 40) for g in np.linspace(0.05, 0.95, 40)), key=lambda t: t[0])
    loss, at = best[0], np.array(best[1:])
    for _ in range(20):
        r, h = error(*at), 1e-5
        jac = np.stack([(error(at[0] + h, at[1]) - r) / h, (error(at[0], at[1] + h) - r) / h], axis=1)
        step = np.linalg.lstsq(jac, -r, rcond=None)[0]
        for scale in (1.0, 0.5, 0.1, 0.01):
            new = np.clip(at + scale * step, [0.05, 0.01], [100, 0.99])
            if (value := float((error(*new) ** 2).sum())) < loss - 1e-15:
                loss, at = value, new
                break
        else:
            break
    return RecallModel(float(at[0]), float(at[1])), math.sqrt(loss / max(1, len(recall)))
