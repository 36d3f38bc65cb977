"""Pairwise reward model: a logistic fit of preferences on differences of features, and its accuracy."""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..functions import signals as S


@dataclass(frozen=True)
class PairwiseReward:
    """Weights of a reward that is linear in the features; ``converged`` tells whether the last step stood still."""

    weights: tuple[float, ...]
    converged: bool

    def margin(self, diff: str = "diff") -> Column:
        """Reward of the chosen response less the rejected one's."""
        return sum((F.lit(w) * F.col(diff)[i] for i, w in enumerate(self.weights)), F.lit(0.0))


def usable_differences(df: DataFrame, size: int, diff: str = "diff") -> DataFrame:
    """Rows whose differences are all there and finite."""
    return df.where((F.size(diff) == size) & F.forall(diff, lambda x: x.isNotNull() & ~F.isnan(x) & (F.abs(x) < float("inf"))))


def fit_pairwise_reward(df: DataFrame, size: int, diff: str = "diff", ridge: float = 1e-3, steps: int = 25, still: float = 1e-9) -> PairwiseReward:
    """Newton steps on the pairwise log loss of ``diff`` (array<double>: chosen less rejected), without an intercept.

    A step is one aggregate of ``size`` first and ``size * (size + 1) / 2`` second derivatives, so that one row comes
    back however many pairs there are.  ``ridge`` per pair keeps the fit finite where a feature separates all pairs.
    No rows: all weights are zero.
    """
    rows, w = usable_differences(df, size, diff), np.zeros(size)
    cells = [(i, j) for i in range(size) for j in range(i, size)]
    for _ in range(steps):
        x = [F.col(diff)[i] for i in range(size)]
        miss = 1 - S.sigmoid(PairwiseReward(tuple(w), False).margin(diff))
        scored = rows.withColumns({"_miss": miss, "_bend": miss * (1 - miss)})
        sums = [F.sum(F.col("_miss") * x[i]).alias(f"g{i}") for i in range(size)] + [F.sum(F.col("_bend") * x[i] * x[j]).alias(f"h{i}_{j}") for i, j in cells]
        got = scored.agg(F.count(F.lit(1)).alias("n"), *sums).first()
        if not got["n"]:
            break
        g = np.array([got[f"g{i}"] for i in range(size)]) - ridge * got["n"] * w
        h = ridge * got["n"] * np.eye(size)
        for i, j in cells:
            h[i, j] += got[f"h{i}_{j}"]
            h[j, i] = h[i, j]
        move = np.linalg.solve(h, g)
        w = w + move
        if np.abs(move).max() < still:
            return PairwiseReward(tuple(w), True)
    return PairwiseReward(tuple(w), False)


def reward_accuracy(df: DataFrame, margin: Column) -> DataFrame:
    """Share of pairs whose chosen response has the larger reward; ties count one half."""
    hit = F.when(margin > 0, 1.0).when(margin == 0, 0.5).when(margin < 0, 0.0)
    return df.agg(F.avg(hit).alias("accuracy"), F.count(hit).alias("n_pairs"))
