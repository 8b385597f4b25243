"""Group softmax and the training objective."""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F


def group_prob(scored: DataFrame, gamma: float, score: str = "cosine") -> DataFrame:
    """Adds ``prob``: softmax of gamma * score over the group, the maximum taken off."""
    w = Window.partitionBy("group_id")
    s = F.lit(gamma) * F.col(score)
    e = F.exp(s - F.max(s).over(w))
    return scored.withColumn("prob", e / F.sum(e).over(w))


def objective(scored: DataFrame, gamma: float, score: str = "cosine") -> DataFrame:
    """One row: minus the summed log probability of the positives."""
    return group_prob(scored, gamma, score).where("is_pos").agg(F.sum(-F.log("prob")).alias("objective"))


def cosine_grad(q: np.ndarray, k: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Row-wise cosine and its gradients by both sides."""
    nq, nk = (np.linalg.norm(x, axis=-1, keepdims=True) for x in (q, k))
    nq, nk = np.maximum(nq, 1e-12), np.maximum(nk, 1e-12)
    c = (q * k).sum(-1, keepdims=True) / (nq * nk)
    return c[..., 0], k / (nq * nk) - c * q / nq**2, q / (nq * nk) - c * k / nk**2


def group_grad(cos: np.ndarray, gamma: float) -> tuple[float, np.ndarray]:
    """Summed loss of groups (rows; column 0 is the positive) and its gradient by cosine."""
    s = gamma * cos
    s = s - s.max(1, keepdims=True)
    p = np.exp(s)
    p /= p.sum(1, keepdims=True)
    g = gamma * p
    g[:, 0] -= gamma
    return float(-np.log(np.maximum(p[:, 0], 1e-300)).sum()), g
