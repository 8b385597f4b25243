"""Sign binarisation and the gradients that stand in for its derivative."""

from __future__ import annotations

import numpy as np
from pyspark.sql import Column
from pyspark.sql import functions as F

SURROGATES = ("identity", "clipped", "anneal", "stochastic")


def sign(x: np.ndarray) -> np.ndarray:
    """-1 for x <= 0 (and for either zero), else +1; NaN is an error."""
    x = np.asarray(x)
    if np.isnan(x).any():
        raise ValueError("NaN has no sign")
    return np.where(x > 0, 1.0, -1.0).astype(np.float32)


def sign_expr(x: Column) -> Column:
    """The same for a column: null stays null, NaN is an error."""
    return F.when(F.isnan(x), F.raise_error(F.lit("NaN has no sign")).cast("int")).when(x > 0, F.lit(1)).when(x <= 0, F.lit(-1))


def slope_at(epoch: int, growth: float = 1.05, cap: float = 10.0) -> float:
    """Annealing slope: from 1, gently up."""
    return min(cap, growth**epoch)


def grad(kind: str, x: np.ndarray, slope: float = 1.0) -> np.ndarray:
    """Stand-in derivative of sign at ``x``.

    identity: 1; clipped: 1 within [-1, 1]; anneal: that of tanh(slope x);
    stochastic: that of the hard sigmoid's expectation.
    """
    if kind == "identity":
        return np.ones_like(x)
    if kind in ("clipped", "stochastic"):
        return (np.abs(x) <= 1.0).astype(x.dtype)
    if kind == "anneal":
        return slope * (1.0 - np.tanh(slope * x) ** 2)
    raise ValueError(f"one of {SURROGATES}")


def stochastic_sign(x: np.ndarray, rng: np.random.Generator) -> np.ndarray:
    """+1 with the probability of the hard sigmoid: unbiased, noisy."""
    return np.where(rng.random(x.shape) < np.clip((x + 1.0) / 2.0, 0.0, 1.0), 1.0, -1.0).astype(np.float32)
