"""Ladder layers: a base plane of signs, then planes of signs of what is left.

With c_0 = p_0 = sign(W f):  p_t = sign(R (f - tanh(B c_{t-1}))),
c_t = c_{t-1} + 2^-t p_t (or + p_t without weights).  The loop over planes runs
inside one Arrow batch; B and R may differ for each t or be shared.
"""

from __future__ import annotations

import hashlib
from collections.abc import Callable
from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..functions.codes import CodeSpec, norm_sq_expr, pack, plus_times
from ..functions.text import let
from . import binarize


@dataclass
class LadderParams:
    """W (n x m), and B (m x n) and R (n x m) for each residual plane."""

    W: np.ndarray
    B: list[np.ndarray]
    R: list[np.ndarray]
    weighted: bool = True
    shared: bool = False

    @property
    def n(self) -> int:
        return self.W.shape[0]

    @property
    def depth(self) -> int:
        return len(self.B)

    def layer(self, t: int) -> tuple[np.ndarray, np.ndarray]:
        """B and R for residual plane ``t`` (from 1)."""
        k = 0 if self.shared else t - 1
        return self.B[k], self.R[k]

    def weight(self, t: int) -> float:
        return 2.0**-t if self.weighted else 1.0

    @property
    def fingerprint(self) -> str:
        h = hashlib.sha256(repr((self.weighted, self.shared)).encode())
        for x in (self.W, *self.B, *self.R):
            h.update(np.ascontiguousarray(x, dtype=np.float64).tobytes())
        return h.hexdigest()[:16]

    def spec(self, depth: int | None = None) -> CodeSpec:
        return CodeSpec(self.n, (self.depth if depth is None else depth) + 1, self.weighted, self.fingerprint)


def hadamard(n: int) -> np.ndarray:
    """Rows of ±1, pairwise orthogonal; n is a power of two."""
    h = np.ones((1, 1))
    while h.shape[0] < n:
        h = np.block([[h, h], [h, -h]])
    return h


def init_hadamard(n: int = 64, depth: int = 2, scale: float | None = None, weighted: bool = True) -> LadderParams:
    """No training: W = R is a Hadamard matrix, B its transpose times a scale.

    The default scale suits unit vectors: a coordinate of W f / sqrt(n) is about
    sqrt(2 / (pi n)) away from zero.
    """
    h = hadamard(n)
    scale = float(np.sqrt(2.0 / (np.pi * n))) if scale is None else scale
    return LadderParams(h, [scale / np.sqrt(n) * h.T] * depth, [h] * depth, weighted)


def init_orthogonal(m: int, n: int, depth: int = 2, seed: int = 0, scale: float | None = None, weighted: bool = True, sample: np.ndarray | None = None) -> LadderParams:
    """Random rows (orthogonal where n <= m, stacked orthogonal blocks beyond)."""
    rng = np.random.default_rng(seed)
    blocks, rows = [], 0
    while rows < n:
        q, _ = np.linalg.qr(rng.standard_normal((m, m)))
        blocks.append(q[: min(m, n - rows)])
        rows += blocks[-1].shape[0]
    W = np.concatenate(blocks)
    if scale is None:
        f = sample if sample is not None else rng.standard_normal((512, m)) / np.sqrt(m)
        b = binarize.sign(f @ W.T)
        back = b @ W
        scale = float((back * f).sum() / (back * back).sum())
    return LadderParams(W, [scale * W.T] * depth, [W] * depth, weighted)


def base(f: np.ndarray, W: np.ndarray) -> np.ndarray:
    return binarize.sign(f @ W.T)


def reconstruct(b: np.ndarray, B: np.ndarray) -> np.ndarray:
    return np.tanh(b @ B.T)


def residual(f: np.ndarray, back: np.ndarray, R: np.ndarray) -> np.ndarray:
    return binarize.sign((f - back) @ R.T)


def refine(b: np.ndarray, d: np.ndarray, t: int, weighted: bool = True) -> np.ndarray:
    return b + (2.0**-t if weighted else 1.0) * d


def encode(f: np.ndarray, params: LadderParams, depth: int | None = None) -> list[np.ndarray]:
    """All planes (±1) of a block of real vectors."""
    f = np.asarray(f, dtype=np.float64)
    planes = [base(f, params.W)]
    b = planes[0].astype(np.float64)
    for t in range(1, (params.depth if depth is None else depth) + 1):
        B, R = params.layer(t)
        planes.append(residual(f, reconstruct(b, B), R))
        b = refine(b, planes[-1], t, params.weighted)
    return planes


def dense(planes: list[np.ndarray], weighted: bool = True) -> np.ndarray:
    return sum((2.0**-t if weighted else 1.0) * p.astype(np.float64) for t, p in enumerate(planes))


@dataclass
class Tape:
    """What the backward pass needs."""

    f: np.ndarray
    z: list[np.ndarray] = field(default_factory=list)
    codes: list[np.ndarray] = field(default_factory=list)
    backs: list[np.ndarray] = field(default_factory=list)


def forward(f: np.ndarray, params: LadderParams, act: Callable[[np.ndarray], np.ndarray] = binarize.sign) -> tuple[np.ndarray, Tape]:
    """The dense code and its tape; ``act`` replaces sign in gradient checks."""
    tape = Tape(f, [f @ params.W.T])
    b = act(tape.z[0]).astype(np.float64)
    tape.codes.append(b)
    for t in range(1, params.depth + 1):
        B, R = params.layer(t)
        back = np.tanh(b @ B.T)
        z = (f - back) @ R.T
        b = b + params.weight(t) * act(z)
        tape.backs.append(back)
        tape.z.append(z)
        tape.codes.append(b)
    return b, tape


def backward(g: np.ndarray, tape: Tape, params: LadderParams, slope_grad: Callable[[np.ndarray], np.ndarray]) -> tuple[dict, np.ndarray]:
    """Gradients of W, B, R and of f, from the gradient of the dense code."""
    out = {"W": np.zeros_like(params.W), "B": [np.zeros_like(x) for x in params.B], "R": [np.zeros_like(x) for x in params.R]}
    gf = np.zeros_like(tape.f)
    gb = g
    for t in range(params.depth, 0, -1):
        B, R = params.layer(t)
        k = 0 if params.shared else t - 1
        back, before = tape.backs[t - 1], tape.codes[t - 1]
        gz = params.weight(t) * gb * slope_grad(tape.z[t])
        out["R"][k] += gz.T @ (tape.f - back)
        gd = gz @ R
        gf += gd
        ga = -gd * (1.0 - back**2)
        out["B"][k] += ga.T @ before
        gb = gb + ga @ B
    gz = gb * slope_grad(tape.z[0])
    out["W"] += gz.T @ tape.f
    gf += gz @ params.W
    return out, gf


def matrix(column: pa.Array, m: int | None = None) -> np.ndarray:
    """Rows of equal length (``m``, if given) as a matrix; other lengths are an error."""
    sizes = np.asarray(column.value_lengths())
    m = int(sizes[0]) if m is None and len(sizes) else m
    if (sizes != m).any():
        raise ValueError(f"vectors of length {m} expected, not {sorted(set(sizes.tolist()))[:5]}")
    return column.flatten().to_numpy(zero_copy_only=False).reshape(len(sizes), m or 0)


def encode_vectors(df: DataFrame, params: LadderParams, vector: str = "embedding", key: str = "vec_id", depth: int | None = None, out_key: str = "keyword_id") -> DataFrame:
    """``out_key``, plane words and norm_sq of the vectors of ``df``.

    Null vectors and vectors with a null component are left out (they have no
    signs); NaN and vectors of another length are errors.  One Arrow pass, no shuffle.
    """
    spec, m = params.spec(depth), params.W.shape[1]

    def run(batches):
        for batch in batches:
            if not batch.num_rows:
                continue
            f = matrix(batch.column(1), m)
            words = [w for p in encode(f, params, depth) for w in pack(p).T]
            yield pa.RecordBatch.from_arrays([batch.column(0), *[pa.array(np.ascontiguousarray(w), pa.int64()) for w in words]], [out_key, *spec.columns()])

    usable = df.where(F.col(vector).isNotNull() & F.forall(vector, lambda x: x.isNotNull()))
    source = usable.select(F.col(key).cast("long").alias(out_key), F.col(vector).cast("array<double>").alias("v"))
    coded = source.mapInArrow(run, ", ".join([f"{out_key} long", *[f"{c} long" for c in spec.columns()]]))
    return coded.withColumn("norm_sq", norm_sq_expr(spec))


def planes_sql(vector: Column, params: LadderParams, depth: int) -> list[Column]:
    """Planes as arrays of ±1, in SQL only; small sizes, for comparison with an oracle."""

    def times(rows: np.ndarray, x: Column) -> Column:
        def product(row: np.ndarray, v: Column) -> Column:
            return F.aggregate(F.zip_with(v, F.array(*[F.lit(float(w)) for w in row]), lambda a, b: a * b), F.lit(0.0), lambda s, y: s + y)

        return let(x, lambda v: F.array(*[product(row, v) for row in rows]))

    signs = [F.transform(times(params.W, vector), lambda x: F.when(x > 0, 1).otherwise(-1))]
    code = F.transform(signs[0], lambda x: x.cast("double"))
    for t in range(1, depth + 1):
        B, R = params.layer(t)
        back = F.transform(times(B, code), F.tanh)
        left = F.zip_with(vector, back, lambda a, b: a - b)
        signs.append(F.transform(times(R, left), lambda x: F.when(x > 0, 1).otherwise(-1)))
        code = F.zip_with(code, signs[-1], plus_times(params.weight(t)))
    return signs
