"""Small closed forms: code cardinality, cube edges."""

from __future__ import annotations

from fractions import Fraction


def values_per_dim(planes: int, weighted: bool = True) -> list[float]:
    """The values one dimension of a code can take."""
    out = {0.0}
    for t in range(planes):
        w = 2.0**-t if weighted else 1.0
        out = {x + s * w for x in out for s in (-1, 1)}
    return sorted(out)


def cardinality(planes: int, n: int, weighted: bool = True) -> int:
    """Number of codes: 2^planes per dimension, or planes + 1 without weights."""
    return (2**planes if weighted else planes + 1) ** n


def cardinality_ratio(planes: int, n: int) -> Fraction:
    return Fraction(cardinality(planes, n), cardinality(planes, n, False))


def edge_fraction(volume: float, dims: int) -> float:
    """How much of each edge a cube needs to cover ``volume`` of the unit cube."""
    return volume ** (1.0 / dims)
