"""Barycentric Lagrange interpolation on Gauss-Lobatto nodes, as NumPy code and as an Arrow-batched column function."""

from __future__ import annotations

import functools

import numpy as np
import pandas as pd
from pyspark.sql import Column
from pyspark.sql import functions as F


@functools.lru_cache(maxsize=16)
def lobatto_nodes(n: int) -> np.ndarray:
    """The n nodes on [-1, 1]: the ends and the roots of the derivative of the Legendre polynomial of degree n - 1."""
    if n < 2:
        raise ValueError("at least two nodes")
    inner = np.polynomial.legendre.Legendre.basis(n - 1).deriv().roots() if n > 2 else []
    return np.concatenate([[-1.0], np.sort(np.real(inner)), [1.0]])


@functools.lru_cache(maxsize=16)
def barycentric_weights(n: int) -> np.ndarray:
    x = lobatto_nodes(n)
    gaps = x[:, None] - x[None, :]
    np.fill_diagonal(gaps, 1.0)
    return 1.0 / gaps.prod(axis=1)


def cardinal_values(at: np.ndarray, n: int) -> np.ndarray:
    """(points, n): value of each node's cardinal polynomial at the points; on a node exactly 0 or 1."""
    gap = np.asarray(at, float)[:, None] - lobatto_nodes(n)[None, :]
    on = np.isclose(gap, 0.0, atol=1e-14)
    part = barycentric_weights(n) / np.where(on, 1.0, gap)
    values = part / part.sum(axis=1, keepdims=True)
    hit = on.any(axis=1)
    values[hit] = on[hit].astype(float)
    return values


def interpolate_points(field: np.ndarray, x: np.ndarray, y: np.ndarray, z: np.ndarray, n: int) -> np.ndarray:
    """Tensor-product value of each point in its own cell. ``field``: (points, n**3), x running fastest."""
    grid = field.reshape(-1, n, n, n)
    return np.einsum("pkji,pi,pj,pk->p", grid, cardinal_values(x, n), cardinal_values(y, n), cardinal_values(z, n), optimize=True)


def interpolated(field: str | Column, x: str | Column, y: str | Column, z: str | Column, n: int) -> Column:
    """Column form: ``field`` is the cell's array of n**3 values, x, y, z the place inside the cell in [-1, 1]."""

    @F.pandas_udf("double")
    def at(f: pd.Series, a: pd.Series, b: pd.Series, c: pd.Series) -> pd.Series:
        if not len(f):
            return pd.Series([], dtype=float)
        return pd.Series(interpolate_points(np.stack(f.to_numpy()), a.to_numpy(), b.to_numpy(), c.to_numpy(), n))

    return at(field, x, y, z)
