"""Packed symmetric matrices: the upper triangle, row by row, as array<double> of D(D+1)/2."""

from __future__ import annotations

import numpy as np
from pyspark.sql import Column
from pyspark.sql import functions as F


def place(i: int, j: int, dim: int) -> int:
    """Slot of entry (i, j), from 0."""
    i, j = min(i, j), max(i, j)
    return i * dim - i * (i - 1) // 2 + (j - i)


def slots(dim: int) -> list[tuple[int, int]]:
    return [(i, j) for i in range(dim) for j in range(i, dim)]


def dim_of(length: int) -> int:
    """D of a packed matrix with so many slots."""
    return (int((8 * length + 1) ** 0.5) - 1) // 2


def diagonal(cov: Column, dim: Column) -> Column:
    """Diagonal of a packed matrix, for any D."""
    return F.transform(F.sequence(F.lit(0), dim - 1), lambda i: F.element_at(cov, (i * dim - F.floor(i * (i - 1) / 2) + 1).cast("int")))


def dense(packed: np.ndarray, dim: int) -> np.ndarray:
    """(b, D(D+1)/2) to (b, D, D)."""
    i, j = np.triu_indices(dim)
    out = np.zeros((len(packed), dim, dim))
    out[:, i, j] = packed
    out[:, j, i] = packed
    return out


def packed(full: np.ndarray) -> np.ndarray:
    i, j = np.triu_indices(full.shape[-1])
    return full[..., i, j]
