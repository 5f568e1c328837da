"""Distances as Column expressions (unrolled, inside whole-stage codegen) and on NumPy blocks.  (C: distances)"""

from __future__ import annotations

from collections.abc import Sequence

import numpy as np
from pyspark.sql import Column
from pyspark.sql import functions as F

KINDS = ("euclidean", "sqeuclidean", "manhattan", "chebyshev")


def distance_expr(kind: str, a: Sequence[Column], b: Sequence[Column]) -> Column:
    """Distance of two unrolled vectors."""
    gaps = [x - y for x, y in zip(a, b, strict=True)]
    if kind in ("euclidean", "sqeuclidean"):
        total = gaps[0] * gaps[0]
        for g in gaps[1:]:
            total = total + g * g
        return F.sqrt(total) if kind == "euclidean" else total
    if kind == "manhattan":
        total = F.abs(gaps[0])
        for g in gaps[1:]:
            total = total + F.abs(g)
        return total
    if kind == "chebyshev":
        return F.greatest(*(F.abs(g) for g in gaps)) if len(gaps) > 1 else F.abs(gaps[0])
    raise ValueError(f"distance must be one of {KINDS}, not {kind!r}")


def vector(name: str, d: int) -> list[Column]:
    """The d elements of an array column."""
    return [F.col(name).getItem(i) for i in range(d)]


def _added(kind: str, gaps) -> np.ndarray:
    """A distance from the coordinates' gaps, added up in their order: equal wherever a pair is met."""
    total = None
    for gap in gaps:
        part = gap * gap if kind in ("euclidean", "sqeuclidean") else np.abs(gap)
        if total is None:
            total = part
        else:
            total = np.maximum(total, part) if kind == "chebyshev" else total + part
    return np.sqrt(total) if kind == "euclidean" else total


def distances(kind: str, block: np.ndarray, x: np.ndarray) -> np.ndarray:
    """Distance of each row of ``block`` to the point ``x``."""
    if kind not in KINDS:
        raise ValueError(f"distance must be one of {KINDS}, not {kind!r}")
    return _added(kind, (block[:, i] - x[i] for i in range(block.shape[1])))


def block_distances(kind: str, a: np.ndarray, b: np.ndarray) -> np.ndarray:
    """All distances of two blocks (the rows of ``a`` are cut where memory asks for it)."""
    rows = max(1, 16_000_000 // max(len(b), 1))
    if len(a) > rows:
        return np.concatenate([block_distances(kind, a[i : i + rows], b) for i in range(0, len(a), rows)])
    return _added(kind, (a[:, i, None] - b[None, :, i] for i in range(a.shape[1])))


def pairwise(kind: str, a: np.ndarray, b: np.ndarray) -> np.ndarray:
    """All distances of two blocks, row by row (low memory)."""
    return np.stack([distances(kind, b, x) for x in a]) if len(a) else np.zeros((0, len(b)))
