"""Linkage distances between clusters of equal-length segments."""

from __future__ import annotations

from collections.abc import Sequence
from dataclasses import dataclass

import numpy as np

KINDS = ("single", "complete", "average", "centroid", "ward")


@dataclass(slots=True)
class Stats:
    """Size, sum and members of a cluster; centroid and Ward linkage need the first two only."""

    n: int
    total: np.ndarray
    members: Sequence[int]


def ward(a: Stats, b: Stats) -> float:
    gap = a.total / a.n - b.total / b.n
    return float(np.sqrt(2.0 * a.n * b.n / (a.n + b.n)) * np.linalg.norm(gap))


def centroid(a: Stats, b: Stats) -> float:
    return float(np.linalg.norm(a.total / a.n - b.total / b.n))


def link(kind: str, a: Stats, b: Stats, rows: np.ndarray) -> float:
    """rows: all prepared segments, for linkages over pairs of members."""
    if kind == "ward":
        return ward(a, b)
    if kind == "centroid":
        return centroid(a, b)
    left, right = rows[list(a.members)], rows[list(b.members)]
    square = (left * left).sum(1)[:, None] + (right * right).sum(1)[None, :] - 2 * left @ right.T
    d = np.sqrt(np.maximum(square, 0.0))
    return float({"single": d.min, "complete": d.max, "average": d.mean}[kind]())
