"""Choices made before a plan is built."""

from __future__ import annotations

from dataclasses import dataclass, replace

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from seqnorm.operators.living import Params

#: What one task may hold: points of a series, and bytes of patterns to send to every task.
SERIES_POINTS, BROADCAST_BYTES, TRAIN_SEGMENTS, EXACT_SCORES, QUADRATIC_POINTS = 4_000_000, 64 << 20, 50_000, 50_000_000, 200_000


@dataclass(frozen=True)
class Choice:
    """series: one task per series; blocks: blocks with halo for a fixed model."""

    scan: str
    broadcast_patterns: bool
    train_rounds: bool
    binned_auc: bool
    quadratic: bool


def choose(points: DataFrame, params: Params = Params(), patterns_per_series: int = 64) -> Choice:
    """One aggregation over series sizes decides how series are scanned, trained and measured."""
    per = points.groupBy("series_id").agg(F.count(F.lit(1)).alias("n"))
    most, total, series = per.agg(F.max("n"), F.sum("n"), F.count(F.lit(1))).first()
    most, total = most or 0, total or 0
    return Choice(
        scan="series" if most <= SERIES_POINTS else "blocks",
        broadcast_patterns=series * patterns_per_series * params.ell_m * 8 <= BROADCAST_BYTES,
        train_rounds=most * 0.2 / params.ell_m > TRAIN_SEGMENTS,
        binned_auc=total > EXACT_SCORES,
        quadratic=most <= QUADRATIC_POINTS,
    )


def detect(points: DataFrame, params: Params = Params(), train: float = 0.2, frozen: bool = False) -> DataFrame:
    """Scores of every series, with births whatever its size, as births make a series sequential and so one task's.

    With `frozen`, or with params that have no births, no concept is learned after training, and series are scored in
    blocks when one of them is larger than a task should hold; that doesn't change the frozen model's scores."""
    from seqnorm.operators import detect as how
    from seqnorm.operators.model import fit

    params = replace(params, births=False) if frozen else params
    if params.births or choose(points, params).scan == "series":
        return how.scores(how.online(points, params, train))
    return how.in_blocks(points, fit(points, params, train), params)
