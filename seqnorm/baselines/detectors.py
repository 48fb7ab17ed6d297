"""The compared detectors as DataFrame operators: points (series_id, pos, x) to (series_id, start, score)."""

from __future__ import annotations

import pickle
from collections.abc import Callable

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from seqnorm.baselines import kernels
from seqnorm.functions.distance import scaled
from seqnorm.operators import segment
from seqnorm.session import materialise, ship

SCORES = "series_id string, start bigint, score double"


def per_series(points: DataFrame, kernel: Callable[[np.ndarray], np.ndarray]) -> DataFrame:
    """One task per series, for detectors that go through a series in order."""
    ship(points.sparkSession)

    def run(g: pd.DataFrame) -> pd.DataFrame:
        g = g.sort_values("pos")
        score = kernel(g["x"].to_numpy(float))
        return pd.DataFrame({"series_id": g["series_id"].iloc[0], "start": g["pos"].iloc[0] + np.arange(len(score)), "score": score})

    return points.select("series_id", "pos", "x").groupBy("series_id").applyInPandas(run, SCORES)


def static_weighted(points: DataFrame, ell: int, mult: int = 2, sample: int = 5000, select: str = "random", weight: str = "freq") -> DataFrame:
    def kernel(x: np.ndarray) -> np.ndarray:
        shapes, weights = kernels.static_fit(x, ell, mult, sample, select, weight)
        return kernels.static_score(x, shapes, weights, ell)

    return per_series(points, kernel)


def batch_shape(points: DataFrame, ell: int, mult: int = 2, batch: int = 5000, k: int = 4, alpha: float = 0.5, decay: float = 0.8, sample: int | None = None, mode: str = "online") -> DataFrame:
    """Batches are fitted and scored in tasks of their own; only merging their few shapes goes through a series in order.

    Positions are dense and begin at 0.  The offline mode has one batch, which is the whole series."""
    if mode == "offline":
        return per_series(points, lambda x: kernels.batch_shape(x, ell, mult, batch, k, alpha, decay, sample, mode))
    ship(points.sparkSession)
    cells = segment.block_rows(points, batch, 0, ell - 1)
    spread = 8 * points.sparkSession.sparkContext.defaultParallelism
    cells = cells.repartition(spread, "series_id", "block_id")  # few bytes and much work: the planner would merge them
    keys, model = "series_id string, block_id bigint", "centres array<array<double>>, weights array<double>"

    def fit(g: pd.DataFrame) -> pd.DataFrame:
        g = g.sort_values("pos")
        fresh = kernels.batch_fit(g["x"].to_numpy(float), ell, mult, k, sample)
        return pd.DataFrame({"series_id": g["series_id"].iloc[:1], "block_id": g["block_id"].iloc[:1], "centres": [[c.tolist() for c, _ in fresh]], "weights": [[w for _, w in fresh]]})

    def merge(g: pd.DataFrame) -> pd.DataFrame:
        centres, weights, out = [], [], []
        for fresh, shares in zip(*(g.sort_values("block_id")[c] for c in ("centres", "weights"))):
            centres, weights = kernels.batch_merge(centres, weights, [(np.array(c, float), float(w)) for c, w in zip(fresh, shares)], alpha, decay)
            out.append(([c.tolist() for c in centres], list(weights)))
        return g.sort_values("block_id")[["series_id", "block_id"]].assign(centres=[c for c, _ in out], weights=[w for _, w in out])

    def score(g: pd.DataFrame, m: pd.DataFrame) -> pd.DataFrame:
        g, m = g.sort_values("pos"), m.iloc[0]
        s = kernels.batch_score(g["x"].to_numpy(float), ell, [np.array(c, float) for c in m["centres"]], list(m["weights"]), batch)
        return pd.DataFrame({"series_id": m["series_id"], "start": g["pos"].to_numpy()[: len(s)], "score": s})

    fitted = materialise(cells.groupBy("series_id", "block_id").applyInPandas(fit, f"{keys}, {model}"), "shapes")
    merged = fitted.groupBy("series_id").applyInPandas(merge, f"{keys}, {model}").repartition(spread, "series_id", "block_id")
    return cells.groupBy("series_id", "block_id").cogroup(merged.groupBy("series_id", "block_id")).applyInPandas(score, SCORES)


def backward_discord(points: DataFrame, ell: int, lookback: int | None = None, prune: bool = True, block: int | None = None) -> DataFrame:
    """Exact per series; with a lookback and a block, giant series are cut into blocks with a halo of the lookback."""
    if block is None or lookback is None:
        return per_series(points, lambda x: kernels.backward_discord(x, ell, lookback, prune))
    ship(points.sparkSession)
    cells = segment.block_rows(points, block, lookback + 4 * ell, ell - 1)

    def run(g: pd.DataFrame) -> pd.DataFrame:
        g = g.sort_values("pos")
        score = kernels.backward_discord(g["x"].to_numpy(float), ell, lookback, False, 0)
        start = g["pos"].to_numpy()[: len(score)]
        own = (start // block == g["block_id"].iloc[0]) & (start >= 4 * ell)
        early = (start // block == g["block_id"].iloc[0]) & (start < 4 * ell)
        return pd.DataFrame({"series_id": g["series_id"].iloc[0], "start": np.r_[start[early], start[own]], "score": np.r_[np.zeros(early.sum()), score[own]]})

    return cells.groupBy("series_id", "block_id").applyInPandas(run, SCORES)


def transformer(points: DataFrame, ell: int, train: float = 0.2, epochs: int = 3, seed: int = 0, stride: int = 1, block: int = 8192) -> DataFrame:
    """A series' first points train its model in one task, as that goes in order; windows are scored in blocks.

    Positions are dense and begin at 0.  With a stride a series is one task."""
    if stride != 1:
        return per_series(points, lambda x: kernels.transformer_score(x, ell, train, epochs, seed, stride))
    ship(points.sparkSession)
    spread = 8 * points.sparkSession.sparkContext.defaultParallelism
    points = points.select("series_id", "pos", "x")
    sizes = points.groupBy("series_id").agg(F.count(F.lit(1)).alias("n"))
    first = F.greatest(F.lit(ell + 1), F.floor(F.col("n") * train).cast("int"))
    prefix = points.join(F.broadcast(sizes), "series_id").filter(F.col("pos") < first)

    def fit(g: pd.DataFrame) -> pd.DataFrame:
        x, n = g.sort_values("pos")["x"].to_numpy(float), int(g["n"].iloc[0])
        net = None if n < kernels.transformer_first(n, ell, train) else kernels.transformer_fit(x, ell, epochs, seed)
        return pd.DataFrame({"series_id": g["series_id"].iloc[:1], "n": [n], "model": [pickle.dumps(net)]})

    def score(g: pd.DataFrame, m: pd.DataFrame) -> pd.DataFrame:
        g, net = g.sort_values("pos"), pickle.loads(m["model"].iloc[0])
        x, start = g["x"].to_numpy(float), g["pos"].to_numpy()
        n = min(block, max(0, len(x) - ell + 1))
        s = kernels.transformer_errors(x[: n + ell - 1], ell, *net) if net and n else np.zeros(n)
        return pd.DataFrame({"series_id": m["series_id"].iloc[0], "start": start[:n], "score": s})

    models = materialise(prefix.groupBy("series_id").applyInPandas(fit, "series_id string, n bigint, model binary"), "transformer")
    cells = segment.block_rows(points, block, 0, ell - 1).repartition(spread, "series_id", "block_id")
    number = F.explode(F.sequence(F.lit(0).cast("bigint"), F.floor((F.col("n") - 1) / block)))
    carried = models.select("series_id", number.alias("block_id"), "model").repartition(spread, "series_id", "block_id")
    return cells.groupBy("series_id", "block_id").cogroup(carried.groupBy("series_id", "block_id")).applyInPandas(score, SCORES)


def matrix_profile(points: DataFrame, ell: int, side: str = "both") -> DataFrame:
    """Reference profile by kernel; windows without any neighbour get null."""
    out = per_series(points, lambda x: kernels.matrix_profile(x, ell, side))
    return out.withColumn("score", F.when(F.col("score") < float("inf"), F.col("score")))


def left_profile(points: DataFrame, ell: int, block: int = 64) -> DataFrame:
    """The left profile as a join: blocks of windows against blocks that end no later; the exact quadratic form, for short series."""
    w = segment.windows(points, ell).withColumn("z", scaled(F.col("xs"))).select("series_id", "start", "z")
    b = w.groupBy("series_id", F.floor(F.col("start") / block).alias("blk")).agg(F.collect_list(F.struct("start", "z")).alias("ws"))
    later, earlier = b.select("series_id", F.col("blk").alias("i"), F.explode("ws").alias("a")), b.select("series_id", F.col("blk").alias("j"), "ws")
    square = lambda x, y: F.aggregate(F.zip_with(x, y, lambda p, q: (p - q) * (p - q)), F.lit(0.0), lambda s, v: s + v)
    pairs = later.join(earlier, "series_id").filter("j <= i")
    best = F.array_min(F.transform(F.filter("ws", lambda e: e["start"] <= F.col("a.start") - ell), lambda e: square(F.col("a.z"), e["z"])))
    return pairs.select("series_id", F.col("a.start").alias("start"), best.alias("s")).groupBy("series_id", "start").agg(F.sqrt(F.min("s")).alias("score")).filter("score is not null")


def adaptive_window(points: DataFrame, ell: int, delta: float = 0.002) -> DataFrame:
    """(series_id, pos) of the drifts that adaptive windows find over level, spread and roughness of points with a period of ell."""
    ship(points.sparkSession)

    def run(g: pd.DataFrame) -> pd.DataFrame:
        g = g.sort_values("pos")
        at = kernels.drift_positions(g["x"].to_numpy(float), ell, delta)
        return pd.DataFrame({"series_id": g["series_id"].iloc[0], "pos": g["pos"].to_numpy()[at]})

    return points.select("series_id", "pos", "x").groupBy("series_id").applyInPandas(run, "series_id string, pos bigint")


def batch_ids(points: DataFrame, batch: int = 5000) -> DataFrame:
    return points.groupBy("series_id", F.floor(F.col("pos") / batch).alias("batch_id")).agg(F.count(F.lit(1)).alias("n"), F.min("pos").alias("first_pos"))


__all__ = ["adaptive_window", "backward_discord", "batch_ids", "batch_shape", "left_profile", "matrix_profile", "per_series", "static_weighted", "transformer"]
