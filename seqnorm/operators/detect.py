"""Detection as DataFrame operators: online in epochs, offline, and in blocks for a fixed model."""

from __future__ import annotations

from dataclasses import replace

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from seqnorm.functions import distance as D
from seqnorm.operators import segment
from seqnorm.operators.living import Detected, Living, Params, activity, detect_series, eta_of, fit_series, offline_series, scan_series, window_score
from seqnorm.operators.model import living_of
from seqnorm.session import ship

SCORES = "series_id string, start bigint, score double, nearest int, no_active boolean, event string, pattern_id int"
EVENTS = ("off", "on_recurring", "born", "refused")


def events_of(found: Detected) -> list[tuple[int, str, int]]:
    """(window, kind, pattern) of every change of activity, and of every pattern refused; the first window's state is no change."""
    out = [(j, "born", q) for j, q in found.births] + [(j, "refused", -1) for j in found.refused]
    born = {q: j for j, q in found.births}
    for q in range(found.active.shape[1]):
        change = np.flatnonzero(np.diff(found.active[:, q].astype(np.int8))) + 1
        for j in change:
            if found.active[j, q] and born.get(q) != j:
                out.append((int(j), "on_recurring", q))
            elif not found.active[j, q]:
                out.append((int(j), "off", q))
    return sorted(out)


def frame_of(series: str, found: Detected, offset: int = 0) -> pd.DataFrame:
    """Scores and drift events in one schema: an event is a row with event set and no score."""
    n = len(found.score)
    scores = pd.DataFrame({"series_id": series, "start": np.arange(n) + offset, "score": found.score, "nearest": found.nearest, "no_active": found.no_active, "event": None, "pattern_id": found.nearest})
    events = events_of(found)
    if events:
        e = pd.DataFrame({"series_id": series, "start": [x[0] + offset for x in events], "score": np.nan, "nearest": -1, "no_active": False, "event": [x[1] for x in events], "pattern_id": [x[2] for x in events]})
        scores = pd.concat([scores, e], ignore_index=True)
    return scores.astype({"nearest": "int32", "pattern_id": "int32"})


def _whole(points: DataFrame, run) -> DataFrame:  # noqa: ANN001
    ship(points.sparkSession)
    return points.select("series_id", "pos", "x").groupBy("series_id").applyInPandas(run, SCORES)


def online(points: DataFrame, params: Params = Params(), train: float = 0.2, events: bool = True) -> DataFrame:
    """Train on each series' prefix and scan the series with births and drift events; without events in stretches, as
    activity need not be kept."""
    scan = detect_series if events else scan_series

    def run(g: pd.DataFrame) -> pd.DataFrame:
        g = g.sort_values("pos")
        x = g["x"].to_numpy(float)
        model = fit_series(x[: max(params.ell_m, int(len(x) * train))], params)
        found = scan(x, model, params)
        if not events:
            found = replace(found, births=[], refused=[], active=found.active[:, :0])
        return frame_of(g["series_id"].iloc[0], found, int(g["pos"].iloc[0]))

    return _whole(points, run)


def batch(points: DataFrame, patterns: DataFrame, params: Params = Params()) -> DataFrame:
    """Scan each series with its trained patterns; points and patterns of a series meet in one task."""
    ship(points.sparkSession)

    def run(g: pd.DataFrame, p: pd.DataFrame) -> pd.DataFrame:
        if not len(g):
            return pd.DataFrame(columns=[c.split()[0] for c in SCORES.split(", ")])
        g = g.sort_values("pos")
        model = living_of(p) if len(p) else Living([], params.win_max * params.ell)
        return frame_of(g["series_id"].iloc[0], detect_series(g["x"].to_numpy(float), model, params), int(g["pos"].iloc[0]))

    left, right = points.select("series_id", "pos", "x").groupBy("series_id"), patterns.groupBy("series_id")
    return left.cogroup(right).applyInPandas(run, SCORES)


def offline(points: DataFrame, params: Params = Params()) -> DataFrame:
    def run(g: pd.DataFrame) -> pd.DataFrame:
        g = g.sort_values("pos")
        return frame_of(g["series_id"].iloc[0], offline_series(g["x"].to_numpy(float), params), int(g["pos"].iloc[0])).query("event.isnull()")

    return _whole(points, run)


def scores(found: DataFrame) -> DataFrame:
    return found.filter("event is null").select("series_id", "start", "score", "nearest", "no_active")


def drift_events(found: DataFrame) -> DataFrame:
    return found.filter("event is not null").select("series_id", F.col("start").alias("pos"), F.col("event").alias("kind"), "pattern_id")


def in_blocks(points: DataFrame, patterns: DataFrame, params: Params = Params(), block: int = 1 << 17) -> DataFrame:
    """Scores of giant series for a fixed model.  A block holds its points and a halo before and after them, wide enough
    for the currency window, so blocks need nothing of each other; patterns come with their series' rows."""
    ship(points.sparkSession)
    params = replace(params, births=False)
    win = int(patterns.agg(F.max("win")).first()[0] or 1)
    before, after = win + params.ell, params.ell - 1 + max(0, params.delta - params.ell)
    cells = segment.block_rows(points, block, before, after)

    def run(g: pd.DataFrame, p: pd.DataFrame) -> pd.DataFrame:
        names = ["series_id", "start", "score", "nearest", "no_active"]
        if not len(g) or not len(p):
            return pd.DataFrame(columns=names)
        g = g.sort_values("pos")
        x, pos, model = g["x"].to_numpy(float), g["pos"].to_numpy(), living_of(p)
        if len(x) < params.ell:
            return pd.DataFrame(columns=names)
        d = np.stack([D.profile(x, q.shape, params.ell, params.distance) for q in model.patterns], 1)
        on = np.stack([activity(D.phi(d[:, i], q.tau, eta_of(q, params)), q.freq, model.win, params)[1] for i, q in enumerate(model.patterns)], 1)
        none = ~on.any(1)
        nearest = np.where(on | none[:, None], d, np.inf).argmin(1)
        score = window_score(d, nearest, params.ell, params.align)
        start = pos[: len(score)]
        own = start // block == g["block_id"].iloc[0]
        return pd.DataFrame({"series_id": g["series_id"].iloc[0], "start": start[own], "score": score[own], "nearest": nearest[own].astype("int32"), "no_active": none[own]})

    blocks = cells.select(F.col("series_id").alias("series_id"), F.col("block_id").alias("block_id")).distinct()
    carried = blocks.join(patterns, "series_id")
    schema = "series_id string, start bigint, score double, nearest int, no_active boolean"
    return cells.groupBy("series_id", "block_id").cogroup(carried.groupBy("series_id", "block_id")).applyInPandas(run, schema)
