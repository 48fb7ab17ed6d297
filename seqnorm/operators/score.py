"""Membership, activity, scores and labels as DataFrame work over a profile (series_id, start, pattern_id, d)."""

from __future__ import annotations

from collections.abc import Iterator

import pandas as pd
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from seqnorm.functions.distance import phi_col
from seqnorm.session import ship

_BY = ("series_id", "pattern_id")


def profile(windows: DataFrame, patterns: DataFrame, kind: str = "zm") -> DataFrame:
    """windows (series_id, start, xs) against their series' patterns by built-in functions; for small series and checks."""
    from seqnorm.functions.distance import min_place_col

    j = windows.join(patterns.select("series_id", "pattern_id", "pattern"), "series_id")
    return j.select("series_id", "start", "pattern_id", min_place_col(F.col("pattern"), F.col("xs"), kind).alias("d"))


def profile_blocks(blocks: DataFrame, patterns: DataFrame, ell: int, block: int, kind: str = "zm") -> DataFrame:
    """blocks (series_id, block_id, start_pos, xs) against their series' patterns by the NumPy kernel."""
    import numpy as np

    from seqnorm.functions.distance import profile as kernel

    ship(blocks.sparkSession)
    j = blocks.join(patterns.select("series_id", "pattern_id", "pattern"), "series_id")

    def run(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for f in frames:
            for r in f.itertuples():
                d = kernel(np.asarray(r.xs, float), np.asarray(r.pattern, float), ell, kind)
                start = r.start_pos + np.arange(len(d))
                own = start // block == r.block_id
                yield pd.DataFrame({"series_id": r.series_id, "start": start[own], "pattern_id": r.pattern_id, "d": d[own]})

    return j.mapInPandas(run, "series_id string, start bigint, pattern_id int, d double")


def with_phi(prof: DataFrame, patterns: DataFrame, eta: float | None = None, eta_times: float = 1.0) -> DataFrame:
    """prof with tau, freq and phi; eta is a constant, or eta_times / tau."""
    p = patterns.select("series_id", "pattern_id", "tau", "freq")
    e = F.lit(eta) if eta is not None else F.lit(eta_times) / F.col("tau")
    return prof.join(p, list(_BY)).withColumn("phi", phi_col(F.col("d"), F.col("tau"), e))


def with_activity(member: DataFrame, win: int, delta_beyond: int = 0, warmup: str = "partial") -> DataFrame:
    """member with phi_avg over (start - win .. start + delta_beyond) and active."""
    frame = Window.partitionBy(*_BY).orderBy("start").rowsBetween(-win, delta_beyond)
    out = member.withColumn("phi_avg", F.avg("phi").over(frame))
    active = F.col("phi_avg") >= F.col("freq")
    return out.withColumn("active", active if warmup == "partial" else active | (F.row_number().over(Window.partitionBy(*_BY).orderBy("start")) <= win))


def drift_events(member: DataFrame) -> DataFrame:
    """(series_id, pos, kind, pattern_id) where a pattern's activity changes."""
    before = F.lag("active").over(Window.partitionBy(*_BY).orderBy("start"))
    e = member.withColumn("before", before).filter(F.col("before").isNotNull() & (F.col("before") != F.col("active")))
    return e.select("series_id", F.col("start").alias("pos"), F.when(F.col("active"), "on_recurring").otherwise("off").alias("kind"), "pattern_id")


def event_kinds(events: DataFrame, overlap: int) -> DataFrame:
    """A switch-on within `overlap` of the latest switch-off before it is abrupt, any other gradual."""
    spec = Window.partitionBy("series_id").orderBy("pos").rowsBetween(Window.unboundedPreceding, 0)
    off = F.last(F.when(F.col("kind") == "off", F.col("pos")), True).over(spec)
    return events.withColumn("drift", F.when((F.col("kind") != "off") & (F.col("pos") - off <= overlap), "abrupt").when(F.col("kind") != "off", "gradual"))


def nearest_active(member: DataFrame) -> DataFrame:
    """(series_id, start, nearest, d, no_active): the active pattern of smallest distance, of all where none is active; ties to the smaller id."""
    key = F.struct(F.when(F.col("active"), 0).otherwise(1).alias("rank"), F.col("d"), F.col("pattern_id"))
    best = member.groupBy("series_id", "start").agg(F.min(key).alias("b"))
    return best.select("series_id", "start", F.col("b.pattern_id").alias("nearest"), F.col("b.d").alias("d"), (F.col("b.rank") == 1).alias("no_active"))


def trailing_min(member: DataFrame, ell: int, align: str = "trailing") -> DataFrame:
    """Score: smallest distance to the window's nearest active pattern over the last ell windows (or half on each side)."""
    before, after = (-ell, 0) if align == "trailing" else (-(ell // 2), ell // 2)
    low = member.withColumn("low", F.min("d").over(Window.partitionBy(*_BY).orderBy("start").rowsBetween(before, after)))
    key = F.struct(F.when(F.col("active"), 0).otherwise(1).alias("rank"), F.col("d"), F.col("pattern_id"), F.col("low"))
    best = low.groupBy("series_id", "start").agg(F.min(key).alias("b"))
    return best.select("series_id", "start", F.col("b.low").alias("score"), F.col("b.pattern_id").alias("nearest"), (F.col("b.rank") == 1).alias("no_active"))


def weighted_sum(prof: DataFrame, weights: DataFrame) -> DataFrame:
    """Sum of weight times distance over all patterns; weights (series_id, pattern_id, weight)."""
    return prof.join(weights, list(_BY)).groupBy("series_id", "start").agg(F.sum(F.col("weight") * F.col("d")).alias("score"))


def offline_nearest(prof: DataFrame, owners: DataFrame, ell: int, ell_m: int) -> DataFrame:
    """Distance to the pattern whose member segment is nearest in time; owners (series_id, pattern_id, seg).  Ties to the earlier."""
    marks = owners.select("series_id", (F.col("seg") * ell_m + ell_m / 2).cast("double").alias("at"), "pattern_id", F.lit(None).cast("bigint").alias("start"))
    starts = prof.select("series_id", "start").distinct().select("series_id", (F.col("start") + ell / 2).cast("double").alias("at"), F.lit(None).cast("int").alias("pattern_id"), "start")
    both = marks.unionByName(starts)
    back = Window.partitionBy("series_id").orderBy("at", F.col("start").isNotNull()).rowsBetween(Window.unboundedPreceding, 0)
    ahead = Window.partitionBy("series_id").orderBy("at", F.col("start").isNull()).rowsBetween(0, Window.unboundedFollowing)
    mark = F.when(F.col("pattern_id").isNotNull(), F.struct("at", "pattern_id"))
    near = both.withColumns({"b": F.last(mark, True).over(back), "a": F.first(mark, True).over(ahead)}).filter("start is not null")
    pick = F.when(F.col("a").isNull() | (F.col("at") - F.col("b.at") <= F.col("a.at") - F.col("at")), F.col("b.pattern_id")).otherwise(F.col("a.pattern_id"))
    chosen = near.select("series_id", "start", F.coalesce(pick, F.col("a.pattern_id")).alias("pattern_id"))
    return chosen.join(prof, ["series_id", "start", "pattern_id"]).select("series_id", "start", F.col("pattern_id").alias("nearest"), F.col("d").alias("score"))


def admit(candidates: DataFrame, patterns: DataFrame) -> DataFrame:
    """candidates (series_id, cand, pattern, freq) with dissimilar, frequent, admitted.  The few patterns of a series meet its candidates by key."""
    from seqnorm.functions.distance import zm_col

    p = patterns.select("series_id", F.col("pattern").alias("own"), "tau", F.col("freq").alias("own_freq"))
    j = candidates.join(p, "series_id", "left")
    near = F.coalesce(zm_col(F.col("pattern"), F.col("own")) <= F.col("tau"), F.lit(False))
    out = j.groupBy("series_id", "cand", "freq").agg((~F.max(near)).alias("dissimilar"), F.min("own_freq").alias("least"))
    return out.select("series_id", "cand", "dissimilar", F.coalesce(F.col("freq") > F.col("least"), F.lit(True)).alias("frequent")).withColumn("admitted", F.col("dissimilar") & F.col("frequent"))


def label(scores: DataFrame, mode: str = "threshold", threshold: float | None = None, k: int | None = None, q: float = 0.99, patterns: DataFrame | None = None) -> DataFrame:
    """scores with label 0/1 by threshold, radius of the nearest pattern, the k top ranks, or a quantile of all scores."""
    if mode == "threshold":
        alarm: Column = F.col("score") > threshold
    elif mode == "radius":
        p = patterns.select("series_id", F.col("pattern_id").alias("nearest"), "tau")
        scores = scores.join(p, ["series_id", "nearest"], "left")
        alarm = F.col("no_active") | (F.col("score") > F.col("tau"))
    elif mode == "topk":
        top = scores.orderBy(F.desc("score"), "series_id", "start").limit(k).select("series_id", "start", F.lit(1).alias("_top"))
        scores = scores.join(top, ["series_id", "start"], "left")
        alarm = F.col("_top").isNotNull()
    else:
        at = scores.agg(F.percentile_approx("score", q, 100000)).first()[0]
        alarm = F.col("score") > at
    return scores.withColumn("label", alarm.cast("tinyint")).drop("_top", "tau")


def alarms(scores: DataFrame, k: int, exclusion: int) -> DataFrame:
    """The k highest scores of each series no two of which start within `exclusion` of each other; earlier first on ties."""
    ship(scores.sparkSession)

    def run(g: pd.DataFrame) -> pd.DataFrame:
        taken: list[tuple[int, float]] = []
        for r in g.sort_values(["score", "start"], ascending=[False, True]).itertuples():
            if all(abs(r.start - s) >= exclusion for s, _ in taken):
                taken.append((r.start, r.score))
                if len(taken) == k:
                    break
        return pd.DataFrame({"series_id": g["series_id"].iloc[0], "rank": range(1, len(taken) + 1), "start": [t[0] for t in taken], "score": [t[1] for t in taken]})

    return scores.select("series_id", "start", "score").groupBy("series_id").applyInPandas(run, "series_id string, rank int, start bigint, score double")
