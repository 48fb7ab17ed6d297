"""Training as a DataFrame operator: points to patterns."""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from seqnorm.operators.living import Living, Params, Pattern, fit_series
from seqnorm.session import ship

PATTERNS = "series_id string, pattern_id int, pattern array<double>, tau double, freq double, norm double, n_members int, first_pos bigint, last_pos bigint, born_at bigint, origin string, win int, ell int, ell_m int"


def rows_of(series: str, model: Living, params: Params, offset: int = 0) -> list[tuple]:
    return [
        (series, i, p.shape.tolist(), p.tau, p.freq, float(np.linalg.norm(p.shape)), len(p.members), offset + min(p.members) * params.ell_m if p.members else p.born_at, offset + (max(p.members) + 1) * params.ell_m - 1 if p.members else p.born_at, p.born_at, p.origin, model.win, params.ell, params.ell_m)
        for i, p in enumerate(model.patterns)
    ]


def living_of(rows) -> Living:  # noqa: ANN001
    """Patterns as a pandas frame of one series back to a model."""
    rows = rows.sort_values("pattern_id")
    ps = [Pattern(np.asarray(r.pattern, float), r.tau, r.freq, list(range(r.n_members)), int(r.born_at), r.origin) for r in rows.itertuples()]
    return Living(ps, int(rows["win"].iloc[0]) if len(rows) else 1)


def training_part(points: DataFrame, train: float | str | DataFrame = 0.2) -> DataFrame:
    """The prefix of each series to learn from, all of it, or another frame of points."""
    if isinstance(train, DataFrame):
        return train
    if train == "all":
        return points
    size = points.groupBy("series_id").agg((F.max("pos") + 1).alias("_n"))
    return points.join(size, "series_id").filter(F.col("pos") < F.lit(float(train)) * F.col("_n")).drop("_n")


def fit(points: DataFrame, params: Params = Params(), train: float | str | DataFrame = 0.2) -> DataFrame:
    """patterns of every series; one task per series, over its training part only."""
    import pandas as pd

    ship(points.sparkSession)
    names = [c.split()[0] for c in PATTERNS.split(", ")]

    def run(g: pd.DataFrame) -> pd.DataFrame:
        g = g.sort_values("pos")
        model = fit_series(g["x"].to_numpy(float), params)
        return pd.DataFrame(rows_of(g["series_id"].iloc[0], model, params, int(g["pos"].iloc[0])), columns=names)

    part = training_part(points, train).select("series_id", "pos", "x")
    return part.groupBy("series_id").applyInPandas(run, PATTERNS)


def save(patterns: DataFrame, path: str, buckets: int = 16) -> None:
    bucket = F.pmod(F.crc32(F.col("series_id").cast("binary")), F.lit(buckets)).cast("int")
    patterns.withColumn("series_bucket", bucket).write.mode("overwrite").partitionBy("series_bucket").parquet(path)


def load(spark, path: str) -> DataFrame:  # noqa: ANN001
    return spark.read.parquet(path).drop("series_bucket")


# -- parts of the trainer on fixed clusters, as plain DataFrame work --------------------------------


def filter_small(clusters: DataFrame, r_min: float = 0.01) -> tuple[DataFrame, DataFrame]:
    """(kept, unclustered segments): clusters of at least max(2, r_min of all segments)."""
    total = clusters.groupBy("series_id").agg(F.greatest(F.lit(2), F.ceil(F.count(F.lit(1)) * r_min)).alias("least"))
    size = clusters.groupBy("series_id", "cluster_id").agg(F.count(F.lit(1)).alias("n"))
    good = size.join(total, "series_id").filter("n >= least").select("series_id", "cluster_id")
    keys = ["series_id", "cluster_id"]
    return clusters.join(good, keys, "left_semi"), clusters.join(good, keys, "left_anti")


def window_len(clusters: DataFrame, ell: int, ell_m: int, win_max: int = 20) -> DataFrame:
    size = clusters.groupBy("series_id", "cluster_id").agg(F.count(F.lit(1)).alias("n"))
    return size.groupBy("series_id").agg(F.least(F.lit(win_max * ell), 2 * F.min("n") * ell_m).cast("bigint").alias("win"))


def centroids(clusters: DataFrame, segments: DataFrame) -> DataFrame:
    """(series_id, cluster_id, pattern): pointwise mean of centred members, by hash aggregation per place."""
    from seqnorm.functions.distance import centred

    cells = clusters.join(segments, ["series_id", "seg"]).select("series_id", "cluster_id", F.posexplode(centred(F.col("xs"))).alias("i", "v"))
    means = cells.groupBy("series_id", "cluster_id", "i").agg(F.avg("v").alias("v"))
    ordered = F.array_sort(F.collect_list(F.struct("i", "v")))
    return means.groupBy("series_id", "cluster_id").agg(F.transform(ordered, lambda s: s["v"]).alias("pattern"))


def radius(clusters: DataFrame, segments: DataFrame, patterns: DataFrame, sigmas: float = 3.0) -> DataFrame:
    from seqnorm.functions.distance import zm_col

    d = clusters.join(segments, ["series_id", "seg"]).join(patterns, ["series_id", "cluster_id"]).withColumn("d", zm_col(F.col("xs"), F.col("pattern")))
    return d.groupBy("series_id", "cluster_id").agg((F.avg("d") + sigmas * F.stddev_pop("d")).alias("tau"))


def spans(clusters: DataFrame, ell_m: int) -> DataFrame:
    """(series_id, cluster_id, first, last): the points that a cluster's segments reach over."""
    return clusters.groupBy("series_id", "cluster_id").agg((F.min("seg") * ell_m).cast("bigint").alias("first"), ((F.max("seg") + 1) * ell_m - 1).cast("bigint").alias("last"))


def radius_sub(prof: DataFrame, spans_: DataFrame, ell: int, sigmas: float = 3.0) -> DataFrame:
    """tau from the windows of length ell inside a cluster's span; prof (series_id, start, pattern_id, d)."""
    s = spans_.withColumnRenamed("cluster_id", "pattern_id")
    inside = prof.join(s, ["series_id", "pattern_id"]).filter((F.col("start") >= F.col("first")) & (F.col("start") + ell - 1 <= F.col("last")))
    return inside.groupBy("series_id", "pattern_id").agg((F.avg("d") + sigmas * F.stddev_pop("d")).alias("tau"))


def presence(member: DataFrame, spans_: DataFrame, win: int, ell: int, mode: str = "overlap") -> DataFrame:
    """freq: the smallest mean membership over windows of `win` starts that meet the cluster's span; member (series_id, start, pattern_id, phi)."""
    from pyspark.sql import Window

    frame = Window.partitionBy("series_id", "pattern_id").orderBy("start").rowsBetween(0, win - 1)
    means = member.select("series_id", "pattern_id", "start", F.avg("phi").over(frame).alias("m"), F.count("phi").over(frame).alias("n")).filter(F.col("n") == win)
    j = means.join(spans_.withColumnRenamed("cluster_id", "pattern_id"), ["series_id", "pattern_id"])
    hi = F.col("start") + win + ell - 2
    common = F.least(hi, F.col("last")) - F.greatest(F.col("start"), F.col("first")) + 1
    span = F.least(F.col("last") - F.col("first") + 1, F.lit(win + ell - 1))
    meets = {"overlap": common > 0, "majority": 2 * common >= span, "contain": common >= span}[mode]
    return j.filter(meets).groupBy("series_id", "pattern_id").agg(F.min("m").alias("freq"))
