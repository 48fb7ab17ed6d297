"""Accuracy and cost measures."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from seqnorm.operators.segment import prefix_sums


def _counted(df: DataFrame, keys: list[str], score: str, y: str) -> DataFrame:
    """Positives p and negatives n of each distinct score, with those of lower scores as p_below and n_below."""
    truth = lambda c: F.sum(c.cast("bigint"))
    c = df.filter(F.col(score).isNotNull() & F.col(y).isNotNull()).groupBy(*keys, score).agg(truth(F.col(y) > 0).alias("p"), truth(F.col(y) <= 0).alias("n"))
    return prefix_sums(c, tuple(keys), score, {"p_below": "p", "n_below": "n"})


def auc(df: DataFrame, score: str = "score", y: str = "y", by: tuple[str, ...] = ()) -> DataFrame:
    """Exact AUC, ties counted half: a row for each group with n_pos, n_neg, auc.

    Rows are counted per score first; running counts go over range partitions of distinct scores, so neither a giant group
    nor the whole table is one task's."""
    keys = list(by)
    out = _counted(df, keys, score, y).groupBy(*keys).agg(F.sum("p").alias("n_pos"), F.sum("n").alias("n_neg"), F.sum(F.col("p") * (F.col("n_below") + F.col("n") / 2.0)).alias("u"))
    return out.select(*keys, "n_pos", "n_neg", F.when((F.col("n_pos") > 0) & (F.col("n_neg") > 0), F.col("u") / F.col("n_pos") / F.col("n_neg")).alias("auc"))


def auc_binned(df: DataFrame, width: float, score: str = "score", y: str = "y") -> DataFrame:
    """AUC over bins of scores with a bound of its error; a bin is a row, however many scores it has."""
    b = _counted(df.withColumn("_bin", F.floor(F.col(score) / width)), [], "_bin", y)
    s = b.agg(F.sum("p").alias("n_pos"), F.sum("n").alias("n_neg"), F.sum(F.col("p") * (F.col("n_below") + F.col("n") / 2.0)).alias("u"), F.sum(F.col("p") * F.col("n")).alias("mixed"))
    pairs = F.col("n_pos") * F.col("n_neg")
    return s.select("n_pos", "n_neg", (F.col("u") / pairs).alias("auc"), (F.col("mixed") / (2.0 * pairs)).alias("bound"))


def roc(df: DataFrame, score: str = "score", y: str = "y") -> DataFrame:
    """(threshold, fpr, tpr) for every distinct score as threshold of the alarms score >= threshold."""
    c = _counted(df, [], score, y)
    total = c.agg(F.sum("p").alias("_pos"), F.sum("n").alias("_neg"))
    rate = lambda below, all_: (F.col(all_) - F.col(below)) / F.col(all_)
    return c.crossJoin(F.broadcast(total)).select(F.col(score).alias("threshold"), rate("n_below", "_neg").alias("fpr"), rate("p_below", "_pos").alias("tpr"))


def confusion(df: DataFrame, alarm: Column, y: str = "y", by: tuple[str, ...] = ()) -> DataFrame:
    hit, true = alarm, F.col(y) > 0
    one = lambda c: F.sum(c.cast("bigint"))
    out = df.groupBy(*by).agg(one(hit & true).alias("tp"), one(hit & ~true).alias("fp"), one(~hit & true).alias("fn"), one(~hit & ~true).alias("tn"))
    precision, recall = F.try_divide("tp", F.col("tp") + F.col("fp")), F.try_divide("tp", F.col("tp") + F.col("fn"))
    out = out.withColumns({"precision": precision, "recall": recall, "fpr": F.try_divide("fp", F.col("fp") + F.col("tn"))})
    return out.withColumn("f1", F.try_divide(2 * F.col("precision") * F.col("recall"), F.col("precision") + F.col("recall")))


def fp_after_drift(alarms: DataFrame, drifts: DataFrame, horizon: int) -> DataFrame:
    """False alarms (series_id, start, y = 0) that start within `horizon` after a drift (series_id, pos), by equal buckets."""
    b = lambda c: F.floor(c / horizon)
    left = alarms.filter(F.col("y") <= 0).withColumn("b", b(F.col("start")))
    right = drifts.withColumn("b", F.explode(F.array(b(F.col("pos")), b(F.col("pos")) + 1)))
    near = left.join(right, ["series_id", "b"]).filter((F.col("start") >= F.col("pos")) & (F.col("start") <= F.col("pos") + horizon))
    return near.groupBy("series_id").agg(F.countDistinct("start").alias("fp_after_drift"))


def window_truth(points: DataFrame, ell: int, y: str = "y_true", least: float | None = None) -> DataFrame:
    """(series_id, start, y): any anomalous point in the window, or a share of at least `least`."""
    frame = Window.partitionBy("series_id").orderBy("pos").rowsBetween(0, ell - 1)
    v = F.max(y).over(frame) if least is None else (F.avg(y).over(frame) >= least).cast("int")
    return points.select("series_id", F.col("pos").alias("start"), v.cast("int").alias("y"), F.count(y).over(frame).alias("_n")).filter(F.col("_n") == ell).drop("_n")


def unclustered(clusters: DataFrame, r_min: float) -> DataFrame:
    from seqnorm.operators.model import filter_small

    return filter_small(clusters, r_min)[1].groupBy("series_id").agg(F.count(F.lit(1)).alias("unclustered"))


def dissim_matrix(items: DataFrame, kind: str = "zm") -> DataFrame:
    """Distances of all pairs of a few named windows (name, xs): concepts and dominant anomalies."""
    from seqnorm.functions.distance import zm_col, zn_col

    a, b = items.select(F.col("name").alias("a"), F.col("xs").alias("xa")), items.select(F.col("name").alias("b"), F.col("xs").alias("xb"))
    return a.crossJoin(F.broadcast(b)).select("a", "b", (zm_col if kind == "zm" else zn_col)(F.col("xa"), F.col("xb")).alias("d"))


def card(points: DataFrame, drifts: DataFrame | None = None) -> DataFrame:
    out = points.groupBy("series_id").agg(F.count(F.lit(1)).alias("n_points"), F.sum(F.col("y_true").cast("bigint")).alias("n_anomalous"), F.avg("x").alias("mean_x"), F.stddev_pop("x").alias("sd_x"))
    if drifts is None:
        return out
    return out.join(drifts.groupBy("series_id").agg(F.count(F.lit(1)).alias("n_drifts")), "series_id", "left").fillna(0, ["n_drifts"])


def by_region(scored: DataFrame) -> DataFrame:
    """Mean score of normal, drift and anomalous windows: scored (score, y, in_transition), by grouping sets."""
    region = F.when(F.col("y") > 0, "anomaly").when(F.col("in_transition"), "drift").otherwise("normal")
    return scored.withColumn("region", region).rollup("region").agg(F.count(F.lit(1)).alias("n"), F.avg("score").alias("mean_score"))


def stability(results: DataFrame, by: str = "method", value: str = "value") -> DataFrame:
    return results.groupBy(by).agg(F.stddev_pop(value).alias("spread"), (F.max(value) - F.min(value)).alias("range"), F.avg(value).alias("mean"))
