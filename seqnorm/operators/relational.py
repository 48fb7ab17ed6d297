"""Operators around the detectors that Spark has no single call for, and thin forms of those it has."""

from __future__ import annotations

from collections.abc import Sequence

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F


def slice_pos(df: DataFrame, lo: int, hi: int) -> DataFrame:
    return df.filter(F.col("pos").between(lo, hi))


def where_active(df: DataFrame) -> DataFrame:
    return df.filter("active")


def asof(left: DataFrame, right: DataFrame, by: str, on: str, value: str, direction: str = "backward") -> DataFrame:
    """left with right's `value` at the latest (backward), next (forward) or nearest place; nearest ties go to the earlier.

    Both sides are put into one stream per key and the last or first value is carried along, so nothing is multiplied."""
    a = left.select("*", F.lit(None).cast(right.schema[value].dataType).alias("_v"), F.lit(1).alias("_side"))
    b = right.select(by, on, F.col(value).alias("_v"), F.lit(0).alias("_side"))
    both = a.unionByName(b, allowMissingColumns=True)
    mark = F.when(F.col("_side") == 0, F.struct(F.col(on).alias("at"), F.col("_v").alias("v")))
    back = F.last(mark, True).over(Window.partitionBy(by).orderBy(on, "_side").rowsBetween(Window.unboundedPreceding, 0))
    ahead = F.first(mark, True).over(Window.partitionBy(by).orderBy(on, F.desc("_side")).rowsBetween(0, Window.unboundedFollowing))
    out = both.withColumns({"_b": back, "_a": ahead}).filter("_side = 1")
    if direction == "backward":
        pick = F.col("_b.v")
    elif direction == "forward":
        pick = F.col("_a.v")
    else:
        near = F.col("_a").isNull() | (F.col(on) - F.col("_b.at") <= F.col("_a.at") - F.col(on))
        pick = F.when(F.col("_b").isNotNull() & near, F.col("_b.v")).otherwise(F.col("_a.v"))
    return out.select(*left.columns, pick.alias(value))


def range_join(a: DataFrame, b: DataFrame, a_lo: str, a_hi: str, b_lo: str, b_hi: str, width: int, by: Sequence[str] = ()) -> DataFrame:
    """Rows whose closed ranges meet: both sides go to the buckets of `width` that they touch, and a pair counts in its first common one."""
    cut = lambda c: F.floor(F.col(c) / width)
    left = a.withColumn("_k", F.explode(F.sequence(cut(a_lo), cut(a_hi))))
    right = b.withColumn("_k", F.explode(F.sequence(cut(b_lo), cut(b_hi))))
    j = left.join(right, [*by, "_k"]).filter((F.col(a_lo) <= F.col(b_hi)) & (F.col(b_lo) <= F.col(a_hi)))
    return j.filter(F.col("_k") == F.greatest(cut(a_lo), cut(b_lo))).drop("_k")


def theta_join(a: DataFrame, small: DataFrame, condition: Column) -> DataFrame:
    """Any condition against a model-sized side (patterns of a series: as many rows as it has learned)."""
    return a.join(F.broadcast(small), condition)


def shuffle_join(a: DataFrame, b: DataFrame, on: str | list[str], how: str = "inner", hash_: bool = False) -> DataFrame:
    return a.join(b.hint("shuffle_hash" if hash_ else "merge"), on, how)


def semi(a: DataFrame, b: DataFrame, on: str | list[str]) -> DataFrame:
    return a.join(b, on, "left_semi")


def anti(a: DataFrame, b: DataFrame, on: str | list[str]) -> DataFrame:
    return a.join(b, on, "left_anti")


def full_outer(a: DataFrame, b: DataFrame, on: str | list[str]) -> DataFrame:
    return a.join(b, on, "full_outer")


def lateral_topk(a: DataFrame, b: DataFrame, by: str, order: Column, k: int) -> DataFrame:
    """The k first rows of b for each row of a with the same key."""
    tagged = a.withColumn("_row", F.monotonically_increasing_id())
    ranked = tagged.join(b, by).withColumn("_rn", F.row_number().over(Window.partitionBy("_row").orderBy(order)))
    return ranked.filter(F.col("_rn") <= k).drop("_row", "_rn")


def self_exclusion_join(windows: DataFrame, ell: int, block: int = 256) -> DataFrame:
    """Pairs of windows of a series that don't overlap, the earlier as b; by pairs of blocks."""
    w = windows.withColumn("_k", F.floor(F.col("start") / block))
    a = w.select("series_id", F.col("start").alias("a_start"), F.col("xs").alias("a_xs"), F.col("_k").alias("_i"))
    b = w.select("series_id", F.col("start").alias("b_start"), F.col("xs").alias("b_xs"), F.col("_k").alias("_j"))
    return a.join(b, "series_id").filter((F.col("_j") <= F.col("_i")) & (F.col("a_start") - F.col("b_start") >= ell)).drop("_i", "_j")


def agg_stats(df: DataFrame, by: Sequence[str], x: str = "x") -> DataFrame:
    return df.groupBy(*by).agg(F.count(x).alias("n"), F.sum(x).alias("total"), F.avg(x).alias("mean"), F.min(x).alias("low"), F.max(x).alias("high"), F.stddev_pop(x).alias("sd"), F.var_pop(x).alias("variance"), F.skewness(x).alias("skew"), F.kurtosis(x).alias("kurt"))


def quantile(df: DataFrame, by: Sequence[str], x: str, q: float, exact: bool = True) -> DataFrame:
    f = F.percentile(F.col(x), q) if exact else F.percentile_approx(x, q)
    return df.groupBy(*by).agg(f.alias("q"))


def count_distinct(df: DataFrame, by: Sequence[str], x: str, rsd: float | None = None) -> DataFrame:
    return df.groupBy(*by).agg((F.countDistinct(x) if rsd is None else F.approx_count_distinct(x, rsd)).alias("n"))


def rank_suite(df: DataFrame, by: str, order: Column) -> DataFrame:
    w = Window.partitionBy(by).orderBy(order)
    return df.withColumns({"row_number": F.row_number().over(w), "rank": F.rank().over(w), "dense_rank": F.dense_rank().over(w), "percent_rank": F.percent_rank().over(w), "cume_dist": F.cume_dist().over(w), "ntile": F.ntile(4).over(w)})


def rolling(df: DataFrame, column: Column, before: int, after: int, name: str = "v") -> DataFrame:
    return df.withColumn(name, column.over(Window.partitionBy("series_id").orderBy("pos").rowsBetween(-before, after)))


def rolling_range(df: DataFrame, column: Column, order: str, before: int, name: str = "v") -> DataFrame:
    """Frame by distance of positions or seconds instead of rows."""
    return df.withColumn(name, column.over(Window.partitionBy("series_id").orderBy(order).rangeBetween(-before, 0)))


def running(df: DataFrame, column: Column, name: str = "v") -> DataFrame:
    return df.withColumn(name, column.over(Window.partitionBy("series_id").orderBy("pos").rowsBetween(Window.unboundedPreceding, 0)))


def islands(df: DataFrame, flag: str) -> DataFrame:
    """Runs of equal flags: (series_id, island, flag, first_pos, last_pos, n)."""
    w = Window.partitionBy("series_id").orderBy("pos")
    change = F.coalesce((F.lag(flag).over(w) != F.col(flag)).cast("int"), F.lit(0))
    numbered = df.withColumn("_c", change).withColumn("island", F.sum("_c").over(w.rowsBetween(Window.unboundedPreceding, 0)))
    return numbered.groupBy("series_id", "island").agg(F.first(flag).alias(flag), F.min("pos").alias("first_pos"), F.max("pos").alias("last_pos"), F.count(F.lit(1)).alias("n"))


def topk(df: DataFrame, k: int, *order: Column) -> DataFrame:
    return df.orderBy(*order).limit(k)


def topk_per(df: DataFrame, by: str, k: int, *order: Column) -> DataFrame:
    w = Window.partitionBy(by).orderBy(*order)
    return df.withColumn("rank", F.row_number().over(w)).filter(F.col("rank") <= k)


def tumbling(df: DataFrame, ts: str, size: str, column: Column, slide: str | None = None) -> DataFrame:
    w = F.window(F.col(ts).cast("timestamp"), size, slide) if slide else F.window(F.col(ts).cast("timestamp"), size)
    out = df.groupBy(w.alias("w")).agg(F.count(F.lit(1)).alias("n"), column.alias("v"))
    return out.select(F.unix_seconds("w.start").alias("start_s"), "n", "v")


def sessions(df: DataFrame, by: str, ts: str, gap: str) -> DataFrame:
    out = df.groupBy(by, F.session_window(F.col(ts).cast("timestamp"), gap).alias("w")).agg(F.count(F.lit(1)).alias("n"))
    return out.select(by, F.unix_seconds("w.start").alias("start_s"), "n")


def json_props(df: DataFrame) -> DataFrame:
    return df.withColumn("k", F.from_json("props", "k INT")["k"])


def grouping_sets(spark, view: str, sets: str, aggregates: str, where: str = "true") -> DataFrame:  # noqa: ANN001
    columns = sorted({c.strip(" ()") for c in sets.replace("(", "").replace(")", "").split(",") if c.strip(" ()")})
    return spark.sql(f"select {', '.join(columns)}, {aggregates} from {view} where {where} group by grouping sets ({sets})")
