"""Positions, windows, segments and blocks of series."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from seqnorm.session import materialise


def assign_pos(df: DataFrame, key: str, order: str, pos_col: str = "pos") -> DataFrame:
    """Dense positions from 0 within each series."""
    return df.withColumn(pos_col, (F.row_number().over(Window.partitionBy(key).orderBy(order)) - 1).cast("bigint"))


def assign_pos_giant(df: DataFrame, order: str, pos_col: str = "pos", parts: int | None = None) -> DataFrame:
    """Dense positions of one giant series: range partitions, their counts, and positions within partitions.

    Only one count per partition is gathered, so no task sees the whole series."""
    n = parts or int(df.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    # written once: the counts and the positions must see the same ranges, whose bounds are sampled anew in every plan
    ranged = materialise(df.repartitionByRange(n, order).withColumn("_p", F.spark_partition_id()), "ranged")
    counts = ranged.groupBy("_p").agg(F.count(F.lit(1)).alias("_c")).orderBy("_p").collect()  # one row per partition
    offsets, total = [], 0
    for r in counts:
        offsets.append((r[0], total))
        total += r[1]
    base = df.sparkSession.createDataFrame(offsets or [(0, 0)], "_p int, _base bigint")
    within = F.row_number().over(Window.partitionBy("_p").orderBy(order)) - 1
    return ranged.join(F.broadcast(base), "_p").withColumn(pos_col, within + F.col("_base")).drop("_p", "_base")


def ranged(df: DataFrame, by: tuple[str, ...], order: str, parts: int | None = None) -> DataFrame:
    """df in range partitions by its groups and an order, numbered by _p in that order.

    It is written once: sums over partitions and the rows of partitions must see the same ranges, whose bounds are
    sampled anew in every plan."""
    n = parts or int(df.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    return materialise(df.repartitionByRange(n, *by, order).withColumn("_p", F.spark_partition_id()), "ranged")


def prefix_sums(df: DataFrame, by: tuple[str, ...], order: str, values: dict[str, str], parts: int | None = None) -> DataFrame:
    """df with, for each {new: column}, the sum of the column over the rows of its group that come before in the order.

    No task sees a whole group: sums within range partitions, and one row for each partition and group before them.  Rows
    that are equal in the order must not be in one group twice, or which of them comes first is open."""
    rows = ranged(df, by, order, parts)
    sums = rows.groupBy("_p", *by).agg(*(F.sum(c).alias(new) for new, c in values.items()))
    if by:
        earlier = Window.partitionBy(*by).orderBy("_p").rowsBetween(Window.unboundedPreceding, -1)
        base = sums.select(F.col("_p").alias("_q"), *(F.col(c).alias(f"_by_{c}") for c in by), *(F.coalesce(F.sum(new).over(earlier), F.lit(0)).alias(f"_base_{new}") for new in values))
    else:
        run, before = dict.fromkeys(values, 0), []
        for r in sums.orderBy("_p").collect():  # one row per partition
            before.append((r["_p"], *run.values()))
            run = {new: v + (r[new] or 0) for new, v in run.items()}
        kinds = ", ".join(f"_base_{new} {sums.schema[new].dataType.simpleString()}" for new in values)
        base = df.sparkSession.createDataFrame(before, f"_q int, {kinds}")
    on = F.col("_p") == F.col("_q")
    for c in by:
        on = on & F.col(c).eqNullSafe(F.col(f"_by_{c}"))
    within = Window.partitionBy("_p", *by).orderBy(order).rowsBetween(Window.unboundedPreceding, -1)
    out = rows.join(base if by else F.broadcast(base), on, "left")
    out = out.withColumns({new: F.coalesce(F.sum(c).over(within), F.lit(0)) + F.coalesce(F.col(f"_base_{new}"), F.lit(0)) for new, c in values.items()})
    return out.drop("_p", "_q", *(f"_by_{c}" for c in by), *(f"_base_{new}" for new in values))


def regularize(df: DataFrame, ts: str, value: str, every: str = "hour", fill: str = "zero") -> DataFrame:
    """(ts, pos, x): sums per unit of time on the full grid between the first and the last; gaps filled as asked."""
    grid = df.agg(F.date_trunc(every, F.min(ts)).alias("a"), F.date_trunc(every, F.max(ts)).alias("b")).select(F.explode(F.expr(f"sequence(a, b, interval 1 {every})")).alias("ts"))
    sums = df.groupBy(F.date_trunc(every, F.col(ts)).alias("ts")).agg(F.round(F.sum(value), 2).alias("x"))
    seconds = {"hour": 3600, "day": 86400}[every]
    epoch = F.unix_seconds(F.col("ts").cast("timestamp"))
    first = df.agg(F.unix_seconds(F.date_trunc(every, F.min(ts)).cast("timestamp")).alias("t0"))
    out = grid.join(sums, "ts", "left").crossJoin(F.broadcast(first)).withColumn("pos", ((epoch - F.col("t0")) / seconds).cast("bigint")).drop("t0")
    return fill_gaps(out, fill)


def fill_gaps(df: DataFrame, policy: str, x: str = "x", pos: str = "pos") -> DataFrame:
    """Missing values by policy: zero, ffill, linear (ends take the nearest value), or error left to the caller as nulls."""
    if policy == "zero":
        return df.withColumn(x, F.coalesce(F.col(x), F.lit(0.0)))
    if policy not in ("ffill", "linear"):
        return df
    rows = ranged(df.withColumn("_here", F.when(F.col(x).isNotNull(), F.struct(F.col(pos).alias("pos"), F.col(x).alias("x")))), (), pos)
    # the nearest values outside each range partition, from one row per partition
    ends = rows.groupBy("_p").agg(F.min("_here").alias("first"), F.max("_here").alias("last")).orderBy("_p").collect()
    last, following, found = None, None, {}
    for r in ends:
        found[r["_p"]] = [r["_p"], last]
        last = r["last"] or last
    for r in reversed(ends):
        found[r["_p"]].append(following)
        following = r["first"] or following
    at = rows.schema["_here"].dataType.simpleString()
    near = df.sparkSession.createDataFrame([tuple(v) for v in found.values()], f"_p int, _out_before {at}, _out_after {at}")
    span = Window.partitionBy("_p").orderBy(pos)
    before = F.coalesce(F.last("_here", True).over(span.rowsBetween(Window.unboundedPreceding, 0)), F.col("_out_before"))
    after = F.coalesce(F.first("_here", True).over(span.rowsBetween(0, Window.unboundedFollowing)), F.col("_out_after"))
    d = rows.join(F.broadcast(near), "_p").withColumns({"_a": before, "_b": after})
    if policy == "ffill":
        d = d.withColumn(x, F.col("_a.x"))
    else:
        line = F.col("_a.x") + (F.col("_b.x") - F.col("_a.x")) * (F.col(pos) - F.col("_a.pos")) / (F.col("_b.pos") - F.col("_a.pos"))
        d = d.withColumn(x, F.when(F.col(x).isNotNull(), F.col(x)).when(F.col("_a").isNotNull() & F.col("_b").isNotNull(), line).otherwise(F.coalesce("_a.x", "_b.x")))
    return d.select(*df.columns)


def windows(points: DataFrame, ell: int, stride: int = 1) -> DataFrame:
    """(series_id, start, xs) of all full windows; for small series, since every value is held ell times."""
    frame = Window.partitionBy("series_id").orderBy("pos").rowsBetween(0, ell - 1)
    out = points.select("series_id", F.col("pos").alias("start"), F.collect_list("x").over(frame).alias("xs")).filter(F.size("xs") == ell)
    return out if stride == 1 else out.filter(F.col("start") % stride == 0)


def window_stats(points: DataFrame, ell: int) -> DataFrame:
    """(series_id, start, mean, sd, energy) of all full windows by sliding aggregates."""
    frame = Window.partitionBy("series_id").orderBy("pos").rowsBetween(0, ell - 1)
    x = F.col("x")
    cols = [F.avg(x).over(frame).alias("mean"), F.stddev_pop(x).over(frame).alias("sd"), F.sum(x * x).over(frame).alias("energy"), F.count(x).over(frame).alias("_n")]
    return points.select("series_id", F.col("pos").alias("start"), *cols).filter(F.col("_n") == ell).drop("_n")


def segments(points: DataFrame, ell_m: int, offset: int = 0, align: str = "none") -> DataFrame:
    """(series_id, seg, start, xs): pieces at multiples of ell_m, incomplete ones left out.

    align 'peak' rotates each piece so that its largest value comes first; 'phase' starts the pieces at the series'
    first largest value within the first piece."""
    pts = points
    if align == "phase":
        first = points.filter(F.col("pos") < ell_m).groupBy("series_id").agg(F.max_by("pos", F.struct("x", -F.col("pos"))).alias("_shift"))
        pts = points.join(first, "series_id").withColumn("pos", F.col("pos") - F.col("_shift")).filter("pos >= 0").drop("_shift")
    at = F.floor((F.col("pos") - offset) / ell_m)
    ordered = F.array_sort(F.collect_list(F.struct("pos", "x")))
    out = pts.filter(F.col("pos") >= offset).groupBy("series_id", at.cast("int").alias("seg")).agg(ordered.alias("ps"))
    out = out.filter(F.size("ps") == ell_m).select("series_id", "seg", (F.col("seg") * ell_m + offset).cast("bigint").alias("start"), F.transform("ps", lambda p: p["x"]).alias("xs"))
    if align == "peak":
        peak = F.array_position("xs", F.array_max("xs")).cast("int")
        out = out.withColumn("xs", F.concat(F.slice("xs", peak, ell_m), F.slice("xs", F.lit(1), peak - 1)))
    return out


def block_rows(points: DataFrame, block: int, before: int, after: int) -> DataFrame:
    """points with block_id, each point also in the blocks whose halo it lies in."""
    pos = F.col("pos")
    lo, hi = F.floor((pos - after) / block), F.floor((pos + before) / block)
    out = points.select("series_id", "pos", "x", F.explode(F.sequence(F.greatest(lo, F.lit(0)), hi)).alias("block_id"))
    return out.withColumn("block_id", F.col("block_id").cast("bigint"))


def blocks(points: DataFrame, block: int, halo: int) -> DataFrame:
    """(series_id, block_id, start_pos, xs): runs of `block` points and `halo` points that follow."""
    rows = block_rows(points, block, 0, halo)
    ordered = F.array_sort(F.collect_list(F.struct("pos", "x")))
    out = rows.groupBy("series_id", "block_id").agg(F.min("pos").alias("start_pos"), ordered.alias("ps"))
    return out.filter(F.col("start_pos") <= F.col("block_id") * block + block - 1).select("series_id", "block_id", "start_pos", F.transform("ps", lambda p: p["x"]).alias("xs"))


def centred_norms(windows_: DataFrame) -> Column:
    from seqnorm.functions.distance import centred

    c = centred(F.col("xs"))
    return F.sqrt(F.aggregate(c, F.lit(0.0), lambda s, v: s + v * v))
