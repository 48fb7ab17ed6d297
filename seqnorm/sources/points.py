"""Series from the given tables and from files, all as points (series_id, pos, x)."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F
from pyspark.sql.types import StructType

from seqnorm.operators import segment


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def read_points(spark: SparkSession, path: str, key: str | Column | None, order: str, value: str, where: str | None = None) -> DataFrame:
    """Points of a Parquet file; the filter and the three columns reach the scan."""
    df = spark.read.parquet(path)
    if where:
        df = df.filter(where)
    k = F.lit("all") if key is None else (F.col(key) if isinstance(key, str) else key)
    return segment.assign_pos(df.select(k.cast("string").alias("series_id"), F.col(order).alias("_o"), F.col(value).cast("double").alias("x")), "series_id", "_o").select("series_id", "pos", "x")


def read_files(spark: SparkSession, path: str, kind: str, schema: StructType | str, **options) -> DataFrame:
    """CSV, JSON lines or ORC with an explicit schema."""
    return spark.read.schema(schema).format(kind).options(**options).load(path)


def read_stream(spark: SparkSession, folder: str, glob: str, schema: StructType | str) -> DataFrame:
    """A file stream; zone-less timestamps become timestamps, as watermarks ask."""
    df = spark.readStream.schema(schema).option("pathGlobFilter", glob).parquet(folder)
    return df.withColumns({f.name: F.col(f.name).cast("timestamp") for f in df.schema if f.dataType.typeName() == "timestamp_ntz"})


def cast_ntz(df: DataFrame, col: str) -> DataFrame:
    return df.withColumn(col, F.col(col).cast("timestamp"))


def events(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All events as one series; the id is dense already, so no position has to be made."""
    return table(spark, sf_dir, "events").select(F.lit("events").alias("series_id"), F.col("event_id").alias("pos"), F.col("value").alias("x"))


def hourly(spark: SparkSession, sf_dir: str, fill: str = "zero") -> DataFrame:
    df = segment.regularize(table(spark, sf_dir, "events"), "ts", "value", "hour", fill)
    return df.select(F.lit("hourly").alias("series_id"), "pos", "x")


def daily(spark: SparkSession, sf_dir: str, name: str, ts: str, value: str, fill: str = "zero") -> DataFrame:
    df = segment.regularize(table(spark, sf_dir, name), ts, value, "day", fill)
    return df.select(F.lit(f"daily_{name}").alias("series_id"), "pos", "x")


def daily_lineitem(spark: SparkSession, sf_dir: str) -> DataFrame:
    return daily(spark, sf_dir, "lineitem", "l_shipdate", "l_extendedprice")


def daily_orders(spark: SparkSession, sf_dir: str) -> DataFrame:
    return daily(spark, sf_dir, "orders", "o_orderdate", "o_totalprice")


def _keyed(df: DataFrame, key: Column, order: list[str], value: Column) -> DataFrame:
    spec = Window.partitionBy("series_id").orderBy(*order)
    out = df.withColumn("series_id", key.cast("string"))
    return out.select("series_id", (F.row_number().over(spec) - 1).cast("bigint").alias("pos"), value.cast("double").alias("x"))


def by_type(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _keyed(table(spark, sf_dir, "events"), F.col("event_type"), ["event_id"], F.col("value"))


def by_user(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _keyed(table(spark, sf_dir, "events"), F.col("user_id"), ["event_id"], F.col("value"))


def doc_lengths(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _keyed(table(spark, sf_dir, "documents"), F.lit("documents"), ["doc_id"], F.col("n_chars"))


def page_lengths(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _keyed(table(spark, sf_dir, "pages"), F.lit("pages"), ["page_id"], F.length("html"))


def turn_lengths(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _keyed(table(spark, sf_dir, "conversations"), F.col("conv_id"), ["turn"], F.length("text"))


def vectors(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Embeddings as windows (series_id, start, xs)."""
    e = table(spark, sf_dir, "embeddings")
    return e.select(F.lit("embeddings").alias("series_id"), F.col("vec_id").alias("start"), F.transform("embedding", lambda v: v.cast("double")).alias("xs"))
