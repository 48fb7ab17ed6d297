"""Shared pieces of the training-data operators."""

from __future__ import annotations

from collections.abc import Callable

import uuid

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from seqnorm.session import checkpoint, materialise, scratch, shared_dir, ship

__all__ = ["checkpoint", "fresh", "hold", "join_split", "materialise", "scratch", "shared_dir", "ship", "table"]

#: A key with more rows than HOT_ROWS, and than all rows over HOT_KEYS, is split; so there are fewer than HOT_KEYS of them.
HOT_ROWS, HOT_KEYS = 1000, 50_000


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def fresh(label: str) -> str:
    """A column name that no table has."""
    return f"{label}_{uuid.uuid4().hex}"


def join_split(rows: DataFrame, side: DataFrame, on: list[str], counts: DataFrame, by: Column, how: str = "inner") -> DataFrame:
    """rows joined with side on keys that aren't null, where a key with very many rows is met by copies of its side in as many parts.

    counts (on, n) tells how many of `rows` a key has; keys that it leaves out count as few.  `by` deals a key's rows
    over the parts.  Only the list of hot keys is broadcast, of fewer than HOT_KEYS rows; side grows by fewer than
    that too when it has one row for a key."""
    part, parts = fresh("part"), fresh("parts")
    total = counts.agg(F.sum("n")).first()[0] or 0
    bar = max(HOT_ROWS, total // HOT_KEYS)
    hot = counts.filter(F.col("n") > bar).select(*on, F.ceil(F.col("n") / bar).cast("int").alias(parts))
    if hot.isEmpty():
        return rows.join(side, on, how)
    hot = F.broadcast(hot)
    dealt = rows.join(hot, on, "left").withColumn(part, F.coalesce(F.pmod(by, F.col(parts)).cast("int"), F.lit(0))).drop(parts)
    copies = side.join(hot, on, "left").withColumn(part, F.explode(F.sequence(F.lit(0), F.coalesce(F.col(parts), F.lit(1)) - 1))).drop(parts)
    return dealt.join(copies, [*on, part], how).drop(part)


_HELD: dict[str, Callable[[], object]] = {}


def hold(owner: str, release: Callable[[], object] = bool) -> None:
    """Called by a kernel in a worker before it fills caches that outlive its task: those of other kernels are let go.

    Workers serve one stage after another, and without this the caches of all would add up."""
    others = [name for name in _HELD if name != owner]
    for name in others:
        _HELD.pop(name)()
    if others:
        import pyarrow as pa

        pa.default_memory_pool().release_unused()
    _HELD[owner] = release
