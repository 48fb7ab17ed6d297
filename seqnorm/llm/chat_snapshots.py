"""Chat formatting with cumulative-snapshot collapse.

Logs often hold a conversation again and again as it grows.  A rolling hash of its turns gives every conversation a
number for each of its prefixes; conversations that are a prefix of a longer one, or equal to one with a smaller id,
are removed by anti-joins, and only the maximal ones are rendered.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .common import materialise

BEGIN, MIDDLE, END = "<|", "|>\n", "<|end|>\n"


def prefixes(df: DataFrame, conv: str = "conv_id", turn: str = "turn", role: str = "role", text: str = "text") -> DataFrame:
    """conv, pos (from 1), role, text, and the 128-bit hash (h1, h2) of the turns up to pos.

    A turn's hash holds its place, so the exclusive or of the first n is a hash of that prefix in its order; it runs
    along a window without holding more than a row."""
    rows = df.select(F.col(conv).cast("bigint").alias("conv"), F.col(turn).cast("bigint").alias("turn"), F.col(role).cast("string").alias("role"), F.col(text).cast("string").alias("text"))
    order = Window.partitionBy("conv").orderBy("turn", "role", "text")
    rows = rows.filter("conv is not null").withColumn("pos", F.row_number().over(order))
    running = order.rowsBetween(Window.unboundedPreceding, 0)
    one = F.xxhash64("pos", F.coalesce("role", F.lit("\x00")), F.coalesce("text", F.lit("\x00")))
    two = F.xxhash64(F.lit(77), F.coalesce("text", F.lit("\x00")), F.coalesce("role", F.lit("\x00")), "pos")
    return rows.withColumns({"h1": F.bit_xor(one).over(running), "h2": F.bit_xor(two).over(running)})


def maximal(df: DataFrame, **names) -> DataFrame:
    """conv and n_turns of the conversations that are no prefix of another; of equal ones the smallest id."""
    found = materialise(prefixes(df, **names).select("conv", "pos", "h1", "h2"), "prefixes")
    return _maximal(found)


def _maximal(found: DataFrame) -> DataFrame:
    whole = found.groupBy("conv").agg(F.max_by(F.struct("pos", "h1", "h2"), "pos").alias("w")).select("conv", "w.pos", "w.h1", "w.h2")
    inner = found.join(whole.select("conv", F.col("pos").alias("n")), "conv").filter("pos < n").groupBy("pos", "h1", "h2").agg(F.count(F.lit(1)).alias("_c")).drop("_c")
    once = whole.groupBy("pos", "h1", "h2").agg(F.min("conv").alias("conv"), F.count(F.lit(1)).alias("copies"))
    return once.join(inner, ["pos", "h1", "h2"], "left_anti").select("conv", F.col("pos").alias("n_turns"), "copies")


def render(df: DataFrame, conv: str = "conv_id", turn: str = "turn", role: str = "role", text: str = "text") -> DataFrame:
    """One row for each maximal conversation: conv_id, n_turns, copies (equal conversations, itself included), rendered.

    Turns are put in order of turn number, then role and text.  A null role is "unknown", a null text empty; turns
    without a conversation are left out; repeated turns are turns; an empty table gives an empty result; other columns
    are not read."""
    named = {"conv": conv, "turn": turn, "role": role, "text": text}
    rows = prefixes(df, **named)
    kept = _maximal(materialise(rows.select("conv", "pos", "h1", "h2"), "prefixes"))
    part = F.concat(F.lit(BEGIN), F.coalesce("role", F.lit("unknown")), F.lit(MIDDLE), F.coalesce("text", F.lit("")), F.lit("\n" + END))
    turns = rows.select("conv", F.struct("pos", part.alias("part")).alias("t")).join(kept, "conv")
    out = turns.groupBy("conv", "n_turns", "copies").agg(F.array_sort(F.collect_list("t")).alias("ts"))
    return out.select(F.col("conv").alias(conv), F.col("n_turns").cast("bigint"), F.col("copies").cast("bigint"), F.array_join(F.col("ts.part"), "").alias("rendered"))
