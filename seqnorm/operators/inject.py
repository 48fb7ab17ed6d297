"""Carriers and injectors: series with known truth, made from closed forms, the noise of the given tables, and overlays.

All randomness is u(key, salt), a number in [0, 1) from an MD5 digest, which any engine computes alike.
A carrier is (series_id, pos, x, base, noise, concept, in_transition, y_true)."""

from __future__ import annotations

import math
from collections.abc import Sequence

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from seqnorm.sources.points import table

#: Weights of the harmonics 1, 2, 3, ... of each concept's period.
CONCEPTS: dict[str, tuple[float, ...]] = {
    "A": (1.0, 0.5),
    "B": (1.0, 0.0, 0.5),
    "C": (0.4, 1.0),
    "D": (0.7, 0.0, 0.0, 0.7),
    "E": (0.2, 0.3, 1.0),
    "G": (1.0, -0.6, 0.3),
}
PERIOD = 50


def u(key: Column, salt: str | int) -> Column:
    """Uniform in [0, 1): 52 bits of md5(key:salt)."""
    digest = F.md5(F.concat(key.cast("string"), F.lit(f":{salt}")))
    return F.conv(F.substring(digest, 1, 13), 16, 10).cast("double") / float(1 << 52)


def normal(key: Column, salt: str | int) -> Column:
    """Standard normal from two uniforms."""
    a, b = F.greatest(u(key, f"{salt}a"), F.lit(1e-12)), u(key, f"{salt}b")
    return F.sqrt(-2 * F.log(a)) * F.cos(2 * math.pi * b)


def shape(concept: Column, pos: Column, period: int = PERIOD, names: Sequence[str] = tuple("ABCD")) -> Column:
    """The closed form of a numbered concept at a position."""
    theta = 2 * math.pi * (pos % period) / period
    out = F.lit(0.0)
    for i, name in reversed(list(enumerate(names))):
        wave = F.lit(0.0)
        for h, w in enumerate(CONCEPTS[name], 1):
            if w:
                wave = wave + w * F.sin(h * theta)
        out = F.when(concept == i, wave).otherwise(out)
    return out


def spine(spark, sf_dir: str, by_type: bool = False) -> DataFrame:  # noqa: ANN001
    """(series_id, pos, noise) from events: noise is the value's deviation from its mean of about 50, in that mean."""
    from pyspark.sql import Window

    e = table(spark, sf_dir, "events")
    noise = ((F.col("value") - 50.0) / 50.0).alias("noise")
    if not by_type:
        return e.select(F.lit("carrier").alias("series_id"), F.col("event_id").alias("pos"), noise)
    at = (F.row_number().over(Window.partitionBy("event_type").orderBy("event_id")) - 1).cast("bigint")
    return e.select(F.col("event_type").alias("series_id"), at.alias("pos"), noise)


def build(spine_: DataFrame, concept: Column, sigma: float = 0.05, period: int = PERIOD, names: Sequence[str] = tuple("ABCD"), transition: Column | None = None) -> DataFrame:
    c = spine_.withColumn("concept", concept.cast("int")).withColumn("in_transition", transition if transition is not None else F.lit(False))
    base = shape(F.col("concept"), F.col("pos"), period, names)
    return c.withColumn("base", base).withColumn("x", F.col("base") + sigma * F.col("noise")).withColumn("y_true", F.lit(0).cast("tinyint"))


# -- schedules of concepts ---------------------------------------------------------------------------


def cuts(n: int, n_d: int, seed: int, ell: int = PERIOD) -> list[int]:
    """n_d distinct cut positions at multiples of ell, never in the first fifth, by the digests of their numbers."""
    import hashlib

    at = lambda i: int(hashlib.md5(f"{i}:cut{seed}".encode()).hexdigest()[:13], 16)
    first, last = math.ceil(0.2 * n / ell), n // ell - 1
    return sorted(i * ell for i in sorted(range(first, max(first, last)), key=at)[:n_d])


def abrupt(positions: Sequence[int], concepts: int, pos: Column | None = None) -> Column:
    """Concept by pieces between cuts; the pieces take the concepts in turn."""
    pos = F.col("pos") if pos is None else pos
    piece = F.lit(0)
    for p in positions:
        piece = piece + F.when(pos >= p, 1).otherwise(0)
    return piece % concepts


def gradual(positions: Sequence[int], width: float, concepts: int, seed: int) -> tuple[Column, Column]:
    """(concept, in transition): within `width` around a cut the later concept is drawn with logistic odds."""
    pos = F.col("pos").cast("double")
    piece, inside = F.lit(0), F.lit(False)
    draw = u(F.col("pos"), f"gradual{seed}")
    for p in positions:
        near = F.abs(pos - p) <= width / 2
        odds = 1.0 / (1.0 + F.exp(-4.0 * (pos - p) / width))
        piece = piece + F.when(near, (draw < odds).cast("int")).otherwise((pos >= p).cast("int"))
        inside = inside | near
    return piece % concepts, inside


def recurring(chunk: int, concepts: int = 2) -> Column:
    return F.pmod(F.floor(F.col("pos") / chunk), F.lit(concepts))


def ratio(n: int, a: int, b: int) -> Column:
    return F.when(F.col("pos") < n * a / (a + b), 0).otherwise(1)


def alternate(b_periods: int, a_periods: int = 10, period: int = PERIOD) -> Column:
    return F.when(F.col("pos") % ((a_periods + b_periods) * period) < a_periods * period, 0).otherwise(1)


# -- anomalies ---------------------------------------------------------------------------------------


def window_id(ell: int = PERIOD) -> Column:
    return F.floor(F.col("pos") / ell)


def _key(ell: int) -> Column:
    return F.concat(F.col("series_id"), F.lit("/"), window_id(ell).cast("string"))


def _apply(df: DataFrame, hit: Column, value: Column) -> DataFrame:
    return df.withColumn("_hit", hit).withColumn("x", F.when(F.col("_hit"), value).otherwise(F.col("x"))).withColumn("y_true", F.when(F.col("_hit"), 1).otherwise(F.col("y_true")).cast("tinyint")).drop("_hit")


def scale(df: DataFrame, share: float, lo: float = 1.5, hi: float = 3.0, ell: int = PERIOD, seed: int = 1, where: Column | None = None) -> DataFrame:
    """Windows drawn with probability `share`, times a factor uniform in [lo, hi]."""
    hit = u(_key(ell), f"hit{seed}") < share
    factor = lo + (hi - lo) * u(_key(ell), f"factor{seed}")
    return _apply(df, hit if where is None else hit & where, F.col("x") * factor)


def scaled_normal(df: DataFrame, s: float, sd: float = 0.1, share: float = 0.1, ell: int = PERIOD, seed: int = 1) -> DataFrame:
    """Windows times a factor drawn from N(s, sd)."""
    return _apply(df, u(_key(ell), f"hit{seed}") < share, F.col("x") * (s + sd * normal(_key(ell), f"factor{seed}")))


def lookalike(df: DataFrame, share: float, src: int = 0, dst: int = 1, mu: float = 1.0, sd: float = 0.1, ell: int = PERIOD, seed: int = 1, sigma: float = 0.05, names: Sequence[str] = tuple("ABCD")) -> DataFrame:
    """Windows of concept dst get the shape of concept src at the same phase, times a factor from N(mu, sd)."""
    other = shape(F.lit(src), F.col("pos"), ell, names) * (mu + sd * normal(_key(ell), f"like{seed}")) + sigma * F.col("noise")
    return _apply(df, (F.col("concept") == dst) & (u(_key(ell), f"hit{seed}") < share), other)


def place(df: DataFrame, law: str, share: float, n: int, lo: float = 1.5, hi: float = 3.0, ell: int = PERIOD, seed: int = 1) -> DataFrame:
    """Scale anomalies whose windows are placed in time by a law: uniform, gauss, rayleigh, invrayleigh.

    Draws are turned into window numbers; the first distinct windows of a long enough row of draws are taken."""
    total = max(1, n // ell)
    wanted = max(1, round(share * total))
    draws = df.sparkSession.range(6 * total).withColumn("q", F.greatest(u(F.col("id"), f"place{seed}"), F.lit(1e-9)))
    q = F.col("q")
    at = {
        "uniform": q,
        "gauss": 0.5 + 0.18 * normal(F.col("id"), f"place{seed}"),
        "rayleigh": 0.3 * F.sqrt(-2 * F.log(q)),
        "invrayleigh": 0.3 / F.sqrt(-2 * F.log(q)),
    }[law]
    w = draws.withColumn("w", F.floor(at * total)).filter((F.col("w") >= 0) & (F.col("w") < total))
    chosen = w.groupBy("w").agg(F.min("id").alias("id")).orderBy("id").limit(wanted).select(F.col("w").alias("_w"), F.lit(True).alias("_chosen"))
    joined = df.join(F.broadcast(chosen), window_id(ell) == F.col("_w"), "left")  # at most one row for each window of one series
    factor = lo + (hi - lo) * u(_key(ell), f"factor{seed}")
    return _apply(joined, F.coalesce("_chosen", F.lit(False)), F.col("x") * factor).drop("_w", "_chosen")
