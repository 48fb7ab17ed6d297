"""Mixing sources to target weights: temperature, limits, and budgeted block permutations.

Shares of tokens are raised to an exponent and normalised.  The exponent is bisected so that the weights have a target
entropy, and raised further if a source would be repeated more often than allowed.  Weights become token budgets.
Each source is a sequence of permuted blocks of documents, with a fresh permutation for every pass; a source gives its
first documents in that order until its budget is used, in whole passes and one last partial pass.
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from .common import fresh, materialise

BLOCKS = 1024
STEPS, WAYS = 5, 32


@dataclass(frozen=True)
class Target:
    """entropy: share of the largest possible entropy that the weights should have, at least (None: keep `exponent`).
    max_repeats: how often a source may be passed over.  budget: tokens of the mixture; None: `part` of all there are.
    A budget that max_repeats does not allow at any exponent is lowered to what it allows."""

    entropy: float | None = 0.97
    exponent: float = 0.7
    max_repeats: float = 4.0
    budget: int | None = None
    part: float = 1.0
    seed: int = 11


def token_count(text: Column) -> Column:
    """Words of a text, at least 1, so that every document costs something."""
    return F.greatest(F.lit(1), F.regexp_count(F.coalesce(text, F.lit("")), F.lit(r"[^\x20\x09-\x0D]+"))).cast("bigint")


def _at_exponents(shares: DataFrame, exponents: list[float]) -> list[tuple[float, float]]:
    """(entropy, largest weight over share) at each exponent, in one aggregation over the sources."""
    power = lambda a: F.pow("share", F.lit(a))
    cells = []
    for i, a in enumerate(exponents):
        cells += [F.sum(power(a)).alias(f"z{i}"), F.sum(power(a) * F.log(power(a))).alias(f"h{i}"), F.max(power(a) / F.col("share")).alias(f"r{i}")]
    row = shares.agg(*cells).first()
    import math

    return [(math.log(row[f"z{i}"]) - row[f"h{i}"] / row[f"z{i}"], row[f"r{i}"] / row[f"z{i}"]) for i in range(len(exponents))]


def _bisect(shares: DataFrame, good: "callable") -> float:
    """The largest exponent in [0, 1] up to which good(entropy, repeats) holds, by cutting the range in WAYS parts a step."""
    low, high = 0.0, 1.0
    for _ in range(STEPS):
        cuts = [low + (high - low) * i / WAYS for i in range(WAYS + 1)]
        ok = [good(*x) for x in _at_exponents(shares, cuts)]
        last = max((i for i in range(WAYS + 1) if all(ok[: i + 1])), default=0)
        low, high = cuts[last], cuts[min(last + 1, WAYS)]
        if low == high:
            break
    return low


def weights(tokens: DataFrame, target: Target = Target()) -> DataFrame:
    """tokens (source, tokens) with share, weight and repeats (budget over tokens), and the exponent used.

    Sources stay a table: only sums come to the driver."""
    import math

    total, n = tokens.agg(F.sum("tokens"), F.count(F.lit(1))).first()
    shares = materialise(tokens.filter("tokens > 0").withColumn("share", F.col("tokens") / F.lit(float(total or 1))), "shares")
    if not n:
        return shares.withColumns({"exponent": F.lit(1.0), "weight": F.col("share"), "repeats": F.lit(0.0)})
    exponent = target.exponent
    if target.entropy is not None:
        wanted = target.entropy * math.log(n)
        exponent = _bisect(shares, lambda h, _: h >= wanted - 1e-12)
    budget = target.budget or total * target.part
    over = budget / total
    if over * _at_exponents(shares, [exponent])[0][1] > target.max_repeats:
        # repeats fall as the exponent rises: look for the largest 1 - exponent that is allowed
        flipped = lambda cuts: _at_exponents(shares, [1 - c for c in cuts])
        low, high = 0.0, 1 - exponent
        for _ in range(STEPS):
            cuts = [low + (high - low) * i / WAYS for i in range(WAYS + 1)]
            fine = [over * r <= target.max_repeats for _, r in flipped(cuts)]
            last = max((i for i in range(WAYS + 1) if all(fine[: i + 1])), default=0)
            low, high = cuts[last], cuts[min(last + 1, WAYS)]
        exponent = 1 - low
        worst = over * _at_exponents(shares, [exponent])[0][1]
        budget = budget * min(1.0, target.max_repeats / worst)
    z = shares.agg(F.sum(F.pow("share", F.lit(exponent)))).first()[0]
    out = shares.withColumn("exponent", F.lit(exponent)).withColumn("weight", F.pow("share", F.lit(exponent)) / F.lit(z))
    repeats = F.col("weight") * F.lit(float(budget)) / F.col("tokens")
    return out.withColumn("repeats", F.least(repeats, F.lit(float(target.max_repeats))))


def mixture(df: DataFrame, target: Target = Target(), key: str = "doc_id", source: str = "source", text: str = "text", blocks: int = BLOCKS) -> DataFrame:
    """One row for each use of a document: key, source, tokens, pass_no (from 0), block, at, weight, exponent.

    `at` in [0, 1) orders the mixture: sorted by it, every prefix holds the sources in their weights.  A null source is
    a source of its own; a null text counts one token; a null key stays null; repeated rows are documents each; an
    empty table gives an empty result; other columns are not read.  Blocks are summed before they are shuffled and a
    source's running totals go over its blocks, so a source with most of the rows is no heavier than others; documents
    are ranked within their block only."""
    rows = df.select(F.col(key).cast("bigint").alias("key"), F.coalesce(F.col(source).cast("string"), F.lit("\x00null")).alias("source"), token_count(F.col(text).cast("string")).alias("tokens"))
    rows = rows.withColumn("row", F.when(F.col("key").isNull(), F.monotonically_increasing_id()))  # written once, so it stays
    rows = materialise(rows, "mix-rows")
    table = weights(rows.groupBy("source").agg(F.sum("tokens").alias("tokens")), target).select("source", "weight", "exponent", "repeats", F.col("tokens").alias("held"))
    table = materialise(table, "mix-weights")
    passes = F.sequence(F.lit(0), F.greatest(F.lit(0), F.ceil("repeats").cast("int") - 1))
    per_pass = table.select("*", F.explode(passes).alias("pass_no"))
    part = F.least(F.lit(1.0), F.col("repeats") - F.col("pass_no"))

    place = lambda *more: F.xxhash64(F.lit(target.seed), *more)
    rows = rows.withColumn("block", F.pmod(place(F.lit("block"), F.col("key"), F.col("tokens"), F.col("row")), F.lit(blocks)).cast("int"))
    sums = rows.groupBy("source", "block").agg(F.sum("tokens").alias("block_tokens"))
    order = Window.partitionBy("source", "pass_no").orderBy(place(F.lit("order"), F.col("source"), F.col("block"), F.col("pass_no")), "block")
    plan = sums.join(per_pass, "source").withColumn("before", F.sum("block_tokens").over(order.rowsBetween(Window.unboundedPreceding, -1)))
    plan = plan.withColumns({"before": F.coalesce("before", F.lit(0)), "limit": F.round(part * F.col("held")).cast("bigint")}).filter(F.col("before") < F.col("limit"))
    plan = plan.select("source", "block", "pass_no", "before", "limit", "block_tokens", "held", "repeats", "weight", "exponent")

    inside = Window.partitionBy("source", "block", "pass_no").orderBy(place(F.lit("inside"), F.col("key"), F.col("row"), F.col("pass_no")), "key", "tokens")
    used = rows.join(plan, ["source", "block"]).withColumn("earlier", F.coalesce(F.sum("tokens").over(inside.rowsBetween(Window.unboundedPreceding, -1)), F.lit(0)))
    used = used.filter(F.col("before") + F.col("earlier") < F.col("limit"))
    at = (F.col("pass_no") * F.col("held") + F.col("before") + F.col("earlier")) / (F.col("repeats") * F.col("held"))
    return used.select(F.col("key").alias(key), F.when(F.col("source") != "\x00null", F.col("source")).alias("source"), "tokens", F.col("pass_no").cast("int"), "block", at.alias("at"), "weight", "exponent")


def mixed(df: DataFrame, target: Target, key: str = "doc_id", source: str = "source", text: str = "text") -> DataFrame:
    """The rows of df that the mixture uses, each as often as it is used.

    Rows with a null key have nothing to be told apart by and stay as they are; repeated rows share their key's uses, and which of them are used is up to a hash of
    their texts.  All columns stay, by any name."""
    name, uses, at, of = (fresh(x) for x in ("used", "uses", "at", "of"))
    keyed = df.filter(F.col(key).isNotNull())
    found = mixture(keyed, target, key, source, text).groupBy(F.col(key).alias(name)).agg(F.count(F.lit(1)).cast("int").alias(uses))
    rest = df.filter(F.col(key).isNull())
    again = lambda n: F.explode(F.sequence(F.lit(1), n))
    columns = [f"`{c}`" for c in df.columns]
    if keyed.groupBy(key).agg(F.count(F.lit(1)).alias("c")).filter("c > 1").isEmpty():
        out = keyed.join(found, F.col(key) == F.col(name))
        return out.withColumn(at, again(F.col(uses))).select(*columns).unionByName(rest)
    rank = F.row_number().over(Window.partitionBy(key).orderBy(F.xxhash64(text)))
    every = F.count(F.lit(1)).over(Window.partitionBy(key))
    out = keyed.withColumns({at: rank, of: every}).join(found, F.col(key) == F.col(name))
    share = F.floor(F.col(uses) / F.col(of)).cast("int") + (F.col(at) <= F.col(uses) % F.col(of)).cast("int")
    return out.withColumn(uses, share).filter(F.col(uses) > 0).withColumn(at, again(F.col(uses))).select(*columns).unionByName(rest)
