"""Quality rules in a short-circuit cascade.

A sample of rows is put through every rule, which gives each rule's cost and the share that it rejects.  Rules run in
the order of rejections per cost, and a row that a rule rejects never meets the later, dearer ones.  The order changes
cost only: a row is kept if no rule rejects it.
"""

from __future__ import annotations

import re
import time
from collections.abc import Callable, Iterator
from dataclasses import dataclass
from functools import cached_property

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import hold, ship

WINDOW = 8
SAMPLE_ROWS = 500

_SPACES = re.compile(r"[^\x20\x09-\x0D]+")
_SYMBOLS = re.compile(r"[#*$%&|<>]")
_MIX = np.uint64(0x9E3779B97F4A7C15)
_ADD = np.uint64(1)


class Text:
    """A text and, when first asked for, its measures."""

    def __init__(self, text: str | None):
        self.text = text or ""

    @cached_property
    def words(self) -> list[str]:
        return _SPACES.findall(self.text)

    @cached_property
    def n_words(self) -> int:
        return len(self.words)

    @cached_property
    def word_chars(self) -> int:
        return sum(map(len, self.words))

    @cached_property
    def n_symbols(self) -> int:
        return len(_SYMBOLS.findall(self.text))

    @cached_property
    def n_dup_lines(self) -> int:
        lines = [x for x in self.text.split("\n") if _SPACES.search(x)]
        return len(lines) - len(set(lines))

    @cached_property
    def n_repeat_words(self) -> int:
        """Words inside windows of eight words that stand twice or more in the text."""
        n = self.n_words - WINDOW + 1
        if n < 2:
            return 0
        numbers: dict[str, int] = {}
        ids = np.fromiter((numbers.setdefault(w, len(numbers)) for w in self.words), np.int64, self.n_words)
        # windows get equal ranks if and only if they are equal: ranks of 2, then 4, then 8 words
        rank, span = ids, 1
        while span < WINDOW:
            pairs = rank[:-span] * (int(rank.max()) + 1) + rank[span:]
            distinct, rank = np.unique(pairs, return_inverse=True)
            span *= 2
            if len(distinct) == len(pairs):
                return 0
        often = np.bincount(rank)[rank] > 1
        edge = np.zeros(self.n_words + 1, np.int64)
        starts = np.flatnonzero(often)
        edge[starts] += 1
        edge[starts + WINDOW] -= 1
        return int((np.cumsum(edge[:-1]) > 0).sum())

    @cached_property
    def few_words(self) -> bool:
        return self.n_words < 20

    @cached_property
    def repeats(self) -> bool:
        return 100 * self.n_repeat_words > 30 * self.n_words


@dataclass(frozen=True)
class Rule:
    """rejects(Text) is true for a text to leave out."""

    name: str
    rejects: Callable[[Text], bool]
    base: bool = False


def _few_words(t: Text) -> bool:
    return t.few_words


def _repeats(t: Text) -> bool:
    return t.repeats


def _symbols(t: Text) -> bool:
    return t.n_symbols > 0.25 * t.n_words


def _dup_lines(t: Text) -> bool:
    return t.n_dup_lines > 0.5 * (t.text.count("\n") + 1)


def _word_length(t: Text) -> bool:
    return not 2 * t.n_words <= t.word_chars <= 20 * t.n_words


def _shouting(t: Text) -> bool:
    return t.text.isupper()


def _stutter(t: Text) -> bool:
    return sum(map(str.__eq__, t.words, t.words[1:])) > 0.4 * t.n_words


RULES = (
    Rule("few_words", _few_words, True),
    Rule("repeated_words", _repeats, True),
    Rule("symbols", _symbols),
    Rule("repeated_lines", _dup_lines),
    Rule("word_length", _word_length),
    Rule("shouting", _shouting),
    Rule("stutter", _stutter),
)


@dataclass(frozen=True)
class Estimate:
    rule: Rule
    cost: float
    rejected: float

    @property
    def worth(self) -> float:
        return self.rejected / self.cost


def estimate(texts: list[str | None], rules: tuple[Rule, ...] = RULES) -> list[Estimate]:
    """Seconds per text and share of rejected texts of each rule, on a sample, the measures computed afresh for each."""
    out = []
    for rule in rules:
        began = time.perf_counter()
        rejected = sum(rule.rejects(Text(t)) for t in texts)
        spent = time.perf_counter() - began
        n = max(1, len(texts))
        out.append(Estimate(rule, max(spent, 1e-9) / n, (rejected + 0.5) / (n + 1)))
    return out


def plan(df: DataFrame, rules: tuple[Rule, ...] = RULES, sample_rows: int = SAMPLE_ROWS, key: str = "doc_id", text: str = "text") -> tuple[Rule, ...]:
    """The rules by rejections per cost on `sample_rows` rows, those with the smallest hashes of their key.

    The ids are chosen first, from the key column alone; only their texts come to the driver."""
    if not sample_rows:
        return rules
    keys = df.select(F.col(key).cast("bigint").alias("_k")).filter("_k is not null").distinct()
    ids = [r[0] for r in keys.orderBy(F.xxhash64("_k"), "_k").limit(sample_rows).collect()]
    texts = [r[0] for r in df.filter(F.col(key).isin(ids)).select(F.col(text).cast("string")).limit(2 * sample_rows).collect()] if ids else []
    return tuple(e.rule for e in sorted(estimate(texts, rules), key=lambda e: -e.worth))


SCHEMA = "key bigint, n_words bigint, word_chars bigint, n_symbols bigint, n_dup_lines bigint, n_repeat_words bigint, base_failed boolean, kept boolean"


def judge(df: DataFrame, rules: tuple[Rule, ...] | None = None, key: str = "doc_id", text: str = "text", sample_rows: int = SAMPLE_ROWS) -> DataFrame:
    """The cascade's verdict on each row together with all measures.

    A null or empty text has no words and fails; repeated rows are judged alike, each for itself; an empty table gives
    an empty result; other columns are not read.  One narrow pass."""
    ship(df.sparkSession)
    order = rules if rules is not None else plan(df, RULES, sample_rows, key, text)
    rows = df.select(F.col(key).cast("bigint").alias("key"), F.col(text).cast("string").alias("text"))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            hold("rules")
            columns: list[list] = [[] for _ in range(7)]
            for value in batch.column(1):
                t = Text(value.as_py())
                kept = not any(rule.rejects(t) for rule in order)
                for c, v in zip(columns, (t.n_words, t.word_chars, t.n_symbols, t.n_dup_lines, t.n_repeat_words, t.few_words or t.repeats, kept)):
                    c.append(v)
            kinds = [pa.int64()] * 5 + [pa.bool_()] * 2
            yield pa.RecordBatch.from_arrays([batch.column(0), *(pa.array(c, k) for c, k in zip(columns, kinds))], names=["key", "n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "base_failed", "kept"])

    return rows.mapInArrow(run, SCHEMA).withColumnRenamed("key", key)


def keep_good(df: DataFrame, rules: tuple[Rule, ...] | None = None, key: str = "doc_id", text: str = "text", sample_rows: int = SAMPLE_ROWS) -> DataFrame:
    """The rows of df that no rule rejects, with all their columns; a row's cascade ends at its first rejection.

    Whole batches pass through one narrow stage, so clashing names and repeated rows need no join."""
    ship(df.sparkSession)
    order = rules if rules is not None else plan(df, RULES, sample_rows, key, text)
    at = df.columns.index(text)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            hold("rules")
            mask = []
            for value in batch.column(at):
                t = Text(None if not value.is_valid else str(value.as_py()))
                mask.append(not any(rule.rejects(t) for rule in order))
            yield batch.filter(pa.array(mask, pa.bool_()))

    return df.mapInArrow(run, df.schema)
