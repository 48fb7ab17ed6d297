"""Bulk-synchronous best-fit packing of documents into sequences of a fixed length.

Documents become pieces of at most `capacity` tokens.  Pieces of one length are interchangeable, so the sorted pieces
and the sorted gaps are kept as runs: (length, count) and (gap, consecutive sequences).  Both sides have at most
`capacity` distinct sizes whatever the number of documents.  A round sweeps the sizes downwards: every length claims
the smallest gaps that hold it (its successors), a gap takes one piece a round, and ranks decide who gets it when
there are fewer gaps than pieces.  Gaps are then updated and the next round begins; pieces that found no gap open just
as many sequences as their tokens need at least.  The rounds give a plan of rank intervals, and each piece looks its
place up by its rank within its length, which comes from counts per task and not from a sort on one machine.
"""

from __future__ import annotations

import gc
import re
import unicodedata
import zlib
from bisect import bisect_left
from collections import defaultdict
from collections.abc import Iterator
from functools import lru_cache

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .common import hold, materialise, ship

CAPACITY = 2048
WORDS_HELD, PARTS_HELD = 300_000, 500_000
CHARS_AT_ONCE = 6_000_000

# The split pattern that the vocabulary's file gives, and white space that Python alone knows.
_SPLIT = r"'s|'t|'re|'ve|'m|'ll|'d|[\p{L}]+|[\p{N}]|[^\s\p{L}\p{N}]+"
_ODD = re.compile("[\x1c-\x1f]|<\\|")


def tokenizer_path(name: str = "word_bpe_49k.json") -> str:
    import public_tokenizers

    return str(public_tokenizers.path(name))


def _printable() -> list[str]:
    """The character that stands for each byte in byte-level vocabularies: itself if printable, else one from 256 on."""
    plain = [*range(33, 127), *range(161, 173), *range(174, 256)]
    others = iter(range(256, 512))
    return [chr(b) if b in plain else chr(next(others)) for b in range(256)]


class Merges:
    """Byte-pair merges of many words at once: every step merges the first best pair of each word."""

    LONGEST = 40

    def __init__(self, vocab: dict[str, int], merges: list, suffix: str):
        chars = _printable()
        self.inner = np.array([vocab.get(c, -1) for c in chars], np.int64)
        self.last = np.array([vocab.get(c + suffix, -1) for c in chars], np.int64)
        pairs = [tuple(m.split(" ")) if isinstance(m, str) else tuple(m) for m in merges]
        keys = np.array([vocab[a] << 32 | vocab[b] for a, b in pairs], np.int64)
        self.made = np.array([vocab[a + b] for a, b in pairs] + [-1], np.int64)
        self.none = len(pairs)
        ranks = np.arange(self.none)
        # two tables by multiplication: what the first can't hold goes to the second
        self.tables, factor = [], 0x9E3779B97F4A7C15
        for bits in (21, 21, 21, 21):
            slots = self._slot(keys, factor, bits)
            table_keys, table_ranks = np.full(1 << bits, -1, np.int64), np.full(1 << bits, self.none, np.int32)
            _, first = np.unique(slots, return_index=True)
            table_keys[slots[first]], table_ranks[slots[first]] = keys[first], ranks[first]
            self.tables.append((factor, bits, table_keys, table_ranks))
            rest = np.setdiff1d(np.arange(len(keys)), first)
            keys, ranks, factor = keys[rest], ranks[rest], factor * 0xBF58476D1CE4E5B9 % (1 << 64) | 1
            if not len(keys):
                break
        assert not len(keys)

    @staticmethod
    def _slot(keys: np.ndarray, factor: int, bits: int) -> np.ndarray:
        return ((keys.view(np.uint64) * np.uint64(factor)) >> np.uint64(64 - bits)).view(np.int64)

    def ranks(self, left: np.ndarray, right: np.ndarray) -> np.ndarray:
        keys = left << 32 | right
        out = None
        for factor, bits, table_keys, table_ranks in self.tables:
            slots = self._slot(keys, factor, bits)
            found = np.where(table_keys[slots] == keys, table_ranks[slots], self.none)
            out = found if out is None else np.minimum(out, found)
        return out

    def encode(self, words: list[bytes]) -> list[bytes]:
        """Ids of words of 1 to LONGEST bytes."""
        sizes = np.fromiter(map(len, words), np.int64, len(words))
        order, out = np.argsort(sizes, kind="stable"), [b""] * len(words)
        for at in range(0, len(order), 8192):
            mine = order[at : at + 8192]
            for k, ids in zip(mine.tolist(), self._some([words[k] for k in mine.tolist()], sizes[mine])):
                out[k] = ids
        return out

    def _some(self, words: list[bytes], sizes: np.ndarray) -> list[bytes]:
        n, wide = len(words), int(sizes.max())
        raw = np.frombuffer(b"".join(w.ljust(wide, b"\0") for w in words), np.uint8).reshape(n, wide)
        ids = self.inner[raw]
        ids[np.arange(n), sizes - 1] = self.last[raw[np.arange(n), sizes - 1]]
        live = np.arange(wide)[None, :] < sizes[:, None]
        after = np.broadcast_to(np.arange(1, wide + 1), (n, wide)).copy()
        after[np.arange(n), sizes - 1] = wide
        before = np.broadcast_to(np.arange(-1, wide - 1), (n, wide)).copy()
        rank = np.full((n, wide), self.none, np.int32)
        if wide > 1:
            rank[:, :-1] = np.where(live[:, 1:], self.ranks(ids[:, :-1], ids[:, 1:]), self.none)
        rows = np.arange(n)
        while len(rows):
            at = rank[rows].argmin(1)
            best = rank[rows, at]
            go = best < self.none
            rows, at, best = rows[go], at[go], best[go]
            if not len(rows):
                break
            gone = after[rows, at]
            following = after[rows, gone]
            ids[rows, at] = self.made[best]
            live[rows, gone] = False
            rank[rows, gone] = self.none
            after[rows, at] = following
            has = following < wide
            before[rows[has], following[has]] = at[has]
            rank[rows, at] = self.none
            rank[rows[has], at[has]] = self.ranks(ids[rows[has], at[has]], ids[rows[has], following[has]])
            earlier = before[rows, at]
            has = earlier >= 0
            rank[rows[has], earlier[has]] = self.ranks(ids[rows[has], earlier[has]], ids[rows[has], at[has]])
        flat = ids[live].astype("<u4").tobytes()
        ends = np.cumsum(live.sum(1)) * 4
        return [flat[a:b] for a, b in zip([0, *ends[:-1].tolist()], ends.tolist())]


class WordTokens:
    """Token ids of texts, for a tokenizer whose tokens never cross white space: words are looked up, unknown ones merged
    in bulk.  Any tokenizer of another make encodes whole texts itself.

    The tables stop growing at their limits; what isn't held is worked out again, with the same result."""

    def __init__(self, path: str):
        import json

        import regex
        from tokenizers import Tokenizer

        self.tokenizer = Tokenizer.from_file(path)
        with open(path, encoding="utf-8") as f:
            made = json.load(f)
        model = made["model"]
        kinds = [x["type"] for x in (made["normalizer"] or {}).get("normalizers", [])]
        split = [x.get("pattern", {}).get("Regex") for x in (made["pre_tokenizer"] or {}).get("pretokenizers", [])]
        self.known = model["type"] == "BPE" and kinds == ["NFC", "Replace", "Lowercase"] and split == [_SPLIT, None] and not made["post_processor"]
        if self.known:
            self.merges = Merges(model["vocab"], model["merges"], model["end_of_word_suffix"] or "")
        self.find = regex.compile(_SPLIT).findall
        self.words: dict[str, bytes] = {}
        self.parts: dict[str, bytes] = {}

    def whole(self, text: str) -> bytes:
        return np.asarray(self.tokenizer.encode(text, add_special_tokens=False).ids, "<u4").tobytes()

    def split(self, word: str) -> list[str]:
        """Parts of a word without white space, in lower case and composed."""
        if not word.isascii():
            word = unicodedata.normalize("NFC", word)
        low = word.lower() if "\u03a3" not in word else "".join(c.lower() for c in word)  # a last sigma is like any other
        if low.isalpha():
            return [low]
        if low[:-1].isalpha() and low[-1] in ".,!?":
            return [low[:-1], low[-1]]
        return self.find(low)

    def learn(self, words: set[str]) -> None:
        order = list(words)
        parts = [self.split(w) for w in order]
        unknown = list({p for ps in parts for p in ps} - self.parts.keys())
        raw = [p.encode("utf-8", "surrogatepass") for p in unknown]
        short = [k for k, b in enumerate(raw) if len(b) <= Merges.LONGEST]
        found = dict(zip([unknown[k] for k in short], self.merges.encode([raw[k] for k in short]))) if short else {}
        found |= {p: self.whole(p) for p in set(unknown) - found.keys()}
        self.parts |= found
        get = self.parts.__getitem__
        self.words |= zip(order, [get(ps[0]) if len(ps) == 1 else b"".join(map(get, ps)) for ps in parts])
        if len(self.parts) > PARTS_HELD:
            for p in found:
                del self.parts[p]

    def encode_batch(self, texts: list[str]) -> Iterator[bytes]:
        """Ids of each text as little-endian unsigned 32-bit numbers."""
        at = 0
        while at < len(texts):
            upto, chars = at, 0
            while upto < len(texts) and (upto == at or chars + len(texts[upto]) <= CHARS_AT_ONCE):
                chars += len(texts[upto])
                upto += 1
            gc.disable()  # millions of strings and no cycles among them
            odd = [not self.known or _ODD.search(t) is not None for t in texts[at:upto]]
            split = [None if o else t.split() for o, t in zip(odd, texts[at:upto])]
            new = {w for ws in split if ws for w in ws} - self.words.keys()
            if new:
                self.learn(new)
            get = self.words.__getitem__
            made = [self.whole(t) if ws is None else b"".join(map(get, ws)) for ws, t in zip(split, texts[at:upto])]
            if len(self.words) > WORDS_HELD:
                for w in new:
                    del self.words[w]
            del split, new
            gc.enable()
            yield from made
            at = upto


@lru_cache(maxsize=4)
def _tokens(path: str) -> WordTokens:
    return WordTokens(path)


PIECES = "doc_id bigint, piece int, start bigint, length bigint, ids_crc32 bigint, task int, local long"


def pieces(df: DataFrame, capacity: int = CAPACITY, path: str | None = None, key: str = "doc_id", text: str = "text", end_id: int = 0) -> DataFrame:
    """The pieces of all documents, with the task that made them and their number there among pieces of their length.

    A null text is empty and is just its end token."""
    ship(df.sparkSession)
    path = path or tokenizer_path()
    rows = df.select(F.col(key).cast("bigint").alias("doc_id"), F.col(text).cast("string").alias("text"))
    end = np.asarray([end_id], "<u4").tobytes()

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        from pyspark import TaskContext

        hold("tokens", _tokens.cache_clear)
        tokens, task, count = _tokens(path), TaskContext.get().partitionId(), defaultdict(int)
        for batch in batches:
            out = []
            texts = [t or "" for t in batch.column(1).to_pylist()]
            for k, ids in zip(batch.column(0).to_pylist(), tokens.encode_batch(texts)):
                ids += end
                n = len(ids) // 4
                for piece, start in enumerate(range(0, n, capacity)):
                    length = min(capacity, n - start)
                    out.append((k, piece, start, length, zlib.crc32(ids[4 * start : 4 * (start + length)]), task, count[length]))
                    count[length] += 1
            if out:
                kinds = [pa.int64(), pa.int32(), pa.int64(), pa.int64(), pa.int64(), pa.int32(), pa.int64()]
                names = ["doc_id", "piece", "start", "length", "ids_crc32", "task", "local"]
                yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*out), kinds)], names=names)

    return rows.mapInArrow(run, PIECES)


class Plan:
    """Rank intervals of each length with their places."""

    def __init__(self):
        self.rows: list[tuple[int, int, int, int]] = []  # length, first rank, first sequence, offset
        self.sequences = 0


def plan_rounds(histogram: dict[int, int], capacity: int = CAPACITY) -> Plan:
    """Best-fit in rounds over runs of equal lengths and equal gaps."""
    plan = Plan()
    left = {n: c for n, c in histogram.items() if c}
    rank: dict[int, int] = defaultdict(int)
    gaps: dict[int, list[tuple[int, int]]] = {}  # gap -> runs (first sequence, count)

    def place(length: int, count: int, sequence: int, gap: int, into: dict[int, list[tuple[int, int]]]) -> None:
        plan.rows.append((length, rank[length], sequence, capacity - gap))
        rank[length] += count
        left[length] -= count
        if gap > length:
            into[gap - length].append((sequence, count))

    def sweep() -> None:
        sizes, made = sorted(gaps), defaultdict(list)
        for length in sorted(left, reverse=True):
            while left[length]:
                at = bisect_left(sizes, length)
                if at == len(sizes):
                    break
                gap = sizes[at]
                sequence, count = gaps[gap].pop()
                taken = min(count, left[length])
                place(length, taken, sequence, gap, made)
                if taken < count:
                    gaps[gap].append((sequence + taken, count - taken))
                elif not gaps[gap]:
                    del gaps[gap], sizes[at]
        for gap, runs in made.items():
            gaps.setdefault(gap, []).extend(runs)

    def open_for(lengths: list[int], most: int) -> None:
        made = defaultdict(list)
        for length in lengths:
            count = min(left[length], most)
            if count:
                place(length, count, plan.sequences, capacity, made)
                plan.sequences += count
                most -= count
        for gap, runs in made.items():
            gaps.setdefault(gap, []).extend(runs)

    large = [n for n in sorted(left, reverse=True) if 2 * n > capacity]
    open_for(large, sum(left[n] for n in large))
    while any(left.values()):
        before = sum(left.values())
        sweep()
        if sum(left.values()) == before:
            tokens = sum(n * c for n, c in left.items())
            open_for(sorted(left, reverse=True), max(1, -(-tokens // capacity)))
        left = {n: c for n, c in left.items() if c}
    return plan


def pack(made: DataFrame, capacity: int = CAPACITY, length: str = "length", task: str = "task", local: str = "local") -> DataFrame:
    """made with sequence_id and offset.  `local` numbers the rows of each (task, length) from 0."""
    spark = made.sparkSession
    ship(spark)
    counts = made.groupBy(F.col(task).alias("_t"), F.col(length).alias("_l")).agg(F.count(F.lit(1)).alias("_c"))
    counts = materialise(counts, "pack-counts")
    histogram = {int(r[0]): int(r[1]) for r in counts.groupBy("_l").agg(F.sum("_c")).collect()}  # at most `capacity` rows
    before = Window.partitionBy("_l").orderBy("_t").rowsBetween(Window.unboundedPreceding, -1)
    bases = counts.select("_t", "_l", F.coalesce(F.sum("_c").over(before), F.lit(0)).alias("_base"))
    plan = plan_rounds(histogram, capacity)
    rows = sorted(plan.rows)
    lengths = np.array([r[0] for r in rows], np.int64)
    firsts = np.array([r[1] for r in rows], np.int64)
    sequences = np.array([r[2] for r in rows], np.int64)
    offsets = np.array([r[3] for r in rows], np.int64)
    starts = np.searchsorted(lengths, np.arange(capacity + 2))
    tables = spark.sparkContext.broadcast((firsts, sequences, offsets, starts))  # intervals of a plan over at most `capacity` sizes

    ranked = made.join(bases, (F.col(task) == F.col("_t")) & (F.col(length) == F.col("_l")))
    ranked = ranked.withColumn("_rank", F.col(local) + F.col("_base"))

    @F.pandas_udf("sequence_id long, offset long")
    def places(n, rank):  # noqa: ANN001, ANN202
        import pandas as pd

        firsts, sequences, offsets, starts = tables.value
        n, rank = n.to_numpy(), rank.to_numpy()
        at = np.empty(len(n), np.int64)
        for size in np.unique(n):
            mine = np.flatnonzero(n == size)
            lo, hi = starts[size], starts[size + 1]
            at[mine] = lo + np.searchsorted(firsts[lo:hi], rank[mine], "right") - 1
        return pd.DataFrame({"sequence_id": sequences[at] + rank - firsts[at], "offset": offsets[at]})

    keep = [F.col(c) for c in made.columns if c not in (task, local)]
    return ranked.select(*keep, F.col("_rank")).withColumn("_p", places(F.col(length), F.col("_rank"))).select(*keep, "_p.sequence_id", "_p.offset")


def pack_documents(df: DataFrame, capacity: int = CAPACITY, path: str | None = None, key: str = "doc_id", text: str = "text") -> DataFrame:
    """Tokenize, cut and pack: doc_id, piece, start, length, ids_crc32, sequence_id, offset.

    Null and empty texts are one token; repeated rows are packed each for itself; a null key stays null; an empty table
    gives an empty result; other columns are not read.  The pieces (numbers only) are written to the shared folder once,
    so that a lost executor never makes a text be tokenized and numbered anew."""
    return pack(materialise(pieces(df, capacity, path, key, text), "pieces"), capacity)
