"""Near-duplicate classes with DartMinHash signatures and banded joining.

A text is a weighted set: its five-word shingles with their counts.  Each unit of weight of a shingle is a region into
which hashed darts fall at ever later times; a dart belongs to one signature coordinate, and each coordinate keeps its
earliest dart.  Two sets agree in a coordinate with the probability of their weighted Jaccard similarity, and a set
with many shingles costs hardly more than one hash for each, as most of its regions see no dart in time.

Bands of coordinates are joined; candidates are checked on the texts; links make classes.  The members of a band's
bucket are compared with its smallest member only, which is enough where these comparisons put them into one class.
Buckets that still hold several classes are compared in blocks, first by sketches alone: what comes out is the members
that have a likely partner in another class.  Texts join these only, and in each block the likely pairs are checked on
them, once for each pair, so that only links come out.  No link between classes is lost to a hot bucket, and no pair
that isn't a link is ever a row.

Classes are the connected parts of the links, found by star contraction: a round hangs the larger neighbours of each
node on its smallest one, then the smaller ones; there are never more edges than links.
"""

from __future__ import annotations

import re
from collections.abc import Iterator
from functools import lru_cache

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import fresh, hold, join_split, materialise, ship

SHINGLE = 5
SIMILARITY = 0.8
BANDS, ROWS = 40, 6
COORDINATES = BANDS * ROWS
#: Members of a block, and words of its texts; a bucket has as many blocks as keep it below both, as dealt by hash.
BLOCK, BLOCK_WORDS = 2000, 4_000_000
SETS_HELD = 1000
WORDS_HELD = 100_000
#: Sketches agree in as large a part as texts are alike, within 0.03 (one standard deviation).
SKETCH_MARGIN = 0.15

_WORD = re.compile(r"\w+")
_GOLD, _ODD = np.uint64(0x9E3779B97F4A7C15), np.uint64(0xD6E8FEB86659FD93)


def _mix(x: np.ndarray) -> np.ndarray:
    """A bijection of 64-bit numbers that spreads every bit."""
    x = x + _GOLD
    x = (x ^ (x >> np.uint64(30))) * np.uint64(0xBF58476D1CE4E5B9)
    x = (x ^ (x >> np.uint64(27))) * np.uint64(0x94D049BB133111EB)
    return x ^ (x >> np.uint64(31))


class _Hashes(dict):
    def __missing__(self, word: str) -> int:
        import xxhash

        h = xxhash.xxh3_64_intdigest(word.encode("utf-8", "surrogatepass"))
        if len(self) < WORDS_HELD:
            self[word] = h
        return h


_HASHES = _Hashes()


def word_hashes(text: str | None) -> np.ndarray:
    """Hashes of the words (letters, digits, underscores) in lower case."""
    words = _WORD.findall((text or "").lower())
    return np.fromiter(map(_HASHES.__getitem__, words), np.uint64, len(words))


def weighted_set(words: np.ndarray, size: int = SHINGLE) -> tuple[np.ndarray, np.ndarray]:
    """(shingle hashes in order, counts); fewer words than a shingle has are one shingle."""
    n = len(words)
    if not n:
        return np.zeros(0, np.uint64), np.zeros(0, np.int64)
    width = min(size, n)
    h = np.zeros(n - width + 1, np.uint64)
    for i in range(width):
        h = h * _ODD + words[i : n - width + 1 + i]
    return np.unique(_mix(h + np.uint64(width)), return_counts=True)


def jaccard(a: tuple[np.ndarray, np.ndarray], b: tuple[np.ndarray, np.ndarray]) -> float:
    """Sum of smaller weights over sum of larger ones; 0 for two empty sets."""
    if not len(a[0]) or not len(b[0]):
        return 0.0
    at = np.minimum(np.searchsorted(b[0], a[0]), len(b[0]) - 1)
    hit = b[0][at] == a[0]
    both = np.minimum(a[1][hit], b[1][at[hit]]).sum()
    either = a[1].sum() + b[1].sum() - both
    return float(both / either) if either else 0.0


def _darts(cells: np.ndarray, until: float, depth: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """The darts of each region up to a time: (region, time, dart).  Gaps between a region's darts are exponential."""
    if until < 1:
        regions, times, darts = [], [], []
        where, clock, n = np.arange(len(cells)), np.zeros(len(cells)), 0
        while len(where):
            n += 1
            with np.errstate(over="ignore"):
                dart = _mix(cells[where] + np.uint64(n) * _ODD)
            clock = clock - np.log(((dart >> np.uint64(11)).astype(np.float64) + 0.5) * 2.0**-53)
            on = clock <= until
            where, clock, dart = where[on], clock[on], dart[on]
            regions.append(where)
            times.append(clock)
            darts.append(dart)
        return np.concatenate(regions), np.concatenate(times), np.concatenate(darts)
    with np.errstate(over="ignore"):
        dart = _mix(cells[:, None] + np.arange(1, depth + 1, dtype=np.uint64)[None, :] * _ODD)
    clock = np.cumsum(-np.log(((dart >> np.uint64(11)).astype(np.float64) + 0.5) * 2.0**-53), axis=1)
    on = clock <= until
    if on[:, -1].any():
        return _darts(cells, until, 2 * depth)
    return np.nonzero(on)[0], clock[on], dart[on]


def signature(keys: np.ndarray, weights: np.ndarray, k: int = COORDINATES) -> np.ndarray:
    """The earliest dart of each of k coordinates, for elements with positive weights (whole or not); zeros for none."""
    weights = np.asarray(weights, np.float64)
    keys, weights = keys[weights > 0], weights[weights > 0]
    if not len(keys):
        return np.zeros(k, np.uint64)
    units = np.ceil(weights).astype(np.int64)
    element = np.repeat(np.arange(len(keys)), units)
    level = np.arange(len(element)) - np.repeat(np.cumsum(units) - units, units)
    with np.errstate(over="ignore"):
        cells = _mix(keys[element] ^ _mix(level.astype(np.uint64)))
    inside = weights[element] - level  # darts above this height in their unit miss the element
    whole = bool((inside >= 1).all())
    until = k * (np.log(k) + 3) / float(weights.sum())
    while True:
        region, time, dart = _darts(cells, until, int(until + 6 * until**0.5 + 10))
        if not whole:
            height = (_mix(dart ^ _GOLD) >> np.uint64(11)).astype(np.float64) * 2.0**-53
            hit = height < inside[region]
            time, dart = time[hit], dart[hit]
        spread = _mix(dart)
        coordinate = (spread % np.uint64(k)).astype(np.int64)
        out, filled = np.zeros(k, np.uint64), np.zeros(k, bool)
        late_first = np.argsort(-time, kind="stable")
        out[coordinate[late_first]] = spread[late_first]
        filled[coordinate] = True
        if filled.all():
            return out
        until *= 2


def bands_of(sig: np.ndarray) -> np.ndarray:
    rows, acc = sig.reshape(BANDS, ROWS), np.arange(BANDS, dtype=np.uint64)
    with np.errstate(over="ignore"):
        for i in range(ROWS):
            acc = _mix(acc * _ODD + rows[:, i])
    return acc.view(np.int64)


def signatures(df: DataFrame, key: str, text: str) -> DataFrame:
    """key, two hashes of the word sequence, number of words, band keys and a sketch of a byte per coordinate."""
    rows = df.select(F.col(key).cast("bigint").alias("key"), F.col(text).cast("string").alias("text"))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        import xxhash

        hold("shingles", _HASHES.clear)
        for whole in batches:
            for at in range(0, whole.num_rows, 2000):
                batch = whole.slice(at, 2000)
                h1, h2, count, bands, sketch = [], [], [], [], []
                for t in batch.column(1):
                    words = word_hashes(t.as_py())
                    digest = xxhash.xxh3_128_digest(words.tobytes())
                    h1.append(int.from_bytes(digest[:8], "little", signed=True))
                    h2.append(int.from_bytes(digest[8:], "little", signed=True))
                    count.append(len(words))
                    sig = signature(*weighted_set(words)) if len(words) else None
                    bands.append(bands_of(sig) if sig is not None else [])
                    sketch.append((sig & np.uint64(255)).astype(np.uint8).tobytes() if sig is not None else None)
                yield pa.RecordBatch.from_arrays(
                    [batch.column(0), pa.array(h1, pa.int64()), pa.array(h2, pa.int64()), pa.array(count, pa.int64()), pa.array(bands, pa.list_(pa.int64())), pa.array(sketch, pa.binary())],
                    names=["key", "h1", "h2", "n_words", "bands", "sketch"],
                )

    return rows.mapInArrow(run, "key bigint, h1 bigint, h2 bigint, n_words bigint, bands array<bigint>, sketch binary")


def verify(pairs: DataFrame, texts: DataFrame) -> DataFrame:
    """pairs (a, b), each once, with their weighted Jaccard similarity; texts (key, text) has each key once.

    A text with very many partners is joined in copies, a part of the partners each."""
    left = texts.select(F.col("key").alias("a"), F.col("text").alias("ta"))
    right = texts.select(F.col("key").alias("b"), F.col("text").alias("tb"))
    many = lambda side: pairs.groupBy(side).agg(F.count(F.lit(1)).alias("n"))
    rows = join_split(pairs.select("a", "b"), left, ["a"], many("a"), F.xxhash64("b"))
    rows = join_split(rows, right, ["b"], many("b"), F.xxhash64("a")).select("a", "b", "ta", "tb")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        @lru_cache(maxsize=256)
        def of(text: str) -> tuple[np.ndarray, np.ndarray]:
            return weighted_set(word_hashes(text))

        for batch in batches:
            found = [jaccard(of(x.as_py() or ""), of(y.as_py() or "")) for x, y in zip(batch.column(2), batch.column(3))]
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), pa.array(found, pa.float64())], names=["a", "b", "similarity"])

    return rows.mapInArrow(run, "a bigint, b bigint, similarity double")


def _stars(edges: DataFrame, small: bool) -> DataFrame:
    """One half round over edges (low, high): the larger (or the smaller) neighbours of each node, and where these are the
    smaller ones the node itself, hang on its smallest neighbour.  A node that has none smaller is its own."""
    near = edges.select(F.col("high").alias("node"), F.col("low").alias("other"))
    both = near if small else near.union(edges.select(F.col("low").alias("node"), F.col("high").alias("other")))
    least = materialise(both.groupBy("node").agg(F.least("node", F.min("other")).alias("least"), F.count(F.lit(1)).alias("n")), "least")
    moving = near if small else edges.select(F.col("low").alias("node"), F.col("high").alias("other"))
    hung = join_split(moving, least.select("node", "least"), ["node"], least.select("node", "n"), F.xxhash64("other"))
    out = hung.select(F.col("least").alias("low"), F.col("other").alias("high"))
    if small:
        out = out.union(least.select(F.col("least").alias("low"), F.col("node").alias("high")))
    return materialise(out.filter("low < high").distinct(), "stars")


def components(links: DataFrame) -> DataFrame:
    """(key, label) of every node of links (a, b): the smallest node that it is connected with.

    A round never has more edges than the one before, and their distances shrink, so that a chain of n links takes
    about log n rounds; it ends when a round leaves all edges as they were, by count and two sums of their hashes."""
    edges = materialise(links.select(F.least("a", "b").alias("low"), F.greatest("a", "b").alias("high")).filter("low < high").distinct(), "links")
    state = None
    while True:
        told = edges.agg(F.count(F.lit(1)), F.bit_xor(F.xxhash64("low", "high")), F.sum(F.pmod(F.xxhash64("high", "low"), F.lit(1 << 31)))).first()
        if told == state or not told[0]:
            return edges.select(F.col("high").alias("key"), F.col("low").alias("label")).union(edges.select(F.col("low").alias("key"), F.col("low").alias("label")).distinct())
        state, edges = told, _stars(_stars(edges, small=False), small=True)


GROUP = "band bigint, i int, j int, own int, key bigint, label bigint, n_words bigint, bands array<bigint>, sketch binary"


def _likely(group: pa.Table, least: float, similarity: float) -> Iterator[tuple[int, np.ndarray, np.ndarray]]:
    """Rows of a pair of blocks with the rows of the other block that may be alike: (row, others, shares of equal sketch bytes).

    They are of different classes, share this band first, and neither is too long to be alike the other."""
    keys, label, own = (group[c].to_numpy() for c in ("key", "label", "own"))
    i, j, band = group["i"][0].as_py(), group["j"][0].as_py(), group["band"][0].as_py()
    weight = np.maximum(group["n_words"].to_numpy() - SHINGLE + 1, 1)
    sketch = np.frombuffer(b"".join(group["sketch"].to_pylist()), np.uint8).reshape(len(keys), -1)
    bands = group["bands"].combine_chunks().flatten().to_numpy().reshape(len(keys), -1)
    earlier = bands[:, : int(np.flatnonzero(bands[0] == band)[0])]
    left, right = np.flatnonzero(own == i), np.flatnonzero(own == j)
    for x in left:
        others = right[(label[right] != label[x]) & (np.minimum(weight[right], weight[x]) >= similarity * np.maximum(weight[right], weight[x]))]
        if i == j:
            others = others[keys[others] > keys[x]]
        if len(others):
            same = (sketch[others] == sketch[x]).mean(1)
            others, same = others[same >= least], same[same >= least]
            first = ~(earlier[others] == earlier[x]).any(1)
            if first.any():
                yield int(x), others[first], same[first]


def _unresolved(members: DataFrame, failing: DataFrame, labels: DataFrame, signed: DataFrame, texts: DataFrame, similarity: float) -> DataFrame:
    """Links (a, b) between classes that share a bucket and are alike in two of their members; a and b are labels.

    members (band, key, leader, n, n_words); signed (key, n_words, bands, sketch).  Only buckets with a failing comparison
    between classes are looked at, in pairs of blocks.  A pair is tried in the first band that it shares, the likeliest
    pairs first, and no more once its classes are joined."""
    least = similarity - SKETCH_MARGIN
    apart = members.join(failing.select(F.col("a").alias("leader"), F.col("b").alias("key")), ["leader", "key"], "left_semi")
    open_ = materialise(apart.groupBy("band").agg(F.first("n").alias("n"), F.first("n_words").alias("words")), "open")
    inside = join_split(members.select("band", "key"), open_.select("band", F.ceil(F.greatest(F.col("n") / BLOCK, F.col("words") / BLOCK_WORDS)).cast("int").alias("blocks")), ["band"], open_.select("band", "n"), F.xxhash64("key"))
    inside = inside.join(labels, "key", "left").withColumn("label", F.coalesce("label", "key")).join(signed, "key")
    inside = inside.withColumn("own", F.pmod(F.xxhash64("key"), F.col("blocks")).cast("int"))
    inside = inside.withColumn("other", F.explode(F.sequence(F.lit(0), F.col("blocks") - 1)))
    inside = inside.select("band", F.least("own", "other").alias("i"), F.greatest("own", "other").alias("j"), "own", "key", "label", "n_words", "bands", "sketch")

    def look(group: pa.Table) -> pa.Table:
        seen = np.zeros(group.num_rows, bool)
        for x, others, _ in _likely(group, least, similarity):
            seen[x] = True
            seen[others] = True
        return group.filter(pa.array(seen))

    def check(group: pa.Table) -> pa.Table:
        label = group["label"].to_numpy()
        found = [(-s, x, int(y)) for x, others, same in _likely(group, least, similarity) for y, s in zip(others, same)]
        owner: dict[int, int] = {}

        def root(c: int) -> int:
            while c in owner:
                c = owner[c]
            return c

        @lru_cache(maxsize=SETS_HELD)
        def of(row: int) -> tuple[np.ndarray, np.ndarray]:
            return weighted_set(word_hashes(group["text"][row].as_py()))

        links = []
        for _, x, y in sorted(found):
            a, b = root(int(label[x])), root(int(label[y]))
            if a != b and jaccard(of(x), of(y)) >= similarity:
                owner[a] = b
                links.append(sorted((int(label[x]), int(label[y]))))
        return pa.table({"a": pa.array([p[0] for p in links], pa.int64()), "b": pa.array([p[1] for p in links], pa.int64())})

    likely = materialise(inside.groupBy("band", "i", "j").applyInArrow(look, GROUP), "likely")
    return likely.join(texts, "key").groupBy("band", "i", "j").applyInArrow(check, "a bigint, b bigint").distinct()


def classes(df: DataFrame, key: str = "doc_id", text: str = "text", similarity: float = SIMILARITY) -> DataFrame:
    """key and class_id (the smallest key of its class) for each row of df.

    Texts with the same words are one class from the start.  A text without a word (null, empty, punctuation only) is a
    class of its own.  A row with a null key takes the class of the texts equal to its own, or null, and starts no
    class.  Repeated rows get a row each; an empty table gives an empty result; other columns are not read.  A very long
    text costs in proportion to its words, and fills a block of its bucket sooner.  There are no ties: of equal texts the
    smallest key leads."""
    ship(df.sparkSession)
    sig = materialise(signatures(df, key, text), "signatures")
    worded = sig.filter("n_words > 0")
    groups = materialise(worded.groupBy("h1", "h2").agg(F.min("key").alias("rep"), F.count(F.lit(1)).alias("copies")).filter("rep is not null"), "copies")
    reps = worded.join(groups.select("h1", "h2", F.col("rep").alias("key")), ["h1", "h2", "key"], "left_semi").select("key", "n_words", "bands", "sketch")
    reps = materialise(reps.dropDuplicates(["key"]), "leading")
    banded = reps.select("key", "n_words", F.explode("bands").alias("band"))
    buckets = banded.groupBy("band").agg(F.min("key").alias("leader"), F.count(F.lit(1)).alias("n"), F.sum("n_words").alias("n_words")).filter("n > 1")
    buckets = materialise(buckets, "buckets")
    members = materialise(join_split(banded.select("key", "band"), buckets, ["band"], buckets.select("band", "n"), F.xxhash64("key")), "members")
    tried = materialise(members.filter("key <> leader").select(F.col("leader").alias("a"), F.col("key").alias("b")).distinct(), "tried")
    texts = df.select(F.col(key).cast("bigint").alias("key"), F.col(text).cast("string").alias("text"))
    wanted = members.select("key").distinct()
    texts = materialise(texts.join(wanted, "key", "left_semi").dropDuplicates(["key"]), "candidates")
    checked = materialise(verify(tried, texts), "checked")
    labels = materialise(components(checked.filter(F.col("similarity") >= similarity).select("a", "b")), "labels")

    of = lambda name: labels.select(F.col("key").alias(name), F.col("label").alias(f"label_{name}"))
    apart = checked.filter(F.col("similarity") < similarity)
    leading = lambda: apart.groupBy("a").agg(F.count(F.lit(1)).alias("n"))
    apart = join_split(apart, of("a"), ["a"], leading(), F.xxhash64("b"), "left").join(of("b"), "b", "left")
    failing = materialise(apart.filter(F.coalesce("label_a", "a") != F.coalesce("label_b", "b")).select("a", "b"), "failing")
    if not failing.isEmpty():
        found = materialise(_unresolved(members, failing, labels, reps, texts, similarity), "more")
        if not found.isEmpty():
            joined = components(found).select(F.col("key").alias("label"), F.col("label").alias("joined"))
            known = labels.unionByName(joined.select(F.col("label").alias("key"), "label")).dropDuplicates(["key"])  # a class of one has no label yet
            sizes = known.groupBy("label").agg(F.count(F.lit(1)).alias("n"))
            labels = join_split(known, joined, ["label"], sizes, F.xxhash64("key"), "left").select("key", F.coalesce("joined", "label").alias("label"))

    named = groups.join(labels.withColumnRenamed("key", "rep"), "rep", "left").filter("copies > 1 or label is not null")
    named = named.select("h1", "h2", F.coalesce("label", "rep").alias("class_id"))
    rows = sig.select("key", "h1", "h2", "n_words")
    sizes = groups.select("h1", "h2", F.col("copies").alias("n"))
    out = join_split(rows.filter("n_words > 0"), named, ["h1", "h2"], sizes, F.monotonically_increasing_id(), "left").select("key", F.coalesce("class_id", "key").alias("class_id"))
    return out.unionByName(rows.filter("n_words = 0").select("key", F.col("key").alias("class_id"))).withColumnRenamed("key", key)


def keep_one(df: DataFrame, key: str = "doc_id", text: str = "text", similarity: float = SIMILARITY) -> DataFrame:
    """df with one row of each class, that of the smallest key; rows with a null key all stay, and all columns by any name.

    The ids that go are far fewer than those that stay, so it is they that are joined with the rows."""
    found = materialise(classes(df.filter(F.col(key).isNotNull()), key, text, similarity), "classes")
    name = fresh("gone")
    gone = found.filter(F.col(key) != F.col("class_id")).select(F.col(key).alias(name)).distinct()
    kept = df.join(gone, F.col(key) == F.col(name), "left_anti")
    if found.groupBy(key).count().filter("count > 1").isEmpty():
        return kept
    once = kept.filter(F.col(key).isNotNull()).dropDuplicates([key])  # a repeated row is a copy of itself
    return once.unionByName(kept.filter(F.col(key).isNull()))
