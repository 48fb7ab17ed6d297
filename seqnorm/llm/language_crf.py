"""Language identification by a linear-chain conditional random field over the words of a text.

Emissions are sums of a word's features: hashed ones (the word itself, affixes, character n-grams of the whole word) and
one for each language whose lexicon holds the word.  Lexicons are learned too: the words that several training texts of
a language have.  Transitions between languages are learned together with them, on sequences that switch between texts
of different languages.  A word's label is the likeliest one given the whole text.  Inference is
exact forward-backward over whole texts: texts are cut into blocks whose transfer matrices are multiplied for many
blocks at once, so a very long text costs no more per word than a short one.
"""

from __future__ import annotations

import re
from collections import Counter
from collections.abc import Iterator
from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from .common import hold, ship

BUCKETS = 1 << 17
BLOCK = 64
DOCS_PER_LANGUAGE = 150
#: A model holds BUCKETS weights for each language, and is broadcast.
MOST_LANGUAGES = 200
#: Training texts of a language that must have a word for its lexicon.
LEXICON_TEXTS = 2
WORDS_HELD = 250_000
CHARS_AT_ONCE = 2_000_000
NEW_AT_ONCE = 4096
WORDS_AT_ONCE = 60_000
UNKNOWN = "und"

_WORD = re.compile(r"[^\W\d_]+")


def words_of(text: str | None) -> list[str]:
    """Runs of letters in lower case; none if the text has no letter."""
    words = _WORD.findall((text or "").lower())
    return words if any(any(map(str.isalpha, w)) for w in words) else []


def word_features(word: str) -> list[int]:
    """Buckets of the word, its affixes of 1 to 4 letters, and all its n-grams of 2 and 3 letters."""
    from zlib import crc32

    w = f"^{word}$"
    names = [w, *(f"p{word[:n]}" for n in (1, 2, 3, 4)), *(f"s{word[-n:]}" for n in (1, 2, 3, 4))]
    names += [w[i : i + n] for n in (2, 3) for i in range(len(w) - n + 1)]
    return [crc32(x.encode("utf-8", "surrogatepass")) % BUCKETS for x in names]


def lexicons(texts: list[tuple[list[str], int]], least: int = LEXICON_TEXTS) -> dict[str, list[int]]:
    """Features of the words that `least` texts of a language have: (words, language) to {word: [BUCKETS + language]}."""
    counts = Counter(pair for words, y in texts for pair in {(w, y) for w in words})
    out: dict[str, list[int]] = {}
    for (w, y), n in sorted(counts.items()):
        if n >= least:
            out.setdefault(w, []).append(BUCKETS + y)
    return out


def forward_backward(scores: np.ndarray, transitions: np.ndarray, lengths: np.ndarray) -> np.ndarray:
    """Posteriors (words, labels) of chains laid end to end; scores (words, labels), transitions (from, to).

    A chain begins with one step from all labels alike."""
    k = scores.shape[1]
    lengths = np.asarray(lengths, np.int64)
    blocks = -(-lengths // BLOCK)
    total = int(blocks.sum())
    if not total:
        return np.zeros((0, k))
    first = np.cumsum(blocks) - blocks  # first block of each chain
    chain = np.repeat(np.arange(len(lengths)), blocks)
    place = np.arange(total) - first[chain]
    starts = (np.cumsum(lengths) - lengths)[chain] + place * BLOCK
    sizes = np.minimum(BLOCK, lengths[chain] - place * BLOCK)
    at = np.arange(BLOCK)
    live = at[None, :] < sizes[:, None]
    psi = np.ones((total, BLOCK, k))
    rows = (starts[:, None] + at)[live]
    psi[live] = np.exp(scores[rows] - scores[rows].max(1, keepdims=True))
    step = np.exp(transitions - transitions.max())

    through = np.broadcast_to(np.eye(k), (total, k, k)).copy()
    for t in range(BLOCK):
        on = live[:, t]
        if not on.any():
            break
        moved = (through.reshape(-1, k) @ step).reshape(total, k, k) * psi[:, t, None, :]
        moved /= moved.sum((1, 2), keepdims=True)
        through = np.where(on[:, None, None], moved, through)

    into, outof = np.full((total, k), 1.0 / k), np.ones((total, k))
    for p in range(1, int(blocks.max())):
        now = first[blocks > p] + p
        message = (into[now - 1, None, :] @ through[now - 1])[:, 0]
        into[now] = message / message.sum(1, keepdims=True)
    for p in range(int(blocks.max()) - 2, -1, -1):
        now = first[blocks > p + 1] + p
        message = (through[now + 1] @ outof[now + 1, :, None])[:, :, 0]
        outof[now] = message / message.sum(1, keepdims=True)

    alpha = np.empty((total, BLOCK, k))
    state = into
    for t in range(BLOCK):
        moved = (state @ step) * psi[:, t]
        state = np.where(live[:, t, None], moved / moved.sum(1, keepdims=True), state)
        alpha[:, t] = state
    state = outof
    for t in range(BLOCK - 1, -1, -1):
        alpha[:, t] *= state
        moved = (psi[:, t] * state) @ step.T
        state = np.where(live[:, t, None], moved / moved.sum(1, keepdims=True), state)
    out = alpha[live]
    return out / out.sum(1, keepdims=True)


@dataclass
class Model:
    labels: list[str]
    weights: np.ndarray  # (BUCKETS + labels, labels), float32; the last ones are those of the lexicons
    transitions: np.ndarray
    lexicon: dict[str, list[int]] = field(default_factory=dict, repr=False)

    _rows: dict[str, int] = field(default_factory=dict, repr=False)
    _table: list[np.ndarray] = field(default_factory=list, repr=False)

    def emissions(self, words: list[str]) -> np.ndarray:
        """Scores of words; a word's features, far larger than its scores, are held for NEW_AT_ONCE words at a time."""
        out = np.zeros((len(words), len(self.labels)), np.float32)
        for at in range(0, len(words), NEW_AT_ONCE):
            features = [word_features(w) + self.lexicon.get(w, []) for w in words[at : at + NEW_AT_ONCE]]
            ends = np.cumsum([len(f) for f in features])
            flat = np.fromiter((x for f in features for x in f), np.int64, int(ends[-1]))
            out[at : at + len(features)] = np.add.reduceat(self.weights[flat], np.concatenate([[0], ends[:-1]]))
        return out

    def forget(self) -> None:
        """Let go of the words held."""
        self._rows.clear()
        self._table.clear()

    def tag(self, text: str | None) -> list[tuple[str, str, float]]:
        """(word, language, posterior) of each word of a text, given all of it; of languages alike the first by name."""
        words = words_of(text)
        if not words:
            return []
        kinds = {w: i for i, w in enumerate(dict.fromkeys(words))}
        scores = self.emissions(list(kinds))[[kinds[w] for w in words]]
        posterior = forward_backward(scores.astype(np.float64), self.transitions, np.array([len(words)]))
        best = posterior.argmax(1)
        return [(w, self.labels[b], float(p[b])) for w, b, p in zip(words, best, posterior)]

    def shares(self, texts: list[str | None]) -> tuple[np.ndarray, np.ndarray]:
        """(number of words, mean posterior of each label) of each text."""
        split = [words_of(t) for t in texts]
        lengths = np.array([len(ws) for ws in split], np.int64)
        new = list({w for ws in split for w in ws} - self._rows.keys())
        if not self._table:
            self._table.append(np.zeros((0, len(self.labels)), np.float32))
        held = len(self._table[0])
        table = np.concatenate([self._table[0], self.emissions(new)]) if new else self._table[0]
        self._rows |= zip(new, range(held, held + len(new)))
        get = self._rows.__getitem__
        ids = np.fromiter((get(w) for ws in split for w in ws), np.int64, int(lengths.sum()))
        if held + len(new) > WORDS_HELD:
            for w in new:
                del self._rows[w]
        else:
            self._table[0] = table
        del split, new
        out = np.zeros((len(texts), len(self.labels)))
        some = np.flatnonzero(lengths)
        ends = np.cumsum(lengths)
        while len(some):
            upto = max(1, int(np.searchsorted(ends[some], ends[some[0]] + WORDS_AT_ONCE)))
            now, some = some[:upto], some[upto:]
            begin = int(ends[now[0]] - lengths[now[0]])
            posterior = forward_backward(table[ids[begin : ends[now[-1]]]].astype(np.float64), self.transitions, lengths[now])
            out[now] = np.add.reduceat(posterior, ends[now] - lengths[now] - begin) / lengths[now, None]
        return lengths, out


def fit(samples: list[tuple[str, str]], epochs: int = 6, seed: int = 7, rate: float = 0.5) -> Model | None:
    """Learn weights and transitions from all words of (text, language) pairs by Adagrad on the chain's log-likelihood.

    Texts are dealt into two halves, and those of a half see the lexicon of the other one: a text's own words would be
    in a lexicon far oftener than those of a new text.  Stretches of all texts are laid end to end in random order and
    cut into chains of BLOCK words, the last one as long as it comes out."""
    labels = sorted({lang for _, lang in samples})
    if not labels:
        return None
    if len(labels) > MOST_LANGUAGES:
        raise ValueError(f"{len(labels)} languages are more than {MOST_LANGUAGES}: a model for them is too large to broadcast")
    rng, k = np.random.default_rng(seed), len(labels)
    texts = [(words_of(text), labels.index(lang)) for text, lang in samples]
    halves = [lexicons(texts[1::2]), lexicons(texts[::2])]  # what the texts of each half see
    runs: list[tuple[int, int, list[str]]] = []
    for i, (words, y) in enumerate(texts):
        while words:
            n = int(rng.geometric(1 / 24))
            runs.append((y, i % 2, words[:n]))
            words = words[n:]
    rng.shuffle(runs)
    vocabulary = {w: i for i, w in enumerate(sorted({(w, half) for _, half, ws in runs for w in ws}))}
    features = [np.array(word_features(w) + halves[half].get(w, [])) for w, half in vocabulary]
    sizes = np.array([len(f) for f in features], np.int64)
    flat, firsts = np.concatenate(features) if features else np.zeros(0, np.int64), np.cumsum(sizes) - sizes
    ids = np.array([vocabulary[w, half] for _, half, ws in runs for w in ws], np.int64)
    truth = np.array([y for y, _, ws in runs for _ in ws], np.int64)
    weights, transitions = np.zeros((BUCKETS + k, k)), np.zeros((k, k))
    seen_w, seen_t = np.full((BUCKETS + k, k), 1e-2), np.full((k, k), 1e-2)
    n, size = -(-len(ids) // BLOCK), 128
    for _ in range(epochs):
        order = rng.permutation(n)
        for at in range(0, n, size):
            chosen = order[at : at + size]
            lengths = np.minimum(BLOCK, len(ids) - chosen * BLOCK)
            rows = (chosen[:, None] * BLOCK + np.arange(BLOCK)).ravel()
            rows = rows[rows < len(ids)]
            word, y = ids[rows], truth[rows]
            kinds, inverse = np.unique(word, return_inverse=True)
            used = np.concatenate([flat[firsts[i] : firsts[i] + sizes[i]] for i in kinds])
            scores = np.add.reduceat(weights[used], np.cumsum(sizes[kinds]) - sizes[kinds])
            miss, gt = gradient(scores[inverse], transitions, lengths, y)
            chains = len(lengths)
            by_word = np.stack([np.bincount(inverse, miss[:, j], len(kinds)) for j in range(k)], 1) / chains
            repeated = np.repeat(by_word, sizes[kinds], 0)
            buckets, where = np.unique(used, return_inverse=True)
            g = np.stack([np.bincount(where, repeated[:, j], len(buckets)) for j in range(k)], 1) + 1e-4 * weights[buckets]
            seen_w[buckets] += g * g
            weights[buckets] -= rate * g / np.sqrt(seen_w[buckets])
            gt /= chains
            seen_t += gt * gt
            transitions -= rate * gt / np.sqrt(seen_t)
    return Model(labels, weights.astype(np.float32), transitions, lexicons(texts))


def gradient(scores: np.ndarray, transitions: np.ndarray, lengths: np.ndarray, truth: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Derivatives of minus the log-likelihood of the true labels: by each word's scores, and by transitions.

    Both are expected less counted; expected pairs come from neighbouring posteriors and the chain's step.  Chains have
    at most BLOCK words."""
    posterior = forward_backward(scores, transitions, lengths)
    miss = posterior.copy()
    miss[np.arange(len(truth)), truth] -= 1
    k, live = scores.shape[1], np.arange(max(lengths, default=0))[None, :] < np.asarray(lengths)[:, None]
    f, q = np.ones((*live.shape, k)), np.zeros((*live.shape, k))
    f[live], q[live] = np.exp(scores - scores.max(1, keepdims=True)), posterior
    step = np.exp(transitions)
    state, expected = np.full((len(live), k), 1.0 / k), np.zeros((k, k))
    for t in range(live.shape[1]):
        received = state @ step
        if t:  # the share of what each word receives; words behind a chain's end have no posterior
            expected += np.einsum("ci,ij,cj->ij", state, step, q[:, t] / np.maximum(received, 1e-300))
        state = received * f[:, t]
        state /= state.sum(1, keepdims=True)
    counted, last = np.zeros((k, k)), np.cumsum(lengths) - 1
    inner = np.setdiff1d(np.arange(len(truth)), last)
    np.add.at(counted, (truth[inner], truth[inner + 1]), 1)
    # a chain begins with one step from all labels alike, which is a part of its likelihood
    first = np.cumsum(lengths) - lengths
    begins = q[np.asarray(lengths) > 0, 0] if live.shape[1] else np.zeros((0, k))
    expected += step / np.maximum(step.sum(0), 1e-300) * begins.sum(0)
    opened = truth[first[np.asarray(lengths) > 0]] if len(truth) else np.zeros(0, np.int64)
    counted += step / np.maximum(step.sum(0), 1e-300) * np.bincount(opened, minlength=k)
    return miss, expected - counted


def held_out(key: Column) -> Column:
    """True for the third of ids from which nothing is learned."""
    return F.coalesce(F.pmod(F.crc32(key.cast("string").cast("binary")), F.lit(3)) == 1, F.lit(False))


def learn(df: DataFrame, key: str = "doc_id", text: str = "text", lang: str = "lang", docs_per_language: int = DOCS_PER_LANGUAGE, **settings) -> Model | None:
    """Fit on a bounded sample: for each language the `docs_per_language` labelled rows of smallest id hash that aren't held out.

    All words of the chosen texts are learned from, and only these texts come to the driver; ids are chosen from the
    narrow columns alone.  Rows without a key or a language teach nothing; no row at all gives None.  More than
    MOST_LANGUAGES languages raise ValueError."""
    labelled = df.filter(F.col(lang).isNotNull() & F.col(key).isNotNull() & ~held_out(F.col(key)))
    order = Window.partitionBy("_lang").orderBy(F.xxhash64("_k"), "_k")
    ids = labelled.select(F.col(key).cast("bigint").alias("_k"), F.col(lang).alias("_lang")).withColumn("_r", F.row_number().over(order)).filter(F.col("_r") <= docs_per_language)
    chosen = [r[0] for r in ids.select("_k").distinct().collect()]
    if not chosen:
        return None
    rows = labelled.filter(F.col(key).isin(chosen)).select(F.col(key).cast("bigint"), F.col(text).cast("string"), F.col(lang)).collect()
    return fit([(r[1], r[2]) for r in sorted(rows, key=lambda r: (r[0], r[2], r[1] or ""))], **settings)


SCHEMA = "key bigint, held_out boolean, lang_pred string, score double, n_words bigint, mix string"


def _predictions(model: Model | None, batch: pa.RecordBatch, at: int) -> Iterator[tuple[pa.RecordBatch, np.ndarray, list[str], list[float], np.ndarray]]:
    """Rows of a batch, as many at once as have CHARS_AT_ONCE characters: (rows, words, language, score, shares)."""
    hold("languages", model.forget if model else bool)
    begin = 0
    while begin < batch.num_rows:
        texts: list[str | None] = []
        chars = 0
        while begin + len(texts) < batch.num_rows and (not texts or chars < CHARS_AT_ONCE):
            texts.append(batch.column(at)[begin + len(texts)].as_py())
            chars += len(texts[-1] or "")
        part = batch.slice(begin, len(texts))
        begin += len(texts)
        if model is None:
            yield part, np.zeros(len(texts), np.int64), [UNKNOWN] * len(texts), [0.0] * len(texts), np.zeros((len(texts), 0))
            continue
        counts, shares = model.shares(texts)
        best = shares.argmax(1)
        pred = [model.labels[b] if n else UNKNOWN for b, n in zip(best, counts)]
        yield part, counts, pred, [float(s[b]) if n else 0.0 for s, b, n in zip(shares, best, counts)], shares


def identify(df: DataFrame, model: Model | None, key: str = "doc_id", text: str = "text") -> DataFrame:
    """key, held_out, lang_pred, score (mean posterior of that language), n_words, and the mix of languages found.

    A text that is null or has no letter is `und` with score 0, as is every text when there was nothing to learn from.
    Repeated rows get a row each; a null key stays null and counts as not held out; an empty table gives an empty
    result; only the key and the text are read, so other columns may have any name.  Of languages with equal posteriors
    the first by name is told.  A very long text is scored whole, WORDS_AT_ONCE words or one text at a time."""
    spark = df.sparkSession
    ship(spark)
    shared = spark.sparkContext.broadcast(model)  # BUCKETS weights for each of at most MOST_LANGUAGES languages
    rows = df.select(F.col(key).cast("bigint").alias("key"), held_out(F.col(key)).alias("held_out"), F.col(text).cast("string").alias("text"))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        m = shared.value
        for batch in batches:
            for part, counts, pred, score, shares in _predictions(m, batch, 2):
                mix = [",".join(f"{m.labels[j]}:{s[j]:.2f}" for j in np.argsort(-s, kind="stable") if s[j] >= 0.1) for s in shares] if m else [""] * len(pred)
                yield pa.RecordBatch.from_arrays(
                    [part.column(0), part.column(1), pa.array(pred, pa.string()), pa.array(score, pa.float64()), pa.array(counts, pa.int64()), pa.array(mix, pa.string())],
                    names=["key", "held_out", "lang_pred", "score", "n_words", "mix"],
                )

    return rows.mapInArrow(run, SCHEMA).withColumnRenamed("key", key)


def label_words(df: DataFrame, model: Model | None, key: str = "doc_id", text: str = "text") -> DataFrame:
    """key, at (from 0), word, lang, score: the label of every word of every text, for texts that switch between languages.

    A text without a letter has no row, nor has any when there was nothing to learn from; repeated rows have theirs each."""
    spark = df.sparkSession
    ship(spark)
    shared = spark.sparkContext.broadcast(model)
    rows = df.select(F.col(key).cast("bigint").alias("key"), F.col(text).cast("string").alias("text"))
    schema = pa.schema([("key", pa.int64()), ("at", pa.int64()), ("word", pa.string()), ("lang", pa.string()), ("score", pa.float64())])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        m = shared.value
        for batch in batches:
            for k, t in zip(batch.column(0).to_pylist(), batch.column(1)):
                if m is not None and (found := m.tag(t.as_py())):
                    words, langs, scores = zip(*found)
                    yield pa.RecordBatch.from_arrays([pa.array([k] * len(words), pa.int64()), pa.array(range(len(words)), pa.int64()), pa.array(words, pa.string()), pa.array(langs, pa.string()), pa.array(scores, pa.float64())], schema=schema)

    return rows.mapInArrow(run, "key bigint, at bigint, word string, lang string, score double").withColumnRenamed("key", key)


def keep_clear(df: DataFrame, model: Model | None, least: float, sure: float, text: str = "text", lang: str = "lang") -> DataFrame:
    """The rows of df whose text has a language with a score of `least` or more that doesn't contradict the label.

    A language other than the label's contradicts it from a score of `sure` on; a null label is never contradicted.
    A text that is null or has no letter goes, as does every row when there was nothing to learn from.  Repeated rows
    are judged alike, each for itself; an empty table gives an empty result; all columns stay.  Whole batches pass
    through one narrow stage, so texts are neither shuffled nor joined."""
    spark = df.sparkSession
    ship(spark)
    shared = spark.sparkContext.broadcast(model)
    at, label = df.columns.index(text), df.columns.index(lang)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for part, _, pred, score, _ in _predictions(shared.value, batch, at):
                told = part.column(label).to_pylist()
                mask = [p != UNKNOWN and s >= least and not (t is not None and t != p and s >= sure) for p, s, t in zip(pred, score, told)]
                yield part.filter(pa.array(mask, pa.bool_()))

    return df.mapInArrow(run, df.schema)
