"""The ten operators against brute force, on odd rows: nulls, empty and long texts, repeats, clashing names, no rows."""

import binascii
import hashlib
import random
import re
import struct
import zlib
from collections import Counter, defaultdict

import numpy as np
import pytest
from pyspark.sql import functions as F

from seqnorm.llm import best_fit, chat_snapshots, dart_minhash, language_crf, license_scan, quality_cascade, temperature_mix, tiered_shards, tiff_media, warc_revisit

DOCS = "doc_id long, text string, lang string, source string, n_chars long, key string, text_ string, rank int"


def rows():
    rng = random.Random(5)
    words = ["alpha", "beta", "gamma", "delta", "the", "of", "étude", "Ñu", "x1"]
    make = lambda n: " ".join(rng.choice(words) + str(rng.randrange(400)) for _ in range(n))
    base = make(120)
    near = base.split()
    near[60] = "changed"
    texts = [
        None, "", "   ", "...", base, base, " ".join(near), make(300), make(6000), "one", "Released under the MIT License.",
        "All rights reserved. CC BY all rights reserved; GNU General Public License", make(40) + "\n" + make(40) + "\nsame line\nsame line",
        "a b c d e f g h " * 30, "###" * 50, "İstanbul ΑΣ ½ ² 你好\x1c\x85ok", "<|endoftext|> plain",
    ]
    out = [(i, t, "en" if i % 2 else "fr", None if i == 3 else f"s{i % 3}", len(t or ""), "k", "t", 1) for i, t in enumerate(texts)]
    return out + [out[4], (None, base, "en", "s1", 5, "k", "t", 1), (None, None, None, None, None, None, None, None)]


@pytest.fixture(scope="module")
def docs(spark):
    return spark.createDataFrame(rows(), DOCS).repartition(3).cache()


@pytest.fixture(scope="module")
def empty(spark):
    return spark.createDataFrame([], DOCS)


def test_license_scan(docs, empty):
    found = license_scan.scan_licenses(docs).collect()
    assert len(found) == len(rows())
    word = re.compile(r"[^\x00-\x2F\x3A-\x60\x7B-\x7F]+")
    lower = str.maketrans("ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz")
    phrases = {"cc by": "cc-by", "general public license": "gpl", "all rights reserved": "reserved"}
    by = {r.doc_id: r for r in found if r.doc_id is not None}
    for k, text, *_ in rows():
        if k is None:
            continue
        words = word.findall((text or "").translate(lower))
        places = [(i, label) for p, label in phrases.items() for i in range(len(words)) if words[i : i + len(p.split())] == p.split()]
        r = by[k]
        assert (r.n_words, r.n_base) == (len(words), len(places))
        assert (r.first_word, r.last_word) == (min((p for p, _ in places), default=None), max((p for p, _ in places), default=None))
        assert r.base_labels == ",".join(sorted({n for _, n in places}))
        assert set(filter(None, r.base_labels.split(","))) <= set(r.labels.split(",")) and 0 <= r.score <= 1
    assert by[10].labels == "mit" and by[10].score == 1.0
    assert license_scan.scan_licenses(empty).count() == 0


def test_matching_statistics_are_the_longest_factors():
    s = license_scan.Scanner({"a": ("a", "w1 w2 w3 w1 w2 w4"), "b": ("b", "w2 w3 w5")}, {"w2 w3": "p"})
    sequences = [t for _, _, t in s.templates] + [t for _, t in s.phrases]
    factors = {tuple(t[i:j]) for t in sequences for i in range(len(t)) for j in range(i + 1, len(t) + 1)}
    rng = random.Random(1)
    for _ in range(200):
        ids = [rng.choice([0, 1, 2, 3, 4, 5]) for _ in range(25)]
        for i, size, _ in s.statistics(ids):
            best = max((n for n in range(1, i + 2) if tuple(ids[i + 1 - n : i + 1]) in factors), default=0)
            assert size == best


def test_license_notices_that_share_an_opening_with_another_template():
    labels = lambda text: sorted({x[2] for x in license_scan.Scanner().scan(text)["spans"]})
    by = "This work is licensed under the Creative Commons Attribution 4.0 International License"
    assert labels(by) == ["cc-by-4.0"]
    assert license_scan.Scanner().scan(by)["spans"] == [(0, 13, "cc-by-4.0", 12 / 13)]
    assert labels(by.replace("Attribution", "Attribution-ShareAlike")) == ["cc-by-sa-4.0"]
    for name, (label, text) in (license_scan.TEMPLATES | license_scan.LICENSES).items():
        assert labels(text) == [label], name
        assert len(license_scan.Scanner().scan(f"{text} {text} x {text}")["spans"]) >= 3, name
    assert labels("under the terms of the GNU General Public License") == []


def test_licenses_with_a_changed_word_are_found():
    """A word put in, doubled, left out or replaced anywhere in a text of 20 words or more hides no template."""
    scanner, rng = license_scan.Scanner(), random.Random(6)
    assert sorted(license_scan.LICENSES) == sorted(k for k, _, t in scanner.templates if k in license_scan.LICENSES and len(t) > 60)
    for name, (label, text) in (license_scan.TEMPLATES | license_scan.LICENSES).items():
        words = re.findall(r"\w+", text)
        if len(words) < 20:
            continue
        found = 0
        for _ in range(25):
            at = rng.randrange(len(words))
            for piece in (["zzz", words[at]], [words[at]] * 2, [], ["zzz"]):
                spans = scanner.scan(" ".join(["foo"] * 5 + words[:at] + piece + words[at + 1 :] + ["bar"] * 5))["spans"]
                found += label in {x[2] for x in spans} and {x[2] for x in spans} <= {label, "reserved"}
        assert found >= 99, (name, found)


def test_license_runs_are_all_the_longest_common_stretches():
    s = license_scan.Scanner({"a": ("a", "w1 w2 w3 w1 w2 w3 w4 w5"), "b": ("b", "w2 w3 w1 w5"), "c": ("c", "w1 w2 w3 w4")}, {"w2 w3": "p"})
    seen = {}
    s.spans = lambda runs: seen.update(runs) or []
    rng = random.Random(2)
    for _ in range(200):
        seen.clear()
        words = [rng.choice([1, 2, 3, 1, 2, 3, 4, 5, 9]) for _ in range(25)]
        s.scan(" ".join(f"w{w}" for w in words))
        ids = [s.vocab.get(f"w{w}".encode(), 0) for w in words]
        for k, (_, _, t) in enumerate(s.templates):
            same = lambda i, j: 0 <= i < len(ids) and 0 <= j < len(t) and ids[i] == t[j]
            want = []
            for i in range(len(ids)):
                for j in range(len(t)):
                    n = next(n for n in range(len(t) + 1) if not same(i + n, j + n))
                    if n >= 3 and not same(i - 1, j - 1):
                        want.append((i, j, n))
            assert sorted(seen.get(k, [])) == want


def test_tiered_shards(spark, docs, empty):
    settings = tiered_shards.Settings(arrival_rows=2, target_bytes=1 << 16, least_bytes=1 << 10, fan_in=3)
    store = tiered_shards.compacted(docs, settings)
    assert store.version() > 1
    first, last = store.manifest(1), store.manifest()
    assert last.count() < first.count() and last.agg(F.sum("rows")).first()[0] == len(rows())
    key = lambda df: Counter(map(str, df.select("doc_id", "text").collect()))
    assert key(store.read()) == key(docs) == key(store.read(1))
    p = store.placement("doc_id")
    assert p.count() == len(rows()) and p.filter("file_no is null").count() == 0
    with pytest.raises(tiered_shards.CommitConflict):
        store._commit(last, store.version())
    before = store.version()
    assert store.append(docs) == before + 1 and store.read().count() == 2 * len(rows())
    assert store.vacuum() > 0 and store.read().count() == 2 * len(rows())
    assert tiered_shards.compacted(empty, settings).read().count() == 0


def test_tiers_merge_as_a_plan_of_sizes_says(spark, tmp_path):
    """Each merge takes all shards of the lowest full tier, as a plan over the manifest's sizes alone would."""
    import math

    settings = tiered_shards.Settings(arrival_rows=40, target_bytes=200_000, least_bytes=1 << 10, fan_in=3)
    store = tiered_shards.Store(spark, f"file://{tmp_path}/store", settings)
    rng, kept = random.Random(2), {k: spark.conf.get(k) for k in ("spark.sql.files.maxPartitionBytes", "spark.sql.files.openCostInBytes")}
    shape = lambda: {r.file: r.bytes for r in store.manifest().collect()}
    merges = Counter()
    for n in (200, 190, 180, 170):
        data = [(i, "".join(rng.choices("abcdefghij", k=60)), i) for i in range(n)]
        store.append(spark.createDataFrame(data, "doc_id long, text string, _metadata long").coalesce(1))
        files, last = shape(), 1 << 30
        while True:
            tiers = defaultdict(set)
            for file, size in files.items():
                if 2 * size < settings.target_bytes:
                    tiers[int(math.log(max(size, settings.least_bytes) / settings.least_bytes, settings.ratio) + 1e-12)].add(file)
            full = min((t for t, fs in tiers.items() if len(fs) >= settings.fan_in), default=None)
            assert full == store.full()
            if full is None or len(files) >= last:
                break
            last, before = len(files), files
            store.compact_once()
            files, _ = shape(), merges.update([full])
            assert before.keys() - files.keys() == tiers[full]
    assert len(merges) > 1 and store.read().count() == store.placement().count() == 740
    assert kept == {k: spark.conf.get(k) for k in kept}
    store.append(spark.createDataFrame([(1, "x", 1)] * 200, "doc_id long, text string, _metadata long"))
    with pytest.raises(RuntimeError):
        tiered_shards.Store(spark, store.path, tiered_shards.Settings(target_bytes=1 << 30, least_bytes=1, ratio=2, fan_in=1)).compact(1)


def test_mixing_of_rows_without_keys_and_of_clashing_columns(spark):
    rows = [(None, "same text", "hot", 1, 2) for _ in range(400)] + [(i, f"w{i} text", "cold", 1, 2) for i in range(50)] + [(7, "w7 text", "cold", 3, 4)]
    df = spark.createDataFrame(rows, "doc_id long, text string, source string, _used int, _u int")
    target = temperature_mix.Target(entropy=None, exponent=1.0, max_repeats=1.0)
    m = temperature_mix.mixture(df, target).cache()
    assert m.count() == len(rows) and m.filter("source = 'hot'").groupBy("block").count().agg(F.max("count")).first()[0] < 10
    kept = temperature_mix.mixed(df, target)
    assert kept.columns == df.columns and kept.count() == len(rows)
    once = temperature_mix.mixed(df.filter("doc_id is null or doc_id <> 7"), target)
    assert sorted(map(str, once.collect())) == sorted(map(str, df.filter("doc_id is null or doc_id <> 7").collect()))


def test_mixing_weights_against_a_search(spark):
    """Exponent, weights and repeats as a fine search over exponents finds them."""
    held = {"a": 9000, "b": 700, "c": 250, "d": 50}
    table = spark.createDataFrame(list(held.items()), "source string, tokens long")
    total = sum(held.values())

    def shares(x):
        w = {k: (n / total) ** x for k, n in held.items()}
        return {k: v / sum(w.values()) for k, v in w.items()}

    entropy = lambda x: -sum(v * np.log(v) for v in shares(x).values())
    worst = lambda x: max(v * total / held[k] for k, v in shares(x).items())
    grid = np.linspace(0, 1, 20_001)
    for target, want in (
        (temperature_mix.Target(entropy=0.7, max_repeats=1e9), max(x for x in grid if entropy(x) >= 0.7 * np.log(4))),
        (temperature_mix.Target(entropy=0.95, max_repeats=2.0), min(x for x in grid if worst(x) <= 2.0)),
    ):
        got = {r.source: r for r in temperature_mix.weights(table, target).collect()}
        assert all(abs(r.exponent - want) < 2e-4 for r in got.values())
        assert all(abs(r.weight - shares(want)[k]) < 1e-3 and abs(r.repeats - shares(want)[k] * total / held[k]) < 2e-2 for k, r in got.items())


def test_temperature_mix(spark, docs, empty):
    rng = np.random.default_rng(0)
    big = [(i, "w " * int(rng.integers(5, 60)), "en", "hot" if i % 3 else f"s{i % 7}", 0, "", "", 0) for i in range(3000)]
    df = spark.createDataFrame(big, DOCS)
    m = temperature_mix.mixture(df, temperature_mix.Target(entropy=0.98, max_repeats=3.0)).cache()
    share = {r.source: r for r in m.groupBy("source").agg(F.sum("tokens").alias("t"), F.max("pass_no").alias("p"), F.first("weight").alias("w")).collect()}
    total = sum(r.t for r in share.values())
    assert all(abs(r.t / total - r.w) < 0.01 and r.p <= 2 for r in share.values())
    w = np.array([r.w for r in share.values()])
    assert -(w * np.log(w)).sum() >= 0.98 * np.log(len(w)) - 1e-6 or m.agg(F.max("pass_no")).first()[0] == 2
    repeats = m.groupBy("doc_id", "pass_no").count().agg(F.max("count")).first()[0]
    assert repeats == 1
    prefix = m.orderBy("at").limit(m.count() // 2).groupBy("source").agg(F.sum("tokens").alias("t")).collect()
    half = sum(r.t for r in prefix)
    assert all(abs(r.t / half - share[r.source].w) < 0.03 for r in prefix)
    assert temperature_mix.mixture(docs).filter("source is null").count() >= 1
    assert temperature_mix.mixture(empty).count() == 0
    kept = temperature_mix.mixed(docs, temperature_mix.Target(entropy=None, exponent=0.9, max_repeats=1.0))
    assert kept.columns == docs.columns and kept.groupBy("doc_id").count().filter("doc_id is not null and count > 2").isEmpty()


def test_mixing_without_repeats_takes_from_the_largest(spark):
    """At a repetition limit of one pass no document is used twice, and a large source gives more up than small ones."""
    big = [(i, "w " * 10, "en", "hot" if i % 3 == 0 else f"s{i % 7}", 0, "", "", 0) for i in range(6000)]
    df = spark.createDataFrame(big, DOCS)
    held = {r.source: r["count"] for r in df.groupBy("source").count().collect()}
    for part, exponent in ((0.95, 0.0), (1.0, 0.9)):
        target = temperature_mix.Target(entropy=None, exponent=exponent, max_repeats=1.0, part=part)
        kept = temperature_mix.mixed(df, target).cache()
        assert kept.select("doc_id").distinct().count() == kept.count()
        assert abs(kept.count() - part * len(big)) <= len(held)
        left = {r.source: r["count"] / held[r.source] for r in kept.groupBy("source").count().collect()}
        assert part == 1.0 or (left["hot"] < 0.9 and min(v for k, v in left.items() if k != "hot") > 0.98)


def test_forward_backward_is_exact():
    rng = np.random.default_rng(0)
    lengths = np.array([3, 0, 130, 64, 1, 65])
    scores, trans = rng.normal(size=(lengths.sum(), 3)), rng.normal(size=(3, 3))
    got, at = language_crf.forward_backward(scores, trans, lengths), 0
    for n in lengths:
        e, step, alpha, f = np.exp(scores[at : at + n]), np.exp(trans), [], np.full(3, 1 / 3)
        for t in range(n):
            f = (f @ step) * e[t]
            f /= f.sum()
            alpha.append(f)
        b = np.ones(3)
        for t in range(n - 1, -1, -1):
            p = alpha[t] * b
            assert np.allclose(p / p.sum(), got[at + t])
            b = step @ (e[t] * b)
            b /= b.sum()
        at += n


def test_language_crf(spark, docs, empty):
    real = spark.read.parquet("/root/testdata/sf0.01/documents.parquet")
    model = language_crf.learn(real, docs_per_language=60)
    out = language_crf.identify(real, model).join(real.select("doc_id", "lang"), "doc_id").cache()
    assert out.filter("held_out").agg(F.avg((F.col("lang") == F.col("lang_pred")).cast("int"))).first()[0] > 0.97
    want = {r.doc_id: binascii.crc32(str(r.doc_id).encode()) % 3 == 1 for r in out.collect()}
    assert all(r.held_out == want[r.doc_id] for r in out.collect())
    odd = {r.doc_id: r for r in language_crf.identify(docs, model).collect() if r.doc_id is not None}
    assert {odd[k].lang_pred for k in (0, 1, 2, 3, 14)} == {"und"} and odd[4].lang_pred != "und"
    fr, en = (real.filter(F.col("lang") == x).select("text").first()[0][:600] for x in ("fr", "en"))
    mixed = language_crf.identify(spark.createDataFrame([(1, fr + " " + en)], "doc_id long, text string"), model).first()
    assert {p.split(":")[0] for p in mixed.mix.split(",")} == {"fr", "en"}
    assert language_crf.learn(empty) is None and language_crf.identify(docs, None).filter("lang_pred <> 'und'").isEmpty()
    odd_docs = docs.withColumn("extra", F.lit(1)) if "lang" in docs.columns else docs.withColumn("lang", F.lit(None).cast("string"))
    kept = language_crf.keep_clear(odd_docs, model, 0.0, 2.0)
    assert kept.columns == odd_docs.columns
    assert kept.count() == language_crf.identify(odd_docs, model).filter("lang_pred <> 'und'").count()
    assert language_crf.keep_clear(real, model, 0.4, 0.97).count() > 0.9 * real.count()
    wrong = real.filter("lang = 'fr'").withColumn("lang", F.lit("en"))
    sure = language_crf.identify(wrong, model).filter("lang_pred <> 'en' and score >= 0.97").count()
    assert language_crf.keep_clear(wrong, model, 0.0, 0.97).count() == wrong.count() - sure - language_crf.identify(wrong, model).filter("lang_pred = 'und'").count()
    assert language_crf.keep_clear(real, None, 0.4, 0.97).isEmpty() and language_crf.keep_clear(real.limit(0), model, 0.4, 0.97).isEmpty()


def test_language_crf_gradient_is_that_of_the_likelihood():
    """Derivatives against differences of a likelihood that sums over every labelling."""
    from itertools import product

    rng = np.random.default_rng(3)
    lengths = np.array([4, 1, 3])
    scores, trans, truth = rng.normal(size=(8, 2)), rng.normal(size=(2, 2)), rng.integers(0, 2, 8)

    def loss(scores, trans):
        total, at = 0.0, 0
        for n in lengths:
            e = scores[at : at + n]
            worth = {y: np.exp(e[range(n), y].sum() + sum(trans[a, b] for a, b in zip(y, y[1:]))) * np.exp(trans[:, y[0]]).sum() for y in product(range(2), repeat=int(n))}
            total -= np.log(worth[tuple(truth[at : at + n])] / sum(worth.values()))
            at += n
        return total

    by_scores, by_trans = language_crf.gradient(scores, trans, lengths, truth)
    for values, found in ((scores, by_scores), (trans, by_trans)):
        for at in np.ndindex(values.shape):
            kept, out = values[at], []
            for d in (1e-5, -1e-5):
                values[at] = kept + d
                out.append(loss(scores, trans))
            values[at] = kept
            assert abs((out[0] - out[1]) / 2e-5 - found[at]) < 1e-6


def test_language_crf_learns_from_a_few_words_and_labels_each_word(spark):
    """Three short texts are enough to be told apart; words of two languages in one text get their own labels."""
    few = language_crf.fit([("alpha beta gamma", "xx"), ("delta epsilon", "yy"), ("zeta eta theta", "zz")])
    assert [few.labels[s.argmax()] for s in few.shares(["gamma", "epsilon delta", "theta"])[1]] == ["xx", "yy", "zz"]
    assert language_crf.word_features("a" * 60 + "xyz") != language_crf.word_features("a" * 60 + "xqz")
    real = spark.read.parquet("/root/testdata/sf0.01/documents.parquet")
    model = language_crf.learn(real)
    told = {r.lang: r.text.split(".")[0].split() for r in real.filter(language_crf.held_out(F.col("doc_id")) & F.col("lang").isin("fr", "en", "de") & (F.length("text") > 2000)).select("lang", "text").collect()}
    text = " ".join(" ".join(told[x][:12]) for x in ("fr", "en", "de"))
    want = [x for x in ("fr", "en", "de") for w in told[x][:12] for _ in language_crf.words_of(w)]
    got = language_crf.label_words(spark.createDataFrame([(1, text), (2, None), (3, "12")], "doc_id long, text string"), model).orderBy("at").collect()
    assert [r.word for r in got] == language_crf.words_of(text) and {r.doc_id for r in got} == {1}
    assert np.mean([r.lang == w for r, w in zip(got, want)]) >= 0.9
    assert any(model.lexicon.values()) and model.weights.shape[0] == language_crf.BUCKETS + len(model.labels)
    assert language_crf.fit([("same words", "aa"), ("same words", "bb")]).tag("12") == []
    with pytest.raises(ValueError):
        language_crf.fit([("w", f"l{i}") for i in range(language_crf.MOST_LANGUAGES + 1)])


def test_language_crf_cuts(monkeypatch):
    """Texts and words taken in small parts give what they give in one."""
    texts = ["alpha beta " * 40, None, "gamma", "", "delta epsilon zeta " * 200, "1 2 3", "beta"]
    samples = [("alpha beta gamma " * 60, "xx"), ("delta epsilon zeta " * 60, "yy")]
    whole = language_crf.fit(samples).shares(texts)
    monkeypatch.setattr(language_crf, "WORDS_AT_ONCE", 3)
    monkeypatch.setattr(language_crf, "NEW_AT_ONCE", 2)
    monkeypatch.setattr(language_crf, "WORDS_HELD", 1)
    parts = language_crf.fit(samples).shares(texts)
    assert (whole[0] == parts[0]).all() and np.allclose(whole[1], parts[1])


def test_one_kernels_caches_at_a_time():
    from seqnorm.llm import common

    let_go = []
    common.hold("first", lambda: let_go.append("first"))
    common.hold("first", lambda: let_go.append("first"))
    assert not let_go
    common.hold("second")
    assert let_go == ["first"] and set(common._HELD) == {"second"}


def test_tiff_formats():
    rng = np.random.default_rng(0)
    for compression in (1, 5, 8, 32773):
        for tile in (None, (16, 16)):
            for predictor in (False, True):
                for order in "<>":
                    pages = [rng.integers(0, 9, (37, 45, 3)).astype(np.uint8), rng.integers(0, 255, (5, 7)).astype(np.uint8)]
                    got = list(tiff_media.read_tiff(tiff_media.write_tiff(pages, compression, predictor, 8, tile, order)))
                    assert [p.pixels for p in got] == [x.tobytes() for x in pages]
    long = bytes(rng.integers(0, 256, 30_000).astype(np.uint8))
    assert tiff_media.lzw_unpack(tiff_media.lzw_pack(long)) == long and tiff_media.unpack_bits(tiff_media.pack_bits(long)) == long
    with pytest.raises(tiff_media.TiffError):
        list(tiff_media.read_tiff(b"II*\0\x08\0\0\0\xff\xff"))


def test_tiff_codecs_of_every_length():
    """Codecs give back what they took, at each length up to some strips and around the changes of code width."""
    rng = random.Random(4)
    words = [bytes(rng.choices(range(97, 123), k=rng.randrange(1, 9))) + b" " for _ in range(300)]
    long = b"".join(rng.choice(words) for _ in range(20_000))
    noise = bytes(rng.choices(range(256), k=9000))
    for n in [*range(700), *range(3700, 4300, 7), 60_000]:
        for data in (long[:n], noise[:n], b" " * n, (b"aab" * n)[:n], long[: n // 2] + b" " * (n - n // 2)):
            assert tiff_media.lzw_unpack(tiff_media.lzw_pack(data)) == data
            assert tiff_media.unpack_bits(tiff_media.pack_bits(data)) == data
    assert len(tiff_media.lzw_pack(long)) < len(long) / 1.5 and len(tiff_media.pack_bits(b" " * 1280)) == 20


def test_tiff_schemes_do_not_follow_the_length(spark):
    """Short, middling and long texts meet every way of storing them."""
    docs = spark.read.parquet("/root/testdata/sf0.01/documents.parquet").select("text").distinct().collect()
    seen = defaultdict(Counter)
    for (text,) in docs:
        n, media = tiff_media.store_text(text)
        (page,) = tiff_media.read_tiff(media)
        assert page.pixels[:n] == (text or "").encode() and not page.pixels[n:].strip(b" ")
        seen[min(2, len(page.pixels) // 1500)][str(tiff_media.scheme(page.pixels))] += 1
    assert all(len(kinds) == 4 and min(kinds.values()) >= 0.15 * sum(kinds.values()) for kinds in seen.values()) and len(seen) == 3


def test_tiff_media(spark, docs, empty):
    for r in tiff_media.text_media(docs).collect():
        text = dict((x[0], x[1]) for x in rows() if x[0] is not None).get(r.doc_id, "skip")
        if text == "skip":
            continue
        raw = (text or "").encode()
        payload = raw + b" " * (-len(raw) % 192 if raw else 192)
        assert (r.n_bytes, r.payload_bytes) == (len(raw), len(payload))
        assert r.payload_sha256 == hashlib.sha256(payload).hexdigest() and r.tail_crc32 == zlib.crc32(payload[-16:])
    assert tiff_media.text_media(empty).count() == 0
    files = tiff_media.text_media(docs, keep_media=True)
    pages = tiff_media.read_pages(files.withColumn("media", F.when(F.col("doc_id") != 7, F.col("media")).otherwise(F.lit(b"no")))).collect()
    assert len(pages) == len(rows())
    assert [p.error is not None for p in pages if p.doc_id == 7] == [True]


def test_warc(spark):
    body = "<p>" + "z" * 200 + "WARC/1.1\r\n\r\nContent-Length: 5\r\n\r\n</p>"
    pages = [(i, f"http://a/{i}", t) for i, t in enumerate([body, body, "short", "short", None, "", "é" * 60, "é" * 60, "x" * 99, "x" * 99])]
    pages += [(1, "http://a/1", body), (None, "http://n/", body), (50, None, "y" * 300)]
    df = spark.createDataFrame(pages, "page_id long, url string, html string").withColumn("digest_", F.lit(1))
    got = warc_revisit.pages_by_archives(df).collect()
    assert len(got) == len(pages)
    by = {r.page_id: r for r in got if r.page_id != 1}
    for k, _, html in pages:
        raw = (html or "").encode()
        if k == 1:
            continue
        r = by[k]
        assert (r.payload_bytes, r.payload_digest) == (len(raw), hashlib.sha256(raw).hexdigest())
        want = {None: 0, 7: 6}.get(k, None)
        assert (r.record_type, r.refers_to) == (("revisit", want) if want is not None else ("response", None))
    assert [(r.record_type, r.refers_to, r.payload_bytes) for r in got if r.page_id == 1] == [("revisit", 0, len(body))] * 2
    path = warc_revisit.deduplicated_archives(df)
    assert warc_revisit.read_archives(spark, path, True).filter("payload is not null").count() == 9
    assert warc_revisit.pages_by_archives(df.limit(0)).count() == 0


def test_warc_of_others(spark, tmp_path):
    """An archive with a gzip member for each record, of another writer: revisits by record id and by address, and a lost one."""
    import gzip

    def record(kind, uri, rid, block, **more):
        head = {"WARC-Type": kind, "WARC-Record-ID": rid, "WARC-Date": "2020-02-02T02:02:02Z", "WARC-Target-URI": uri, **more, "Content-Length": str(len(block))}
        return ("WARC/1.0\r\n" + "".join(f"{k}: {v}\r\n" for k, v in head.items()) + "\r\n").encode() + block + b"\r\n\r\n"

    page = b"<p>" + b"long \r\n\r\n" * 30_000
    http = b"HTTP/1.1 200 OK\r\nContent-Type: text/html\r\n\r\n"
    digest = hashlib.sha256(page).hexdigest()
    records = [
        record("warcinfo", "", "<urn:a>", b"software: x"),
        record("response", "http://a/", "<urn:b>", http + page, **{"Content-Type": "application/http; msgtype=response"}),
        record("revisit", "http://c/", "<urn:c>", b"", **{"WARC-Refers-To": "<urn:b>", "WARC-Payload-Digest": f"sha256:{digest}"}),
        record("revisit", "http://d/", "<urn:d>", http, **{"WARC-Refers-To-Target-URI": "http://a/", "WARC-Payload-Digest": f"sha256:{digest}"}),
        record("revisit", "http://e/", "<urn:e>", b"", **{"WARC-Refers-To": "<urn:gone>", "WARC-Payload-Digest": f"sha256:{digest}"}),
    ]
    (tmp_path / "x.warc.gz").write_bytes(b"".join(map(gzip.compress, records)))
    (tmp_path / "plain.warc").write_bytes(records[1].replace(b"<urn:b>", b"<urn:p>"))
    got = {r.record_id: r for r in warc_revisit.resolve(warc_revisit.read_archives(spark, str(tmp_path), pattern="*.warc*")).collect()}
    assert set(got) == {f"<urn:{x}>" for x in "bcdep"}
    assert all((got[f"<urn:{x}>"].payload_bytes, got[f"<urn:{x}>"].payload_digest) == (len(page), digest) for x in "bcdp")
    assert (got["<urn:c>"].refers_to_record, got["<urn:e>"].refers_to_record, got["<urn:e>"].payload_bytes) == ("<urn:b>", None, None)
    assert got["<urn:d>"].refers_to_record in ("<urn:b>", "<urn:p>")
    with pytest.raises(ValueError):
        list(warc_revisit.parse(warc_revisit.unpacked(gzip.compress(records[1])[:-20])))
    with pytest.raises(ValueError):
        list(warc_revisit.parse([records[0][:-3]]))


def test_warc_pieces_keep_every_byte(spark, tmp_path):
    """Payloads full of line ends, and bytes that are no UTF-8, through files of several gzip members read in pieces."""
    import gzip
    import random

    rng, want = random.Random(3), {}
    for name in ("a", "b", "c"):
        members = []
        for k in range(40):
            alphabet = (b"\r\n", b"\r\nx", b"\r\n\xff\x00")[k % 3]
            block = bytes(rng.choice(alphabet) for _ in range(rng.choice((0, 1, 4, 5, 3000, 70_000))))
            want[f"<urn:{name}{k}>"] = block
            members.append(f"WARC/1.1\r\nWARC-Type: resource\r\nWARC-Record-ID: <urn:{name}{k}>\r\nContent-Length: {len(block)}\r\n\r\n".encode() + block + b"\r\n\r\n")
        (tmp_path / f"{name}.warc.gz").write_bytes(b"".join(map(gzip.compress, members)) if name < "c" else gzip.compress(b"".join(members)))
    got = {r.record_id: bytes(r.payload) for r in warc_revisit.read_archives(spark, str(tmp_path), True).collect()}
    assert got == want
    pages = spark.createDataFrame([(k, f"u{k}", b.decode("latin-1")) for k, b in enumerate(want.values())], "page_id long, url string, html string")
    found = {r.page_id: r.digest for r in warc_revisit.read_archives(spark, warc_revisit.deduplicated_archives(pages)).collect()}
    assert found == {k: hashlib.sha256(b.decode("latin-1").encode()).hexdigest() for k, b in enumerate(want.values())}


def test_warc_headers_name_the_response(spark):
    body = "y" * 150
    df = spark.createDataFrame([(1, "http://a/ b", body), (2, None, body), (3, "http://c/", "é" * 400_000), (4, None, "é" * 400_000)], "page_id long, url string, html string")
    path = warc_revisit.deduplicated_archives(df)
    records = {r.page_id: r for r in warc_revisit.read_archives(spark, path, True).collect()}
    assert records[2].refers_to == records[1].record_id and records[2].refers_url == "http://a/%20b" and records[2].payload is None
    assert records[4].refers_to == records[3].record_id and records[3].payload_bytes == 800_000 and records[4].url == "about:blank"


def test_dart_minhash(spark, docs, empty):
    got = {r.doc_id: r.class_id for r in dart_minhash.classes(docs).collect() if r.doc_id is not None}
    assert got[4] == got[5] == got[6] == 4 and all(got[k] == k for k in (0, 1, 2, 3, 7, 8, 9))
    assert dart_minhash.classes(empty).count() == 0
    kept = dart_minhash.keep_one(docs)
    assert kept.columns == docs.columns and kept.filter("doc_id = 4").count() == 1 and kept.filter("doc_id in (5, 6)").count() == 0
    assert kept.filter("doc_id is null").count() == 2


def test_dart_estimates():
    rng, errors = np.random.default_rng(1), []
    for _ in range(40):
        keys = rng.integers(0, 2**63, 200).astype(np.uint64)
        a = rng.random(200) * 3 * (rng.random(200) < 0.9)
        b = np.where(rng.random(200) < 0.8, a, rng.random(200) * 3)
        errors.append((dart_minhash.signature(keys, a) == dart_minhash.signature(keys, b)).mean() - np.minimum(a, b).sum() / np.maximum(a, b).sum())
    assert abs(np.mean(errors)) < 0.02 and np.std(errors) < 0.05


def test_near_duplicates_lose_no_link(spark):
    """Chains of edits, a passage that most texts share, and many copies: classes as brute force finds them."""
    rng = random.Random(3)
    word = lambda: f"w{rng.randrange(5000)}"
    shared = [word() for _ in range(60)]
    texts = []
    for _ in range(150):
        texts.append([word() for _ in range(60)] + shared)
    for _ in range(20):
        t = [word() for _ in range(150)]
        for _ in range(6):
            texts.append(list(t))
            for _ in range(rng.choice([0, 1, 3])):
                t[rng.randrange(len(t))] = word()
    df = spark.createDataFrame([(i, " ".join(t)) for i, t in enumerate(texts)], "doc_id long, text string")
    got = {r.doc_id: r.class_id for r in dart_minhash.classes(df).collect()}
    bags = [Counter(tuple(t[i : i + 5]) for i in range(len(t) - 4)) for t in texts]
    owner = list(range(len(texts)))

    def find(i):
        while owner[i] != i:
            i = owner[i]
        return i

    for i in range(len(texts)):
        for j in range(i):
            both = sum((bags[i] & bags[j]).values())
            if both / (sum(bags[i].values()) + sum(bags[j].values()) - both) >= 0.8:
                a, b = sorted((find(i), find(j)))
                owner[b] = a
    assert got == {i: find(i) for i in range(len(texts))}


def test_unresolved_buckets_are_compared_in_blocks(spark):
    """Members of a bucket whose comparison with the leader failed still find each other, in the first band they share."""
    rng = random.Random(0)
    texts = [" ".join(f"w{rng.randrange(9999)}" for _ in range(100)) for _ in range(6)]
    texts[4] = texts[2] + " more"
    sig = [dart_minhash.signature(*dart_minhash.weighted_set(dart_minhash.word_hashes(t))) for t in texts]
    bands = [dart_minhash.bands_of(s) for s in sig]
    at = next(int(b) for b, c in zip(bands[2], bands[4]) if b == c)
    pos = bands[2].tolist().index(at)
    for b in bands:
        b[pos] = at
    signed = spark.createDataFrame([(i, 100, b.tolist(), bytes((s & np.uint64(255)).astype(np.uint8))) for i, (b, s) in enumerate(zip(bands, sig))], "key long, n_words long, bands array<long>, sketch binary")
    members = spark.createDataFrame([(at, i, 0, 6000, 600) for i in range(6)], "band long, key long, leader long, n long, n_words long")
    failing = spark.createDataFrame([(0, i) for i in range(1, 6)], "a long, b long")
    labels = spark.createDataFrame([(i, i) for i in range(6)], "key long, label long")
    words = spark.createDataFrame(list(enumerate(texts)), "key long, text string")
    assert [tuple(r) for r in dart_minhash._unresolved(members, failing, labels, signed, words, 0.8).collect()] == [(2, 4)]


def _roots(n: int, links) -> list[int]:
    owner = list(range(n))

    def find(i):
        while owner[i] != i:
            owner[i] = owner[owner[i]]
            i = owner[i]
        return i

    for i, j in links:
        a, b = sorted((find(i), find(j)))
        owner[b] = a
    return [find(i) for i in range(n)]


@pytest.mark.parametrize("hot", [1000, 5])
def test_components_of_chains_hubs_and_rings(spark, monkeypatch, hot):
    """Labels are the smallest node of each part, with and without keys that are split."""
    from seqnorm.llm import common

    monkeypatch.setattr(common, "HOT_ROWS", hot)
    rng = random.Random(hot)
    links = [(i, i + 1) for i in range(40)] + [(100, 100 + i) for i in range(1, 60)] + [(160, 130 + i) for i in range(8)]
    links += [(200 + i, 200 + (i + 1) % 30) for i in range(30)] + [(rng.randrange(250, 400), rng.randrange(250, 400)) for _ in range(120)]
    rng.shuffle(links)
    want = _roots(400, links)
    got = {r.key: r.label for r in dart_minhash.components(spark.createDataFrame(links * 2, "a long, b long")).collect()}
    assert got == {k: want[k] for k in {x for l in links if l[0] != l[1] for x in l}}
    assert dart_minhash.components(spark.createDataFrame([], "a long, b long")).count() == 0


def test_split_joins_keep_every_row(spark, monkeypatch):
    from seqnorm.llm import common

    monkeypatch.setattr(common, "HOT_ROWS", 3)
    rows = spark.createDataFrame([(k, i) for k, n in ((1, 40), (2, 3), (3, 1), (4, 9)) for i in range(n)], "k long, i long")
    side = spark.createDataFrame([(1, "a"), (2, "b"), (5, "c")], "k long, x string")
    counts = rows.groupBy("k").agg(F.count(F.lit(1)).alias("n"))
    for how in ("inner", "left"):
        got = common.join_split(rows, side, ["k"], counts, F.xxhash64("i"), how)
        want = rows.join(side, "k", how)
        assert got.columns == want.columns and sorted(map(str, got.collect())) == sorted(map(str, want.collect()))


def near_pairs(texts: list[str], least: float) -> dict[tuple[int, int], float]:
    """Weighted Jaccard similarities of five-word shingles, by brute force over shared shingles."""
    bags = []
    for t in texts:
        w = re.findall(r"\w+", (t or "").lower())
        bags.append(Counter(tuple(w[i : i + 5]) for i in range(max(1, len(w) - 4))) if w else Counter())
    where, both = {}, Counter()
    for i, bag in enumerate(bags):
        for x, n in bag.items():
            for j, m in where.setdefault(x, []):
                both[j, i] += min(n, m)
            where[x].append((i, n))
    size = [sum(b.values()) for b in bags]
    found = {(i, j): n / (size[i] + size[j] - n) for (i, j), n in both.items()}
    return {p: s for p, s in found.items() if s >= least}


def test_near_copies_of_the_given_documents(spark):
    """Every pair of documents that brute force finds alike by 0.8 or more is in one class, and nothing else is."""
    docs = spark.read.parquet("/root/testdata/sf0.01/documents.parquet").select("doc_id", "text").orderBy("doc_id").collect()
    ids, texts = [r.doc_id for r in docs], [r.text for r in docs]
    want = _roots(len(ids), near_pairs(texts, 0.8))
    got = {r.doc_id: r.class_id for r in dart_minhash.classes(spark.read.parquet("/root/testdata/sf0.01/documents.parquet")).collect()}
    assert got == {ids[i]: ids[want[i]] for i in range(len(ids))}


def test_near_duplicates_beside_columns_of_any_name(spark):
    df = spark.createDataFrame([(1, "a b c d e f", 1, 2), (2, "a b c d e f", 3, 4), (2, "a b c d e f", 3, 4), (3, None, 5, 6)], "doc_id long, text string, _gone long, key long")
    assert sorted(map(tuple, dart_minhash.keep_one(df).collect()), key=str) == [(1, "a b c d e f", 1, 2), (3, None, 5, 6)]


def test_quality_cascade(spark, docs, empty):
    got = {r.doc_id: r for r in quality_cascade.judge(docs).collect() if r.doc_id is not None}
    for k, text, *_ in rows():
        if k is None:
            continue
        t, r = text or "", got[k]
        words = re.findall(r"[^\x20\x09-\x0D]+", t)
        seen = Counter(tuple(words[i : i + 8]) for i in range(len(words) - 7))
        covered = {p for i in range(len(words) - 7) if seen[tuple(words[i : i + 8])] > 1 for p in range(i, i + 8)}
        lines = [x for x in t.split("\n") if re.search(r"[^\x20\x09-\x0D]", x)]
        want = (len(words), sum(map(len, words)), len(re.findall(r"[#*$%&|<>]", t)), len(lines) - len(set(lines)), len(covered))
        assert (r.n_words, r.word_chars, r.n_symbols, r.n_dup_lines, r.n_repeat_words) == want
        failed = len(words) < 20 or 100 * len(covered) > 30 * len(words)
        assert r.base_failed == failed and not (failed and r.kept)
    assert got[7].kept and got[8].kept
    kept = quality_cascade.keep_good(docs)
    assert kept.columns == docs.columns and kept.filter("doc_id is not null").count() == sum(r.kept for r in got.values()) + 1
    assert quality_cascade.judge(empty).count() == 0 and quality_cascade.keep_good(empty).count() == 0


def test_cascade_order_is_by_rejections_per_cost():
    slow = quality_cascade.Rule("slow", lambda t: sum(range(20000)) < 0)
    fast = quality_cascade.Rule("fast", lambda t: True)
    found = quality_cascade.estimate(["a"] * 20, (slow, fast))
    assert max(found, key=lambda e: e.worth).rule is fast


def test_best_fit(spark, docs, empty):
    from tokenizers import Tokenizer

    tok = Tokenizer.from_file(best_fit.tokenizer_path())
    got = best_fit.pack_documents(docs).collect()
    by = defaultdict(list)
    for r in got:
        by[r.doc_id].append(r)
    for k, text, *_ in rows():
        if k is None or k == 4:
            continue
        ids = tok.encode(text or "", add_special_tokens=False).ids + [0]
        ps = sorted(by[k], key=lambda r: r.piece)
        assert [p.piece for p in ps] == list(range(-(-len(ids) // 2048)))
        for p in ps:
            cut = ids[p.start : p.start + p.length]
            assert len(cut) == p.length and p.ids_crc32 == zlib.crc32(struct.pack(f"<{len(cut)}I", *cut))
    seq = defaultdict(list)
    for r in got:
        seq[r.sequence_id].append((r.offset, r.length))
    for parts in seq.values():
        at = 0
        for offset, length in sorted(parts):
            assert offset == at
            at += length
        assert at <= 2048
    assert len(seq) <= -(-sum(r.length for r in got) // 2048) + 1
    assert best_fit.pack_documents(empty).count() == 0


def test_rounds_pack_tightly():
    rng = random.Random(2)
    for _ in range(100):
        capacity = rng.choice([8, 64, 2048])
        h = {rng.randint(1, capacity): rng.randint(1, 50) for _ in range(rng.randint(1, 20))}
        plan = best_fit.plan_rounds(h, capacity)
        seq, made = defaultdict(list), sorted(plan.rows)
        for i, (length, first, sequence, offset) in enumerate(made):
            upto = made[i + 1][1] if i + 1 < len(made) and made[i + 1][0] == length else h[length]
            for r in range(first, upto):
                seq[sequence + r - first].append((offset, length))
        assert sum(map(len, seq.values())) == sum(h.values())
        for parts in seq.values():
            at = 0
            for offset, length in sorted(parts):
                assert offset == at
                at += length
            assert at <= capacity
        assert plan.sequences <= 1.25 * sum(n * c for n, c in h.items()) / capacity + 1 or max(h) * 2 > capacity


def test_chat_snapshots(spark):
    turns = {1: ["a", "b"], 2: ["a", "b", "c"], 3: ["a", "b", "c"], 4: ["a"], 5: ["b", "a"], 6: [None, ""], 7: ["x"] * 300}
    data = [(c, i, None if t is None else "user", t) for c, ts in turns.items() for i, t in enumerate(ts)] + [(None, 0, "user", "lost")]
    df = spark.createDataFrame(data, "conv_id long, turn long, role string, text string").withColumn("pos", F.lit(1))
    got = {r.conv_id: r for r in chat_snapshots.render(df).collect()}
    assert set(got) == {2, 5, 6, 7} and got[2].copies == 2 and got[7].n_turns == 300
    assert got[5].rendered == "<|user|>\nb\n<|end|>\n<|user|>\na\n<|end|>\n"
    assert chat_snapshots.render(df.limit(0)).count() == 0


def test_pipeline_stages(spark):
    import corpus_pipeline as cp

    docs = spark.read.parquet("/root/testdata/sf0.001/documents.parquet")
    good = cp.quality(spark, docs, "")
    assert 0 < good.count() < docs.count() and good.columns == docs.columns
    spoken = cp.language(spark, good.cache(), "")
    one = cp.near_duplicates(spark, spoken.cache(), "")
    assert one.count() == one.select("doc_id").distinct().count() <= spoken.count()
    assert cp.packing(spark, one.limit(20), "").columns[:2] == ["doc_id", "piece"]
