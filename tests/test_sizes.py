"""Paths for long series and large tables, against the plain ones."""

import numpy as np
import pyarrow as pa
import pytest

from seqnorm import workloads
from seqnorm.operators import contig
from seqnorm.operators.living import Params, detect_series, fit_series, offline_series, scan_series


def wave(n, seed=0):
    rng, at = np.random.default_rng(seed), np.arange(n)
    theta = 2 * np.pi * (at % 50) / 50
    kinds = [np.sin(theta) + 0.5 * np.sin(2 * theta), np.sin(theta) + 0.5 * np.sin(3 * theta), 0.4 * np.sin(theta) + np.sin(2 * theta)]
    return np.choose((at * 6 // n) % 3, kinds) + 0.05 * rng.normal(size=n)


@pytest.mark.parametrize("how", [{}, {"delta": 400}, {"warmup": "hold"}, {"distance": "zn"}, {"all_active": True}, {"max_patterns": 2}])
def test_a_scan_in_stretches_scores_as_the_whole_does(how):
    x, p = wave(12000), Params(**how)
    model = fit_series(x[:2400], p)
    whole, cut = detect_series(x, model, p), scan_series(x, model, p, 1500)
    assert np.allclose(whole.score, cut.score, atol=1e-9) and (whole.nearest == cut.nearest).all() and (whole.no_active == cut.no_active).all()
    assert whole.births == cut.births and whole.refused == cut.refused and whole.epochs == cut.epochs and cut.dist.size == 0


def test_offline_scores_need_a_pattern_only_where_it_is_the_nearest():
    x = wave(12000)
    whole, lean = offline_series(x, Params()), offline_series(x, Params(), keep=False)
    assert np.allclose(whole.score, lean.score, atol=1e-9) and lean.dist.size == 0 and lean.evaluations < 2 * len(x)


def test_groups_of_sorted_rows_are_found_whatever_the_batches():
    g, s = np.repeat([0, 0, 3], [5, 4, 6]), ["a"] * 5 + ["b"] * 4 + ["a"] * 6
    whole = pa.RecordBatch.from_pydict({"g": pa.array(g, pa.int32()), "series_id": s, "x": np.arange(15.0), "y": pa.array([0] * 15, pa.int8())})
    for size in (1, 2, 7, 15):
        got = [(k, n, x.tolist()) for k, n, x, _ in workloads._groups(whole.slice(i, size) for i in range(0, 15, size))]
        assert got == [(0, "a", [0, 1, 2, 3, 4]), (0, "b", [5, 6, 7, 8]), (3, "a", [9, 10, 11, 12, 13, 14])]


def test_auc_of_counts_ties_half():
    score, y = np.array([1.0, 2, 2, 3, np.nan]), np.array([0, 1, 0, 1, 1])
    assert workloads.auc_of(score, y) == pytest.approx((1.5 + 2) / 4) and workloads.auc_of(score, y * 0) is None


def test_joins_look_their_place_up_and_not_through_all():
    seen = []

    class Counted(list):
        def index(self, *a):
            seen.append(a)
            return super().index(*a)

    for k in (1, 4):
        a = contig.Agglomeration(np.random.default_rng(2).normal(size=(300, 8)).cumsum(0), k=k)
        a.live = Counted(a.live)
        f = a.run()
        assert not seen and len(f.roots()) == 1 and len(f.roots()[0].members) == 300


def test_batches_in_tasks_of_their_own_score_as_the_series_does(spark):
    from pyspark.sql import functions as F

    from seqnorm.baselines import detectors, kernels

    x = wave(4630)
    pts = spark.createDataFrame([("s", i, float(v)) for i, v in enumerate(x)], "series_id string, pos bigint, x double")
    got = detectors.batch_shape(pts, 50, batch=1000).orderBy("start").toPandas()
    assert got["start"].tolist() == list(range(len(x) - 49)) and np.allclose(got["score"], kernels.batch_shape(x, 50, batch=1000), atol=1e-6)
    tasks = detectors.batch_shape(pts, 50, batch=1000).groupBy(F.spark_partition_id()).count().count()
    assert tasks > 1  # one task for the whole series before


@pytest.mark.parametrize("name", "dissim_matrix op_cross_pivot op_range_join chain_cut_toy".split())
def test_what_was_made_up_comes_from_a_given_table(spark, name):
    import duckdb

    from seqnorm import catalog

    from test_queries import SF, same

    con = duckdb.connect()
    for table in "events lineitem orders".split():
        con.execute(f"create view {table} as select * from '{SF}/{table}.parquet'")
    found = catalog.queries()[name](spark, SF)
    assert found.inputFiles()
    same(found.toPandas(), con.execute(catalog.oracle_sql()[name]).df())


def test_cut_rules_are_those_of_the_branches_of_line_items(spark):
    import duckdb

    from seqnorm import catalog

    from test_queries import SF, same

    con = duckdb.connect()
    con.execute(f"create view lineitem as select * from '{SF}/lineitem.parquet'")
    found = catalog.cut_toy_rules(spark, SF)
    assert found.inputFiles()  # the branches were made up before
    same(found.toPandas(), con.execute(catalog.oracle_sql()["cut_toy_rules"]).df())


@pytest.mark.parametrize("how", [{}, {"delta": 400}, {"warmup": "hold"}, {"distance": "zn"}, {"max_patterns": 2}, {"scan": "lazy"}])
def test_a_stream_is_scored_in_stretches_however_its_points_are_dealt(how, monkeypatch):
    from seqnorm.streaming import detector

    x, p, found, looks = wave(6000), Params(**how), [], []
    look = detector.LiveSeries._bring
    monkeypatch.setattr(detector.LiveSeries, "_bring", lambda self, i, *a: looks.append(i) or look(self, i, *a))
    for cuts in ([6000], [7, 1190, 2100, 2101, 6000]):
        live, rows, lo = detector.LiveSeries(p, 1200, 1500), [], 0
        for hi in cuts:
            for f in live.push_all(np.arange(lo, hi), x[lo:hi]):
                rows += detector._tuples(f)
            lo = hi
        found.append(rows + list(live.flush()))
    assert how.get("scan") or len(looks) < len(x) / 10  # once for each window and pattern before
    a, b = found
    assert len(a) == len(b) and all(u[0] == v[0] and u[2:] == v[2:] and u[1] == pytest.approx(v[1], abs=1e-9) for u, v in zip(a, b))
    whole = detect_series(x, fit_series(x[:1200], p), p)
    scores = [r for r in a if r[4] is None]
    assert np.allclose([r[1] for r in scores], whole.score, atol=1e-7) and [r[2] for r in scores] == whole.nearest.tolist()
    assert [(r[0], r[5]) for r in a if r[4] == "born"] == whole.births


def test_online_scores_without_events_are_those_with_them(spark):
    from seqnorm.operators import detect

    pts = spark.createDataFrame([("s", i, float(v)) for i, v in enumerate(wave(4000))], "series_id string, pos bigint, x double")
    lean, full = detect.online(pts, events=False).toPandas(), detect.scores(detect.online(pts)).toPandas()
    assert lean["event"].isna().all() and len(lean) == len(full) and np.allclose(lean.sort_values("start")["score"], full.sort_values("start")["score"])


def test_discords_hold_the_points_and_not_their_windows():
    import tracemalloc

    from seqnorm.baselines import kernels
    from seqnorm.functions import distance as D

    x = np.r_[wave(3000) + 1e4, np.full(200, 1e4), wave(800, 1) + 1e4]  # far from zero, with flat windows
    ready = D.prepare(D.sliding(x, 50), "zn")
    plain = [0.0 if j < 200 else float(np.sqrt(((ready[: j - 49] - ready[j]) ** 2).sum(1).min())) for j in range(len(ready))]
    assert np.allclose(kernels.backward_discord(x, 50, prune=False), plain, atol=1e-5)
    x = wave(60000)
    tracemalloc.start()
    kernels.backward_discord(x, 50)
    peak = tracemalloc.get_traced_memory()[1]
    tracemalloc.stop()
    assert peak < len(x) * 50 * 8  # all windows were held, more than once, before


def test_a_transformer_scores_blocks_in_tasks_of_their_own(spark):
    from pyspark.sql import functions as F

    from seqnorm.baselines import detectors, kernels

    x = wave(3010)
    rows = [("s", i, float(v)) for i, v in enumerate(x)] + [("short", i, float(i)) for i in range(50)] + [("none", 0, 1.0)]
    pts = spark.createDataFrame(rows, "series_id string, pos bigint, x double")
    found = detectors.transformer(pts, 50, block=500)
    got = found.orderBy("series_id", "start").toPandas()
    long, short = got[got["series_id"] == "s"], got[got["series_id"] == "short"]
    assert long["start"].tolist() == list(range(len(x) - 49)) and np.allclose(long["score"], kernels.transformer_score(x, 50), rtol=1e-4)
    assert short["score"].tolist() == [0.0] and "none" not in set(got["series_id"])
    assert found.filter("series_id = 's'").groupBy(F.spark_partition_id()).count().count() > 1  # one task before


def test_single_precision_scores_as_double_does():
    from seqnorm.baselines import kernels

    x = wave(3000)
    single, double = (kernels.transformer_errors(x, 50, *kernels.transformer_fit(x[:1000], 50, dtype=t)) for t in (np.float32, np.float64))
    assert np.allclose(single, double, rtol=1e-2) and np.corrcoef(single, double)[0, 1] > 0.9999


def test_links_are_worked_out_once_and_contiguous_members_hold_no_memory(monkeypatch):
    rows, seen = np.random.default_rng(2).normal(size=(150, 8)).cumsum(0), []
    real = contig.Agglomeration.distance
    monkeypatch.setattr(contig.Agglomeration, "distance", lambda self, a, b: seen.append((a, b)) or real(self, a, b))
    f = contig.Agglomeration(rows, k=20, repair=False).run()
    assert len(seen) == len(set(seen))  # every pair around a join was worked out anew before
    f = contig.Agglomeration(rows, repair=False).run()
    assert all(isinstance(x.held, range) for x in f.nodes) and f.roots()[0].members == tuple(range(150))


def test_joins_without_time_need_no_list_of_all_pairs():
    from seqnorm.operators import living

    rows = wave(20000).reshape(-1, 100)
    f, found = contig.cluster(rows, k=len(rows), repair=False)
    free = contig.free_forest(rows)
    assert contig.branch_cut(free) == found == living.tree_without_time(rows, Params())
    assert np.allclose([free.nodes[j].height for j in free.order], [f.nodes[j].height for j in f.order])


def test_points_are_packed_and_come_back_in_order_whatever_the_batches():
    rng = np.random.default_rng(4)
    rows = [(s, n, p, 10.0 * p + s, p % 3 - 1 if p % 7 else None) for s in (0, 1) for n in "ab" for p in range(0, 40, 1 + s)]
    rows = [rows[i] for i in rng.permutation(len(rows))]
    kinds = (pa.int32(), pa.string(), pa.int64(), pa.float64(), pa.int8())
    whole = pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*rows), kinds)], ["s", "series_id", "pos", "x", "y"])
    for size in (1, 7, len(rows)):
        packed = pa.Table.from_batches(workloads._pack(whole.slice(i, size) for i in range(0, len(rows), size)))
        assert packed.num_rows <= 4 * -(-len(rows) // size)
        packed = packed.rename_columns(["g", *packed.column_names[1:]]).sort_by([(c, "ascending") for c in ("g", "series_id", "lo")])
        got = list(workloads._groups(workloads._unpack(packed.to_batches(max_chunksize=3))))
        assert [g[:2] for g in got] == [(0, "a"), (0, "b"), (1, "a"), (1, "b")]
        for s, n, x, y in got:
            want = sorted(r[2:] for r in rows if r[:2] == (s, n))
            assert x.tolist() == [r[1] for r in want] and np.array_equal(y.astype(float), [np.nan if r[2] is None else r[2] for r in want], equal_nan=True)
    assert [b.num_rows for b in workloads._pack([whole.slice(0, 0)])] == [0]


def test_offline_scores_hold_little_beyond_the_points():
    import tracemalloc

    x, p = wave(300000), Params(r_min=0.5)
    tracemalloc.start()
    found = offline_series(x, p, keep=False)
    peak = tracemalloc.get_traced_memory()[1]
    tracemalloc.stop()
    assert peak < 8 * x.nbytes  # more than that before
    cut = offline_series(x, p, keep=False, step=1000)
    assert np.allclose(found.score, cut.score, atol=1e-9) and found.evaluations == cut.evaluations


def test_presence_in_stretches_is_that_of_the_whole():
    from seqnorm.operators.living import presence_of

    phi = np.random.default_rng(1).random(5000)
    for mode in ("overlap", "majority", "contain"):
        for members in ([3, 9], [10], [400]):
            whole = presence_of(phi, members, 300, 100, 50, mode, 40)
            assert whole == pytest.approx(presence_of(np.split(phi, [400, 900, 2500]), members, 300, 100, 50, mode, 40), abs=1e-12)


def test_groups_with_the_most_work_come_first_and_in_partitions_of_their_own(spark):
    from pyspark.sql import functions as F

    assert workloads.places([("zm", "offline"), ("zm", "transformer"), ("dtw", "offline"), ("zm", "batch_shape"), ("dtw", "online")]) == [4, 2, 1, 3, 0]
    rows = [("a", n, i, float(v), i % 9 == 0) for n in ("s", "t") for i, v in enumerate(wave(700))]
    frame = spark.createDataFrame(rows, "setting string, series_id string, pos bigint, x double, y_true boolean")
    got = workloads.scored(frame, {"a": Params()}, ("offline", "discord", "online"))
    at = got.select("method", F.spark_partition_id().alias("p")).distinct().toPandas().groupby("method")["p"].agg(["min", "max"])
    assert at["max"]["online"] < at["min"]["discord"] and at["max"]["discord"] < at["min"]["offline"]  # by hash before


def test_shape_distances_need_no_transforms_and_training_no_large_arrays(monkeypatch):
    from seqnorm.baselines import kernels
    from seqnorm.functions import distance as D

    rows, sizes = D.prepare(D.sliding(wave(900), 100), "zn"), []
    full = [[np.correlate(r, rows[7], "full")] for r in rows]
    with monkeypatch.context() as m:
        m.setattr(np.fft, "irfft", lambda *a, **k: pytest.fail("rows were transformed"))
        d, shift = kernels.shape_distances(rows, rows[7])
        kernels.k_shape(rows, 3)
    assert np.allclose(d, [1 - f[0].max() / 100 for f in full]) and shift.tolist() == [int(f[0].argmax()) - 99 for f in full]
    real = kernels.Transformer.passes
    monkeypatch.setattr(kernels.Transformer, "passes", lambda self, x: sizes.append(len(x)) or real(self, x))
    parts = kernels.transformer_fit(wave(400), 50)[0].p
    assert max(sizes) == kernels.PART  # 64 before
    monkeypatch.setattr(kernels, "PART", 64)
    assert all(np.allclose(v, parts[k], atol=1e-3) for k, v in kernels.transformer_fit(wave(400), 50)[0].p.items())


@pytest.mark.parametrize("ell", [1, 2, 3, 20, 50])
def test_warping_tries_no_piece_that_its_ends_rule_out(ell, monkeypatch):
    from seqnorm.functions import distance as D

    x, tried = wave(1200), []
    x[600:700] *= 2.5
    windows, pieces = D.sliding(x, ell)[::7], D.sliding(x[50:150], ell)
    table = D.dtw_table(windows, pieces)
    real = D.dtw_rows
    monkeypatch.setattr(D, "dtw_rows", lambda a, b, *r: tried.append(len(a)) or real(a, b, *r))
    assert np.allclose(D.profile(x, x[50:150], ell, "dtw")[::7], table.min(1), atol=1e-9)
    tried.clear()
    assert np.allclose(D.dtw_least(windows, pieces), table.min(1), atol=1e-9)
    assert ell < 20 or sum(tried) < 0.75 * table.size  # all of them before


@pytest.mark.parametrize("ell", [1, 2, 3, 20, 50])
def test_shape_based_profiles_try_no_shift_that_its_overlap_rules_out(ell, monkeypatch):
    from seqnorm.functions import distance as D

    x = wave(1200)
    x[600:700], x[800:880], x[1000:1100] = x[600:700] * 2.5, 3.0, np.random.default_rng(3).normal(size=100)
    for pattern in (x[50:150], np.r_[x[50:150], np.full(60, 2.0)]):
        table = D.sbd_table(D.sliding(x, ell), D.sliding(pattern, ell))
        assert np.allclose(D.profile(x, pattern, ell, "sbd"), table.min(1), atol=1e-9)
    monkeypatch.setattr(D, "sbd_table", lambda *a: pytest.fail("all shifts of all pieces were tried"))
    assert ell < 20 or len(D.profile(x[:500], x[50:150], ell, "sbd")) == 501 - ell


@pytest.mark.parametrize("block", [4096, 37])
def test_every_pair_of_vectors_has_a_distance(spark, block, monkeypatch):
    import duckdb

    from seqnorm import catalog

    from test_queries import SF, same

    monkeypatch.setattr(catalog, "ROW_BLOCK", block)  # few blocks and many
    con = duckdb.connect()
    con.execute(f"create view v as select vec_id, embedding::double[] as e, list_avg(embedding::double[]) as m from '{SF}/embeddings.parquet'")
    asked = "select a.vec_id as a, b.vec_id as b, sqrt(list_sum([((a.e[i] - a.m) - (b.e[i] - b.m)) ** 2 for i in range(1, 65)])) as d from v a join v b on a.vec_id < b.vec_id"
    got = catalog.queries()["dist_emb_zm_all"](spark, SF).toPandas().sort_values(["a", "b"])
    want = con.execute(asked).df().sort_values(["a", "b"])
    same(got[["a", "b"]], want[["a", "b"]])  # every 50th vector as a, before
    assert len(got) == 500 * 499 // 2 and np.allclose(got["dist"], want["d"], atol=1e-4)


def test_static_scores_make_windows_ready_once_for_all_shapes(monkeypatch):
    from seqnorm.baselines import kernels
    from seqnorm.functions import distance as D

    x, seen, prepare = wave(5000), [], D.prepare
    shapes, weights = [x[a : a + 100] for a in range(0, 4000, 200)], np.arange(1.0, 21) / 210
    want = kernels.centred_mean(sum(w * D.profile(x, s, 50, "zn") for s, w in zip(shapes, weights)), 50)
    monkeypatch.setattr(D, "prepare", lambda v, kind: seen.append(len(v)) or prepare(v, kind))
    assert np.allclose(kernels.static_score(x, shapes, weights, 50, 700), want, atol=1e-9)
    assert sum(seen) == len(x) - 49 + 51 * len(shapes)  # all windows for each shape before


@pytest.mark.parametrize("change", [lambda x: x, lambda x: x * 1e6 + 3e7, lambda x: np.where(np.arange(len(x)) % 97 == 0, 1e4, x), lambda x: np.round(x, 1), lambda x: x * 0])
def test_single_precision_finds_the_piece_and_double_gives_its_distance(change, monkeypatch):
    from seqnorm.functions import distance as D

    x = change(wave(3000))
    windows, pieces, double, rows = D.sliding(x[500:1100], 50), D.sliding(wave(1000).reshape(-1, 100).mean(0), 50), [], D.dtw_rows
    whole = D.dtw_table(np.array(windows), pieces).min(1)
    monkeypatch.setattr(D, "dtw_rows", lambda a, b, *r: double.append(len(a)) or rows(a, b, *r))
    assert np.allclose(D.dtw_least(windows, pieces), whole, rtol=1e-12, atol=1e-12 * abs(x).max())
    if np.allclose(x, wave(3000)):
        assert sum(double) < 5 * len(windows)  # every piece that its bounds let through, before


def test_training_and_births_compare_many_shapes_at_a_time(monkeypatch):
    from seqnorm.functions import distance as D
    from seqnorm.operators import living

    rows, one = wave(1000).reshape(-1, 100), {k: D.named(k) for k in ("sbd", "dtw")}
    for kind, f in one.items():
        assert np.allclose(D.to_shape(rows, rows[0], kind), [f(r, rows[0]) for r in rows], atol=1e-9)
        monkeypatch.setitem(D._NAMED, kind, None)  # one pair at a time in Python, before
    for kind in one:
        p = Params(distance=kind)
        model = fit_series(wave(3000), p)
        assert model.patterns and not living.accept(model.patterns[0], model, p)
