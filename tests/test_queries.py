"""Queries against DuckDB, plans, and the paths that must agree."""

import duckdb
import numpy as np
import pytest
from pyspark.sql import functions as F

from seqnorm import catalog
from seqnorm.functions import distance as D
from seqnorm.operators import contig, detect, metrics, model, segment
from seqnorm.operators.living import Params
from seqnorm.sources import points as P
from seqnorm.sources import sinks

SF = "/root/testdata/sf0.01"
SOME = (
    "points_hourly gapfill_orders_linear windows_hourly segments_daily dist_min_place link_ward chain_cut_toy cut_toy_rules tau_fixed freq_majority_fixed"
    " active_flags_trained drift_events_hourly score_trailing_min score_offline_nearest_time label_radius alarms_per_series admit_both auc_carrier roc_points"
    " dist_dtw_small ca_ward_norepair_daily ca_rounds_daily anom_dissim op_agg_stats label_quantile auc_binned stability auc_doc_toxic gapfill_orders_ffill"
    " inj_gradual inj_place_rayleigh by_region op_asof_nearest op_range_join op_islands op_session stream_hourly"
    " gapfill_hourly_linear stream_detect_equals_batch stream_late_count"
).split()


@pytest.fixture(scope="module")
def duck():
    con = duckdb.connect()
    for t in "events lineitem orders documents labels pages conversations embeddings".split():
        con.execute(f"create view {t} as select * from '{SF}/{t}.parquet'")
    return con


def same(a, b):
    key = lambda r: tuple(repr(float(v)) if isinstance(v, (int, float, np.number)) and not isinstance(v, bool) else str(v) for v in r)
    cols = sorted(a.columns)
    assert cols == sorted(b.columns)
    clean = lambda f: sorted(map(key, f[cols].astype(object).where(f[cols].notna(), None).values.tolist()))
    assert clean(a) == clean(b)


@pytest.mark.parametrize("name", SOME)
def test_against_sql(spark, duck, name):
    same(catalog.queries()[name](spark, SF).toPandas(), duck.execute(catalog.oracle_sql()[name]).df())


def test_catalog_is_consistent():
    assert set(catalog.oracle_sql()) <= set(catalog.queries()) and len(catalog.queries()) > 160


def test_whole_tables_reach_the_distances_and_joins(spark, duck):
    v = {r.vec_id: np.array(r.embedding, float) for r in spark.read.parquet(f"{SF}/embeddings.parquet").collect()}
    asked = [i for i in v if i % 50 == 0]  # queries, each against every other row
    pairs = {(a, b) for a in asked for b in v if a != b}
    for kind, every in (("zm", 25), ("zn", 25), ("sbd", 25), ("dtw", 500)):
        got = catalog.queries()[f"dist_emb_{kind}_all"](spark, SF).toPandas()
        assert len(got) == len(pairs) and set(zip(got["a"], got["b"])) == pairs
        for a, b, dist in got.iloc[::every].itertuples(index=False):
            assert dist == pytest.approx(D.named(kind)(v[a], v[b]), abs=1e-4)
    got = catalog.queries()["op_range_join_lineitem"](spark, SF).toPandas()
    same(got, duck.execute("""with b as (select l_orderkey, l_linenumber, date_diff('day', date '1970-01-01', cast(l_shipdate as date)) as b_lo, date_diff('day', date '1970-01-01', cast(l_shipdate as date)) + cast(l_quantity as bigint) - 1 as b_hi from lineitem)
        select w * 7 as a_lo, w * 7 + 6 as a_hi, b.* from b, unnest(range(b_lo // 7, b_hi // 7 + 1)) t(w)""").df())
    days, marks = P.daily_lineitem(spark, SF).toPandas(), P.daily_orders(spark, SF).filter("x > 0").toPandas()
    got = catalog.queries()["op_asof_backward_all"](spark, SF).toPandas().sort_values("pos")
    at = np.searchsorted(np.sort(marks["pos"]), got["pos"], "right") - 1
    want = marks.sort_values("pos")["x"].to_numpy()[at]
    assert len(got) == len(days) and np.allclose(got["mark"].to_numpy(float)[at >= 0], want[at >= 0], atol=0.01)


def test_batch_blocks_and_series_agree(spark):
    pts = catalog._drifting(spark, SF).cache()
    p = Params(births=False)
    pats = model.fit(pts, p).cache()
    whole = detect.scores(detect.batch(pts, pats, p)).toPandas().sort_values("start")
    for block in (3000, 4096):
        cut = detect.in_blocks(pts, pats, p, block).toPandas().sort_values("start")
        assert (whole["start"].to_numpy() == cut["start"].to_numpy()).all()
        assert np.allclose(whole["score"].to_numpy(), cut["score"].to_numpy(), atol=1e-6)


def test_giant_positions_use_no_single_partition(spark):
    e = P.table(spark, SF, "events").select("event_id", "value")
    out = segment.assign_pos_giant(e, "event_id", parts=5)
    assert "SinglePartition" not in out._jdf.queryExecution().executedPlan().toString()
    assert out.filter(F.col("pos") != F.col("event_id")).count() == 0


def test_scan_is_pruned_and_pushed(spark):
    df = P.read_points(spark, f"{SF}/events.parquet", "event_type", "event_id", "value", "event_id < 500")
    plan = df._jdf.queryExecution().executedPlan().toString()
    assert "LessThan(event_id,500)" in plan and "props" not in plan


def test_rounds_join_what_the_heap_joins_without_inversions(spark):
    rows = [("s", i, [float(v), float(v), 0.0]) for i, v in enumerate([0, 0.1, 5, 5.2, 5.1, 9, 9.3, 20])]
    df = spark.createDataFrame(rows, "series_id string, seg int, xs array<double>")
    got = contig.agglomerate_rounds(df, stop_height=2.0).select("seg_lo", "seg_hi").collect()
    f = contig.Agglomeration(np.array([[a - np.mean(r[2]) for a in r[2]] for r in rows]), repair=False, stop_height=2.0).run()
    assert sorted((r.seg_lo, r.seg_hi) for r in got) == sorted((x.lo, x.hi) for x in f.roots())


def test_rounds_go_on_until_the_asked_number_is_left(spark):
    flat = [("flat", i, [1.0, 2.0, 4.0]) for i in range(150)]
    ramp = [("ramp", i, [0.0, float(i)]) for i in range(150)]
    fall = [("fall", i, [0.0, float(v)]) for i, v in enumerate(np.cumsum(np.arange(12, 0, -1) ** 2))]
    df = spark.createDataFrame(flat + ramp + fall, "series_id string, seg int, xs array<double>")
    for stop in (1, 7):
        got = contig.agglomerate_rounds(df, stop_clusters=stop).toPandas()
        for name, n in (("flat", 150), ("ramp", 150), ("fall", 12)):
            g = got[got["series_id"] == name].sort_values("seg_lo")
            assert len(g) == stop and g["n"].sum() == n and (g["seg_hi"] - g["seg_lo"] + 1 == g["n"]).all()


def test_truth_and_auc(spark):
    pts = spark.createDataFrame([("s", i, int(i in (5, 6))) for i in range(12)], "series_id string, pos long, y_true int")
    y = {r.start: r.y for r in metrics.window_truth(pts, 3).collect()}
    assert y == {i: int(3 <= i <= 6) for i in range(10)}
    d = spark.createDataFrame([(float(s), y) for s, y in ((1, 0), (2, 1), (2, 0), (3, 1))], "score double, y int")
    assert metrics.auc(d).first().auc == pytest.approx(0.875)
    assert metrics.auc(d.withColumn("score", -F.col("score"))).first().auc == pytest.approx(0.125)


def test_upsert_is_idempotent(spark, tmp_path):
    df = spark.createDataFrame([("s", i, float(i)) for i in range(5)], "series_id string, start long, score double")
    put = sinks.upsert_scores(str(tmp_path / "scores"))
    put(df, 0)
    put(df, 0)
    assert spark.read.parquet(str(tmp_path / "scores")).count() == 5
