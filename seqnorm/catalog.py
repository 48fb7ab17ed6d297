"""Queries over the given tables, one for each method, measure, injector, workload and operator."""

from __future__ import annotations

from collections.abc import Callable, Iterator

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import Window

from seqnorm import oracles, workloads
from seqnorm.baselines import detectors
from seqnorm.functions import distance as D
from seqnorm.operators import contig, detect, inject, metrics, model, relational, score, segment
from seqnorm.operators.living import Params
from seqnorm.session import materialise, scratch
from seqnorm.sources import points as P

ELL, ELL_M, WIN = 24, 48, 24  # hourly series: a day, two days, a day of window starts
Query = Callable[[SparkSession, str], DataFrame]


def rounded(df: DataFrame, *names: str, digits: int = 4) -> DataFrame:
    return df.withColumns({n: F.round(F.col(n), digits) for n in names})


# -- sources, windows, distances ---------------------------------------------------------------------


def _points() -> dict[str, Query]:
    make = {
        "points_events": P.events, "points_hourly": P.hourly, "points_daily_lineitem": P.daily_lineitem, "points_daily_orders": P.daily_orders,
        "points_by_type": P.by_type, "points_by_user": P.by_user, "points_doc_len": P.doc_lengths, "points_page_len": P.page_lengths, "points_turn_len": P.turn_lengths,
    }
    out: dict[str, Query] = {k: (lambda s, d, f=f: rounded(f(s, d), "x")) for k, f in make.items()}
    for policy in ("zero", "ffill", "linear"):
        out[f"gapfill_orders_{policy}"] = lambda s, d, p=policy: rounded(P.daily(s, d, "orders", "o_orderdate", "o_totalprice", p).select("pos", "x"), "x")
        out[f"gapfill_hourly_{policy}"] = lambda s, d, p=policy: rounded(P.hourly(s, d, p).select("pos", "x"), "x")
    return out


def windows_hourly(s: SparkSession, d: str) -> DataFrame:
    return rounded(rounded(segment.window_stats(P.hourly(s, d), ELL), "mean", "sd", digits=6), "energy").select("start", "mean", "sd", "energy")


def windows_by_type(s: SparkSession, d: str) -> DataFrame:
    return rounded(segment.window_stats(P.by_type(s, d), 50), "mean", "sd", digits=3).select("series_id", "start", "mean", "sd")


def _segment_norms(df: DataFrame) -> DataFrame:
    return rounded(df.select("seg", "start", F.element_at("xs", 1).alias("first"), segment.centred_norms(df).alias("norm")), "first", "norm")


def segments_hourly(s: SparkSession, d: str) -> DataFrame:
    return _segment_norms(segment.segments(P.hourly(s, d), ELL_M))


def segments_daily(s: SparkSession, d: str) -> DataFrame:
    return _segment_norms(segment.segments(P.daily_lineitem(s, d), 14))


def blocks_equal_windows(s: SparkSession, d: str) -> DataFrame:
    """Windows cut from blocks: the same as windows over the whole series."""
    b = segment.blocks(P.hourly(s, d), 100, ELL - 1)
    w = b.select("block_id", "start_pos", F.explode(F.sequence(F.lit(0), F.size("xs") - ELL)).alias("i"), "xs").filter(F.size("xs") >= ELL)
    w = w.filter(F.floor((F.col("start_pos") + F.col("i")) / 100) == F.col("block_id"))
    return rounded(w.select((F.col("start_pos") + F.col("i")).alias("start"), D.mean_of(F.slice("xs", F.col("i") + 1, ELL)).alias("mean")), "mean", digits=6)


def _vector_pairs(s: SparkSession, d: str, n: int) -> DataFrame:
    v = P.vectors(s, d).filter(F.col("start") < n)
    a, b = v.select(F.col("start").alias("a"), F.col("xs").alias("xa")), v.select(F.col("start").alias("b"), F.col("xs").alias("xb"))
    return a.join(b, F.col("a") < F.col("b"))


def dist_emb_zm(s: SparkSession, d: str) -> DataFrame:
    return rounded(_vector_pairs(s, d, 20).select("a", "b", D.zm_col(F.col("xa"), F.col("xb")).alias("dist")), "dist")


def dist_emb_zn(s: SparkSession, d: str) -> DataFrame:
    return rounded(_vector_pairs(s, d, 20).select("a", "b", D.zn_col(F.col("xa"), F.col("xb")).alias("dist")), "dist")


def dist_sbd_emb(s: SparkSession, d: str) -> DataFrame:
    from seqnorm.functions import registry

    registry.register(s)
    return rounded(_vector_pairs(s, d, 8).select("a", "b", F.call_udf("sbd_dist", "xa", "xb").alias("dist")), "dist")


def dist_dtw_small(s: SparkSession, d: str) -> DataFrame:
    from seqnorm.functions import registry

    registry.register(s)
    return rounded(_vector_pairs(s, d, 8).select("a", "b", F.call_udf("dtw_dist", "xa", "xb").alias("dist")), "dist")


QUERY_EVERY, ROW_BLOCK, QUERY_BLOCK = 50, 4096, 512


def dist_emb_zm_all(s: SparkSession, d: str) -> DataFrame:
    """Distances of every pair of vectors of the whole table, the smaller number first.

    Vectors are dealt to blocks by a hash of their numbers, and every two blocks meet in one group, which gives its pairs out
    piece by piece: a task holds two blocks and a piece, whatever the table's size."""
    import numpy as np
    import pyarrow as pa

    from seqnorm.session import ship

    ship(s)
    v = P.vectors(s, d)
    n = v.count()
    blocks = max(1, -(-n // ROW_BLOCK), min(8, n // 256))
    own, other = F.pmod(F.xxhash64("start"), F.lit(blocks)).cast("int"), F.explode(F.sequence(F.lit(0), F.lit(blocks - 1)))
    dealt = v.select(own.alias("own"), F.col("start").alias("id"), "xs").select("own", other.alias("other"), "id", "xs")
    dealt = dealt.select(F.least("own", "other").alias("i"), F.greatest("own", "other").alias("j"), "own", "id", "xs")

    def distances(batches):  # noqa: ANN001, ANN202
        got = [(b.column("i")[0].as_py(), b.column("j")[0].as_py(), b.column("own").to_numpy(), b.column("id").to_numpy(), np.stack(b.column("xs").to_numpy(zero_copy_only=False))) for b in batches if b.num_rows]
        one = got[0][0] == got[0][1]
        side, ids, xs = (np.concatenate(c) for c in list(zip(*got))[2:])
        left, right = (side == k for k in got[0][:2])
        (a, x), (b, y) = ((ids[k], D.prepare(xs[k], "zm")) for k in (left, right))
        step = max(1, (1 << 20) // max(1, len(b)))
        for at in range(0, len(a), step):
            p = a[at : at + step, None]
            keep = p < b if one else p != b  # a block meets itself once
            yield pa.RecordBatch.from_arrays([pa.array(np.minimum(p, b)[keep]), pa.array(np.maximum(p, b)[keep]), pa.array(np.round(D._euclid(x[at : at + step], y)[keep], 4))], ["a", "b", "dist"])

    distances.__annotations__ = {"batches": Iterator[pa.RecordBatch], "return": Iterator[pa.RecordBatch]}  # tells Spark to take pieces
    # a group is few bytes and much work: the planner would merge them
    met = dealt.repartition(8 * s.sparkContext.defaultParallelism, "i", "j").groupBy("i", "j")
    return met.applyInArrow(distances, "a bigint, b bigint, dist double")


def _search(kind: str) -> Query:
    """Distances of the vectors whose number is divisible by 50, as queries a, to every other vector b of the table.

    Blocks of queries meet blocks of rows, each pair of blocks in one group, so neither side has to fit anywhere as a whole."""

    def run(s: SparkSession, d: str) -> DataFrame:
        import numpy as np
        import pyarrow as pa

        from seqnorm.session import ship

        ship(s)
        # read anew for each side, as Spark can't tell the columns of one side from the other's otherwise
        v = lambda: P.vectors(s, d).select(F.col("start").alias("id"), "xs")
        q = lambda: v().filter(F.col("id") % QUERY_EVERY == 0)
        i, j = F.floor(F.col("id") / ROW_BLOCK).alias("i"), F.floor(F.col("id") / (QUERY_EVERY * QUERY_BLOCK)).alias("j")
        rows = v().select(i, "id", "xs").crossJoin(F.broadcast(q().select(j).distinct()))
        queries = q().select(j, "id", "xs").crossJoin(F.broadcast(v().select(i).distinct()))

        def numbers(t: pa.Table) -> tuple[np.ndarray, np.ndarray]:
            return t.column("id").to_numpy(), np.stack(t.column("xs").to_numpy())

        def distances(left: pa.Table, right: pa.Table) -> pa.Table:
            if not left.num_rows or not right.num_rows:
                return pa.table({"a": pa.array([], pa.int64()), "b": pa.array([], pa.int64()), "dist": pa.array([], pa.float64())})
            (a, x), (b, y) = numbers(left), numbers(right)
            if kind in ("zm", "zn"):
                dist = D._euclid(D.prepare(x, kind), D.prepare(y, kind))
            else:  # transforms of 32,768 pairs at a time
                dist = D.dtw_table(x, y) if kind == "dtw" else D.sbd_table(x, y, max(1, (1 << 15) // len(y)))
            other = (a[:, None] != b[None, :]).ravel()
            return pa.table({"a": np.repeat(a, len(b))[other], "b": np.tile(b, len(a))[other], "dist": np.round(dist.ravel()[other], 4)})

        parts = 8 * s.sparkContext.defaultParallelism  # a group is few bytes and much work: the planner would merge them
        left, right = (f.repartition(parts, "i", "j").groupBy("i", "j") for f in (queries, rows))
        return left.cogroup(right).applyInArrow(distances, "a bigint, b bigint, dist double")

    return run


def _day_pairs(s: SparkSession, d: str) -> DataFrame:
    g = segment.segments(P.hourly(s, d), ELL)
    return g.select(F.col("seg").alias("a"), F.col("xs").alias("xa")).join(g.select(F.col("seg").alias("b"), F.col("xs").alias("xb")), F.col("b") == F.col("a") + 1)


def dist_zm_pairs(s: SparkSession, d: str) -> DataFrame:
    return rounded(_day_pairs(s, d).select("a", "b", D.zm_col(F.col("xa"), F.col("xb")).alias("dist")), "dist")


def dist_zn_pairs(s: SparkSession, d: str) -> DataFrame:
    return rounded(_day_pairs(s, d).select("a", "b", D.zn_col(F.col("xa"), F.col("xb")).alias("dist")), "dist")


def dist_min_place(s: SparkSession, d: str) -> DataFrame:
    """Each day against the piece of two days that begins a day before it."""
    pts = P.hourly(s, d)
    days = segment.segments(pts, ELL).select("seg", "xs")
    two = segment.segments(pts, ELL_M).select(F.col("seg").alias("pattern"), F.col("xs").alias("long"))
    j = days.join(two, F.col("pattern") == F.floor(F.col("seg") / 2) - 1)
    return rounded(j.select("seg", "pattern", D.min_place_col(F.col("long"), F.col("xs")).alias("dist")), "dist")


# -- linkage and clustering --------------------------------------------------------------------------


def _links(kind: str) -> Query:
    def run(s: SparkSession, d: str) -> DataFrame:
        """Linkage of neighbouring groups of five segments."""
        import numpy as np
        import pandas as pd

        from seqnorm.functions.linkage import Stats, link

        def kernel(g: pd.DataFrame) -> pd.DataFrame:
            g = g.sort_values("seg")
            rows = D.prepare(np.stack(g["xs"].to_numpy()).astype(float), "zm")
            groups = [list(range(i, i + 5)) for i in range(0, len(rows) - 4, 5)]
            stats = [Stats(len(m), rows[m].sum(0), m) for m in groups]
            return pd.DataFrame({"grp": range(len(groups) - 1), "dist": [round(link(kind, a, b, rows), 4) for a, b in zip(stats, stats[1:])]})

        return segment.segments(P.hourly(s, d), ELL_M).groupBy("series_id").applyInPandas(kernel, "grp long, dist double")

    return run


def adjacent_gap_links(s: SparkSession, d: str) -> DataFrame:
    """Ward distance of neighbouring segments, by one window pass."""
    g = segment.segments(P.daily_lineitem(s, d), 14).withColumn("c", D.centred(F.col("xs")))
    nxt = F.lead("c").over(Window.partitionBy("series_id").orderBy("seg"))
    return rounded(g.withColumn("n", nxt).filter("n is not null").select("seg", D.euclid(F.col("c"), F.col("n")).alias("dist")), "dist", digits=2)


# The heights of two branches of the worked examples.
TOY_HEIGHTS = {1: (0.13, 0.23, 0.55, 26.12, 145.0), 13: (1.11, 2.58, 13.72, 4.2, 145.0)}  # of the worked example


def _chain(s: SparkSession, d: str, rows: Callable[[contig.Forest], list[tuple]], schema: str) -> DataFrame:
    """Rows made of the forest of the daily segments' neighbour distances, joined by boundary linkage until four clusters are left."""
    import numpy as np
    import pandas as pd

    from seqnorm.session import ship

    ship(s)
    names = [c.split()[0].strip("`") for c in schema.split(", ")]

    def run(g: pd.DataFrame) -> pd.DataFrame:
        links = g.sort_values("seg")["dist"].to_numpy(float)
        near = lambda a, b: links[max(a[0], b[0]) - 1] if max(a[0], b[0]) - min(a[-1], b[-1]) == 1 else 1e300
        f = contig.Agglomeration(np.zeros((len(links) + 1, 1)), linker=near, repair=False, stop_clusters=4).run()
        return pd.DataFrame(rows(f), columns=names)

    g = segment.segments(P.daily_lineitem(s, d), 14).withColumn("c", D.centred(F.col("xs")))
    nxt = F.lead("c").over(Window.partitionBy("series_id").orderBy("seg"))
    links = g.withColumn("n", nxt).filter("n is not null").select("series_id", "seg", D.euclid(F.col("c"), F.col("n")).alias("dist"))
    return links.groupBy("series_id").applyInPandas(run, schema)


def chain_cut_toy(s: SparkSession, d: str) -> DataFrame:
    """The joins of the daily segments' chain."""
    rows = lambda f: [(step, x.lo, x.hi, float(x.height)) for step, x in enumerate(f.nodes[j] for j in f.order)]
    return rounded(_chain(s, d, rows, "step int, lo int, hi int, height double"), "height", digits=2)


def cut_toy_rules(s: SparkSession, d: str) -> DataFrame:
    """The limits of every cut rule at every step of the branch of each daily segment in their chain, and whether it cuts there."""

    def rows(f: contig.Forest) -> list[tuple]:
        out = []
        for seed in range(f.n_leaves):
            h, up = [], f.nodes[seed].parent
            while up >= 0:
                h.append(float(f.nodes[up].height))
                up = f.nodes[up].parent
            for rule in ("mean_jump", "running_mean", "mean_plus_std", "printed"):
                limits = [contig.jump_limit(h, rule, at) for at in range(len(h) - 1)]
                out += [(seed, rule, at + 1, limit, bool(h[at + 1] - h[at] > limit)) for at, limit in enumerate(limits)]
        return out

    return rounded(_chain(s, d, rows, "seed int, rule string, step int, limit double, cut boolean"), "limit", digits=2)


def _ca(repair: bool, k: int) -> Query:
    return lambda s, d: rounded(contig.agglomerate(segment.segments(P.daily_lineitem(s, d), 14), repair=repair, k=k).select("node", "lo_seg", "hi_seg", "n", "height", "reverted"), "height", digits=2)


def ca_rounds_daily(s: SparkSession, d: str) -> DataFrame:
    """Rounds of locally closest pairs until twenty clusters are left."""
    return contig.agglomerate_rounds(segment.segments(P.daily_lineitem(s, d), 14), stop_clusters=20).select("cluster_id", "seg_lo", "seg_hi", "n")


def ca_clusters_daily(s: SparkSession, d: str) -> DataFrame:
    return contig.clusters(segment.segments(P.daily_lineitem(s, d), 14)).select("cluster_id", "seg")


# -- the fixed model on the hourly series ------------------------------------------------------------


class Fixed:
    """Three patterns from runs of five segments of the hourly series; test radius and eta as the oracle queries have them."""

    def __init__(self, s: SparkSession, d: str):
        self.points = P.hourly(s, d)
        self.segments = segment.segments(self.points, ELL_M)
        self.clusters = self.segments.filter("seg < 15").select("series_id", F.floor(F.col("seg") / 5).cast("int").alias("cluster_id"), "seg")
        self.patterns = model.centroids(self.clusters, self.segments).withColumnRenamed("cluster_id", "pattern_id")
        self.spans = model.spans(self.clusters, ELL_M)
        blocks = segment.blocks(self.points, 256, ELL - 1)
        self.profile = materialise(score.profile_blocks(blocks, self.patterns, ELL, 256), "profile")

    def taus(self) -> DataFrame:
        return model.radius_sub(self.profile, self.spans, ELL, 0.0)

    def member(self, freq: float | None = None) -> DataFrame:
        taus = self.taus()
        with_phi = self.profile.join(taus, ["series_id", "pattern_id"]).withColumn("phi", D.phi_col(F.col("d"), F.col("tau"), 10.0 / F.col("tau")))
        if freq is not None:
            return with_phi.withColumn("freq", F.lit(freq))
        return with_phi.join(model.presence(with_phi, self.spans, WIN, ELL), ["series_id", "pattern_id"])

    def active(self, freq: float | None = 0.6, ahead: int = 0) -> DataFrame:
        return score.with_activity(self.member(freq), WIN, ahead)


def centroids_fixed(s: SparkSession, d: str) -> DataFrame:
    p = Fixed(s, d).patterns
    return rounded(p.select("pattern_id", F.posexplode("pattern").alias("i", "v")), "v", digits=6)


def tau_fixed(s: SparkSession, d: str) -> DataFrame:
    f = Fixed(s, d)
    literal = model.radius(f.clusters, f.segments, f.patterns.withColumnRenamed("pattern_id", "cluster_id"), 3.0).select(F.col("cluster_id").alias("pattern_id"), F.col("tau").alias("tau_segment"))
    return rounded(literal.join(f.taus(), "pattern_id").select("pattern_id", "tau_segment", F.col("tau").alias("tau_sub")), "tau_segment", "tau_sub")


def win_fixed(s: SparkSession, d: str) -> DataFrame:
    return model.window_len(Fixed(s, d).clusters, ELL, ELL_M, 20).select("win")


def _freq(mode: str) -> Query:
    def run(s: SparkSession, d: str) -> DataFrame:
        """Clusters of unequal length, so that the modes differ: segments 0, 1 to 9, 10 to 14 for the spans."""
        f = Fixed(s, d)
        seg = F.col("seg")
        uneven = f.segments.filter("seg < 15").select("series_id", F.when(seg < 1, 0).when(seg < 10, 1).otherwise(2).alias("cluster_id"), "seg")
        return rounded(model.presence(f.member(0.6).drop("freq"), model.spans(uneven, ELL_M), WIN, ELL, mode).select("pattern_id", "freq"), "freq")

    return run


def unclustered_fixed(s: SparkSession, d: str) -> DataFrame:
    """Segments of clusters below the least size, for clusters of 1, 9 and 5 segments and a share of 0.2."""
    seg = F.col("seg")
    uneven = segment.segments(P.hourly(s, d), ELL_M).filter("seg < 15").select("series_id", F.when(seg < 1, 0).when(seg < 10, 1).otherwise(2).alias("cluster_id"), "seg")
    return model.filter_small(uneven, 0.2)[1].select("cluster_id", "seg")


def phi_hourly(s: SparkSession, d: str) -> DataFrame:
    return rounded(Fixed(s, d).member(0.6).select("start", "pattern_id", "d", "phi"), "d", "phi")


def phi_avg_hourly(s: SparkSession, d: str) -> DataFrame:
    return rounded(Fixed(s, d).active().select("start", "pattern_id", "phi_avg"), "phi_avg")


def active_flags_hourly(s: SparkSession, d: str) -> DataFrame:
    return Fixed(s, d).active().select("start", "pattern_id", "active")


def active_flags_trained(s: SparkSession, d: str) -> DataFrame:
    return Fixed(s, d).active(None).select("start", "pattern_id", "active")


def active_delta_hourly(s: SparkSession, d: str) -> DataFrame:
    return Fixed(s, d).active(0.6, 12).select("start", "pattern_id", "active")


def drift_events_hourly(s: SparkSession, d: str) -> DataFrame:
    return score.drift_events(Fixed(s, d).active()).select("pos", "kind", "pattern_id")


def score_nearest_active(s: SparkSession, d: str) -> DataFrame:
    return rounded(score.nearest_active(Fixed(s, d).active()).select("start", "nearest", "d", "no_active"), "d")


def score_no_active_fallback(s: SparkSession, d: str) -> DataFrame:
    return rounded(score.nearest_active(Fixed(s, d).active()).filter("no_active").select("start", "nearest", "d"), "d")


def score_trailing_min(s: SparkSession, d: str) -> DataFrame:
    return rounded(score.trailing_min(Fixed(s, d).active(), ELL).select("start", "score"), "score")


def score_centered(s: SparkSession, d: str) -> DataFrame:
    return rounded(score.trailing_min(Fixed(s, d).active(), ELL, "centered").select("start", "score"), "score")


def score_weighted_sum(s: SparkSession, d: str) -> DataFrame:
    f = Fixed(s, d)
    w = f.patterns.select("series_id", "pattern_id", ((F.col("pattern_id") + 1) / 6.0).alias("weight"))
    return rounded(score.weighted_sum(f.profile, w).select("start", "score"), "score")


def score_offline_nearest_time(s: SparkSession, d: str) -> DataFrame:
    """Members are the even segments of each run; a window goes to the pattern of the member nearest in time."""
    f = Fixed(s, d)
    owners = f.clusters.filter("seg % 2 = 0").select("series_id", F.col("cluster_id").alias("pattern_id"), "seg")
    return rounded(score.offline_nearest(f.profile, owners, ELL, ELL_M).select("start", "nearest", "score"), "score")


def _labelled(mode: str, **how) -> Query:
    def run(s: SparkSession, d: str) -> DataFrame:
        f = Fixed(s, d)
        sc = score.trailing_min(f.active(), ELL)
        pats = f.taus() if mode == "radius" else None
        return score.label(sc, mode, patterns=pats, **how).select("start", F.col("label").cast("int").alias("label"))

    return run


def alarms_per_series(s: SparkSession, d: str) -> DataFrame:
    sc = score.trailing_min(Fixed(s, d).active(), ELL)
    return rounded(score.alarms(sc, 5, ELL).select("rank", "start", "score"), "score")


def _admission(column: str) -> Query:
    def run(s: SparkSession, d: str) -> DataFrame:
        """Every fifth segment as a candidate, half as frequent as its number says; the fixed model with small radii."""
        f = Fixed(s, d)
        cand = f.segments.filter("seg % 5 = 0 and seg < 15").select("series_id", F.col("seg").alias("cand"), F.col("xs").alias("pattern"), (F.col("seg") / 20.0).alias("freq"))
        own = f.patterns.withColumns({"tau": 1400.0 + 100.0 * F.col("pattern_id"), "freq": 0.1 * (F.col("pattern_id") + 1)})
        out = score.admit(cand, own)
        return out.select("cand", column)

    return run


# -- detectors on carriers ---------------------------------------------------------------------------


def _drifting(s: SparkSession, d: str) -> DataFrame:
    """A, B, A, C with scale anomalies; C is never seen in training."""
    n = workloads._n(s, d)
    concept = F.when(F.col("pos") < n // 10, 0).when(F.col("pos") < n // 5, 1).when(F.col("pos") < n * 3 // 5, 0).otherwise(2)
    return inject.scale(workloads.heart(s, d, concept), 0.03)


def fit_events(s: SparkSession, d: str) -> DataFrame:
    p = model.fit(_drifting(s, d), Params())
    return rounded(p.select("pattern_id", "tau", "freq", "norm", "n_members", "first_pos", "last_pos", "win"), "tau", "freq", "norm")


def detect_online_carrier(s: SparkSession, d: str) -> DataFrame:
    return rounded(detect.online(_drifting(s, d), Params()).select("start", "score", "nearest", "no_active", "event", "pattern_id"), "score")


def detect_offline_carrier(s: SparkSession, d: str) -> DataFrame:
    return rounded(detect.scores(detect.offline(_drifting(s, d), Params())).select("start", "score", "nearest"), "score")


def detect_blocks_carrier(s: SparkSession, d: str) -> DataFrame:
    """A fixed model over blocks with halos."""
    pts = _drifting(s, d)
    return rounded(detect.in_blocks(pts, materialise(model.fit(pts, Params()), "patterns"), Params(), 4096).select("start", "score", "nearest", "no_active"), "score")


def detect_sql_udtf(s: SparkSession, d: str) -> DataFrame:
    """Online detection from SQL."""
    from seqnorm.functions import registry

    registry.register(s)
    _drifting(s, d).select("series_id", "pos", "x").createOrReplaceTempView("carrier_points")
    return rounded(s.sql("select start, score, no_active from living_detect(table(select * from carrier_points), 50)"), "score")


def flagship(s: SparkSession, d: str) -> DataFrame:
    return detect_online_carrier(s, d)


def discord_left_hourly(s: SparkSession, d: str) -> DataFrame:
    return rounded(detectors.left_profile(P.hourly(s, d), ELL).select("start", "score"), "score")


def profile_full_hourly(s: SparkSession, d: str) -> DataFrame:
    return rounded(detectors.matrix_profile(P.hourly(s, d), ELL).select("start", "score"), "score")


def static_model_score(s: SparkSession, d: str) -> DataFrame:
    """Weighted sum over given patterns with z-normalised distances: the static score for a fixed model."""
    f = Fixed(s, d)
    prof = score.profile_blocks(segment.blocks(f.points, 256, ELL - 1), f.patterns, ELL, 256, "zn")
    w = f.patterns.select("series_id", "pattern_id", F.lit(1 / 3).alias("weight"))
    return rounded(score.weighted_sum(prof, w).select("start", "score"), "score")


def batch_ids(s: SparkSession, d: str) -> DataFrame:
    return detectors.batch_ids(P.events(s, d), 5000).select("batch_id", "n", "first_pos")


def _baseline(f: Callable[..., DataFrame], **how) -> Query:
    return lambda s, d: rounded(f(_drifting(s, d), 50, **how).select("start", "score"), "score")


def adaptive_window_daily(s: SparkSession, d: str) -> DataFrame:
    return detectors.adaptive_window(P.daily_lineitem(s, d), 7).select("pos")


# -- measures ----------------------------------------------------------------------------------------


def _labels(s: SparkSession, d: str) -> DataFrame:
    return P.table(s, d, "documents").select("doc_id", "n_chars").join(P.table(s, d, "labels"), "doc_id")


def _auc_doc(y) -> Query:  # noqa: ANN001
    return lambda s, d: rounded(metrics.auc(_labels(s, d).withColumn("y", y()), "n_chars"), "auc", digits=6)


def _spikes(s: SparkSession, d: str) -> DataFrame:
    """A plain detector for the measures: the absolute value of each point of a carrier with scale anomalies."""
    c = inject.scale(workloads.heart(s, d), 0.05)
    return c.select("series_id", "pos", F.round(F.abs("x"), 3).alias("score"), F.col("y_true").cast("int").alias("y"), "in_transition", "x")


def auc_carrier(s: SparkSession, d: str) -> DataFrame:
    return rounded(metrics.auc(_spikes(s, d)), "auc")


def auc_binned(s: SparkSession, d: str) -> DataFrame:
    return rounded(metrics.auc_binned(_spikes(s, d), 0.05), "auc", "bound")


def roc_points(s: SparkSession, d: str) -> DataFrame:
    b = _spikes(s, d).withColumn("score", F.floor(F.col("score") / 0.1).cast("long"))
    return rounded(metrics.roc(b), "fpr", "tpr")


def confusion(s: SparkSession, d: str) -> DataFrame:
    return rounded(metrics.confusion(_spikes(s, d), F.col("score") > 1.5), "precision", "recall", "fpr", "f1")


def fp_after_drift(s: SparkSession, d: str) -> DataFrame:
    """Alarms of the fixed model over 1300 within two days after a drift of it."""
    f = Fixed(s, d)
    act = f.active()
    al = score.trailing_min(act, ELL).filter("score > 1000").select("series_id", "start", F.lit(0).alias("y"))
    return metrics.fp_after_drift(al, score.drift_events(act).select("series_id", "pos"), 48).select("fp_after_drift")


def dissim_matrix(s: SparkSession, d: str) -> DataFrame:
    return rounded(workloads.x11(s, d), "d")


def anom_dissim(s: SparkSession, d: str) -> DataFrame:
    """By injected factor, mean and deviation of the anomalous windows' distance to their nearest normal pattern, beside
    the mean and the largest distance between normal patterns; these are the four concepts' periods."""
    period = s.range(50).select(F.explode(F.array(*map(F.lit, range(4)))).alias("pattern"), F.col("id").alias("i"))
    normal = period.groupBy("pattern").agg(F.transform(F.array_sort(F.collect_list(F.struct("i", inject.shape(F.col("pattern"), F.col("i")).alias("v")))), lambda t: t["v"]).alias("shape"))
    a, b = normal.select(F.col("pattern").alias("a"), F.col("shape").alias("sa")), normal.select(F.col("pattern").alias("b"), F.col("shape").alias("sb"))
    between = a.join(b, F.col("a") < F.col("b")).select(D.zm_col(F.col("sa"), F.col("sb")).alias("d")).agg(F.avg("d").alias("normal_mean"), F.max("d").alias("normal_max"))
    parts = None
    for k in (0.5, 1.0, 2.0, 3.0):
        hit = segment.segments(inject.scaled_normal(workloads.heart(s, d), k), 50).select("seg", "xs")
        truth = inject.scaled_normal(workloads.heart(s, d), k).groupBy(F.floor(F.col("pos") / 50).cast("int").alias("seg")).agg(F.min("y_true").alias("y"))
        one = hit.join(truth.filter("y > 0"), "seg").select(F.lit(k).alias("factor"), "seg", "xs")
        parts = one if parts is None else parts.unionByName(one)
    near = parts.join(F.broadcast(normal)).groupBy("factor", "seg").agg(F.min(D.zm_col(F.col("xs"), F.col("shape"))).alias("dist"))
    out = near.groupBy("factor").agg(F.count(F.lit(1)).alias("n"), F.avg("dist").alias("mean"), F.stddev_pop("dist").alias("sd")).crossJoin(F.broadcast(between))
    return rounded(out, "mean", "sd", "normal_mean", "normal_max")


def unclustered_by_rmin(s: SparkSession, d: str) -> DataFrame:
    """Segments outside every cluster as the least cluster size rises, for runs of growing length as clusters."""
    seg = segment.segments(P.daily_lineitem(s, d), 14)
    runs = seg.select("series_id", F.floor(F.sqrt(F.col("seg").cast("double"))).cast("int").alias("cluster_id"), "seg")
    out = None
    for r in (0.001, 0.01, 0.05, 0.1):
        one = metrics.unclustered(runs, r).select(F.lit(r).alias("r_min"), "unclustered")
        out = one if out is None else out.unionByName(one)
    return out


def by_region(s: SparkSession, d: str) -> DataFrame:
    n = workloads._n(s, d)
    concept, inside = inject.gradual([n // 2], n * 0.1, 2, 1)
    c = inject.scale(workloads.heart(s, d, concept, inside), 0.05)
    return rounded(metrics.by_region(c.select(F.abs("x").alias("score"), F.col("y_true").alias("y"), "in_transition")), "mean_score")


def dataset_card(s: SparkSession, d: str) -> DataFrame:
    return rounded(metrics.card(inject.scale(workloads.heart(s, d, inject.recurring(500, 4)), 0.05)), "mean_x", "sd_x")


def stability(s: SparkSession, d: str) -> DataFrame:
    """Spread over event types of the AUC of an event's value for events late in the hour."""
    e = P.table(s, d, "events").select(F.col("event_type").alias("method"), F.col("value").alias("score"), (F.minute("ts") >= 45).cast("int").alias("y"))
    a = metrics.auc(e, by=("method",)).select(F.lit("value").alias("method"), F.col("auc").alias("value"))
    return rounded(metrics.stability(a), "spread", "range", "mean")


# -- injectors ---------------------------------------------------------------------------------------


def _shown(df: DataFrame) -> DataFrame:
    x = F.round("x", 6) + F.lit(0.0)  # no negative zero
    return df.select("pos", x.alias("x"), "concept", "in_transition", F.col("y_true").cast("int").alias("y_true"))


def _injectors() -> dict[str, Query]:
    heart = workloads.heart
    n = workloads._n
    return {
        "inj_scale": lambda s, d: _shown(inject.scale(heart(s, d), 0.05)),
        "inj_scaled_normal": lambda s, d: _shown(inject.scaled_normal(heart(s, d), 2.0)),
        "inj_lookalike": lambda s, d: _shown(inject.lookalike(heart(s, d, inject.ratio(n(s, d), 1, 9)), 0.1)),
        "inj_abrupt": lambda s, d: _shown(heart(s, d, inject.abrupt([n(s, d) // 4, n(s, d) // 2], 4))),
        "inj_gradual": lambda s, d: _shown(heart(s, d, *inject.gradual([n(s, d) // 4, n(s, d) // 2], n(s, d) * 0.05, 4, 1))),
        "inj_recurring": lambda s, d: _shown(heart(s, d, inject.recurring(500, 3))),
        "inj_ratio": lambda s, d: _shown(heart(s, d, inject.ratio(n(s, d), 8, 2))),
        "inj_alternate": lambda s, d: _shown(heart(s, d, inject.alternate(20))),
        **{f"inj_place_{law}": (lambda s, d, law=law: _shown(inject.place(heart(s, d), law, 0.1, n(s, d)))) for law in ("uniform", "gauss", "rayleigh", "invrayleigh")},
    }


# -- operators around --------------------------------------------------------------------------------


def _days(s: SparkSession, d: str) -> DataFrame:
    return P.daily_lineitem(s, d).select("series_id", "pos", "x")


def _marks(s: SparkSession, d: str) -> DataFrame:
    return P.daily_orders(s, d).filter("pos % 10 = 3").select(F.lit("daily_lineitem").alias("series_id"), "pos", F.col("x").alias("mark"))


def _asof(direction: str) -> Query:
    return lambda s, d: rounded(relational.asof(_days(s, d), _marks(s, d), "series_id", "pos", "mark", direction).select("pos", "mark"), "mark", digits=2)


def _asof_all(direction: str) -> Query:
    """As-of against every day of orders on which something was ordered."""

    def run(s: SparkSession, d: str) -> DataFrame:
        marks = P.daily_orders(s, d).filter("x > 0").select(F.lit("daily_lineitem").alias("series_id"), "pos", F.col("x").alias("mark"))
        return rounded(relational.asof(_days(s, d), marks, "series_id", "pos", "mark", direction).select("pos", "mark"), "mark", digits=2)

    return run


def op_range_join_lineitem(s: SparkSession, d: str) -> DataFrame:
    """Every line item's days in use, one piece a day from its shipment, and the weeks (counted from 1970) that they meet."""
    lo = F.unix_date(F.col("l_shipdate").cast("date")).cast("bigint")
    b = P.table(s, d, "lineitem").select("l_orderkey", "l_linenumber", lo.alias("b_lo"), (lo + F.col("l_quantity").cast("bigint") - 1).alias("b_hi"))
    ends = b.agg(F.floor(F.min("b_lo") / 7).alias("first"), F.floor(F.max("b_hi") / 7).alias("last"))
    weeks = ends.select(F.explode(F.sequence("first", "last")).alias("w")).select((F.col("w") * 7).alias("a_lo"), (F.col("w") * 7 + 6).alias("a_hi"))
    return relational.range_join(weeks, b, "a_lo", "a_hi", "b_lo", "b_hi", 16)


def op_range_join(s: SparkSession, d: str) -> DataFrame:
    """Weeks (counted from 1970) and the stretch of ten days that begins with each order, where they meet."""
    lo = F.unix_date(F.col("o_orderdate").cast("date")).cast("bigint")
    b = P.table(s, d, "orders").select("o_orderkey", lo.alias("b_lo"), (lo + 9).alias("b_hi"))
    ends = b.agg(F.floor(F.min("b_lo") / 7).alias("first"), F.floor(F.max("b_hi") / 7).alias("last"))
    weeks = ends.select(F.explode(F.sequence("first", "last")).alias("w")).select((F.col("w") * 7).alias("a_lo"), (F.col("w") * 7 + 6).alias("a_hi"))
    return relational.range_join(weeks, b, "a_lo", "a_hi", "b_lo", "b_hi", 16)


def op_semi(s: SparkSession, d: str) -> DataFrame:
    return relational.semi(P.table(s, d, "documents").select("doc_id", "n_chars"), P.table(s, d, "labels").filter("toxic = 1"), "doc_id")


def op_anti(s: SparkSession, d: str) -> DataFrame:
    return relational.anti(P.table(s, d, "documents").select("doc_id", "n_chars"), P.table(s, d, "labels"), "doc_id")


def _events(s: SparkSession, d: str) -> DataFrame:
    return P.table(s, d, "events")


def _half(s: SparkSession, d: str, k: int) -> DataFrame:
    return _events(s, d).filter(F.col("value") > k).select("user_id", "event_type")


def op_cross_pivot(s: SparkSession, d: str) -> DataFrame:
    return workloads.x11(s, d).withColumnRenamed("a", "item").groupBy("item").pivot("b", ["A", "B", "C", "D"]).agg(F.round(F.first("d"), 4))


def op_unpivot(s: SparkSession, d: str) -> DataFrame:
    t = relational.agg_stats(P.by_type(s, d), ["series_id"]).select("series_id", F.round("mean", 4).alias("mean"), F.round("high", 4).alias("high"))
    return t.unpivot("series_id", ["mean", "high"], "metric", "value")


def op_agg_stats(s: SparkSession, d: str) -> DataFrame:
    return rounded(relational.agg_stats(P.by_type(s, d), ["series_id"]), "total", "mean", "low", "high", "sd", "variance", "skew", "kurt", digits=3)


def op_grouping_sets(s: SparkSession, d: str) -> DataFrame:
    _events(s, d).withColumn("day", F.dayofmonth("ts")).createOrReplaceTempView("op_events")
    return relational.grouping_sets(s, "op_events", "(event_type), (day), ()", "count(*) as n, round(sum(value), 2) as v")


def op_cube(s: SparkSession, d: str) -> DataFrame:
    return _events(s, d).withColumn("dow", F.dayofweek("ts")).cube("event_type", "dow").agg(F.count(F.lit(1)).alias("n"))


def op_rollup(s: SparkSession, d: str) -> DataFrame:
    return _events(s, d).withColumn("dow", F.dayofweek("ts")).rollup("event_type", "dow").agg(F.count(F.lit(1)).alias("n"))


def op_rank_suite(s: SparkSession, d: str) -> DataFrame:
    t = P.table(s, d, "documents").select("doc_id", "lang", "n_chars")
    out = relational.rank_suite(t, "lang", F.struct("n_chars", "doc_id"))
    return rounded(out.select("doc_id", "row_number", "rank", "dense_rank", "percent_rank", "cume_dist", "ntile"), "percent_rank", "cume_dist")


def op_range_frame(s: SparkSession, d: str) -> DataFrame:
    return rounded(relational.rolling_range(_days(s, d), F.avg("x"), "pos", 6).select("pos", "v"), "v", digits=2)


def op_rolling(s: SparkSession, d: str) -> DataFrame:
    return rounded(relational.rolling(_days(s, d), F.max("x"), 3, 3).select("pos", "v"), "v", digits=2)


def op_running(s: SparkSession, d: str) -> DataFrame:
    return rounded(relational.running(_days(s, d).withColumn("x", F.floor("x")), F.sum("x")).select("pos", "v"), "v", digits=1)


def op_islands(s: SparkSession, d: str) -> DataFrame:
    return relational.islands(_days(s, d).withColumn("high", F.col("x") > 300000), "high").select("island", "high", "first_pos", "last_pos", "n")


def op_topk(s: SparkSession, d: str) -> DataFrame:
    """A top-k report."""
    return relational.topk(P.table(s, d, "documents").select("doc_id", "n_chars"), 10, F.desc("n_chars"), F.col("doc_id"))


def op_topk_per(s: SparkSession, d: str) -> DataFrame:
    return relational.topk_per(P.table(s, d, "documents").select("doc_id", "lang", "n_chars"), "lang", 3, F.desc("n_chars"), F.col("doc_id"))


def op_percentile(s: SparkSession, d: str) -> DataFrame:
    return rounded(relational.quantile(P.by_type(s, d), ["series_id"], "x", 0.9), "q")


def op_count_distinct(s: SparkSession, d: str) -> DataFrame:
    return relational.count_distinct(_events(s, d), ["event_type"], "user_id")


def op_json_props(s: SparkSession, d: str) -> DataFrame:
    return relational.json_props(_events(s, d)).groupBy("k").agg(F.count(F.lit(1)).alias("n"))


def op_tumbling(s: SparkSession, d: str) -> DataFrame:
    return rounded(relational.tumbling(_events(s, d), "ts", "6 hours", F.sum("value")), "v", digits=2)


def op_sliding(s: SparkSession, d: str) -> DataFrame:
    return relational.tumbling(_events(s, d), "ts", "6 hours", F.max("value"), "2 hours")


def op_session(s: SparkSession, d: str) -> DataFrame:
    return relational.sessions(_events(s, d), "event_type", "ts", "30 minutes")


def op_lateral_topk(s: SparkSession, d: str) -> DataFrame:
    """The two longest conversations' turns next to each role's threshold of length."""
    t = P.table(s, d, "conversations").select("role", "conv_id", "turn", F.length("text").alias("n"))
    roles = t.select("role").distinct()
    return relational.lateral_topk(roles, t, "role", F.struct(-F.col("n"), F.col("conv_id"), F.col("turn")), 2)


def op_full_outer(s: SparkSession, d: str) -> DataFrame:
    a = _events(s, d).filter("value > 100").groupBy("user_id").agg(F.count(F.lit(1)).alias("a"))
    b = _events(s, d).filter("value < 2").groupBy("user_id").agg(F.count(F.lit(1)).alias("b"))
    return relational.full_outer(a, b, "user_id")


def op_sample_md5(s: SparkSession, d: str) -> DataFrame:
    """A sampling operator whose choice any engine repeats."""
    return _events(s, d).filter(inject.u(F.col("event_id"), "sample") < 0.1).select("event_id")


# -- streams -----------------------------------------------------------------------------------------

_EVENTS = "event_id long, ts timestamp_ntz, user_id long, event_type string, value double, props string"


def _event_stream(s: SparkSession, d: str) -> DataFrame:
    return P.read_stream(s, d, "events.parquet", _EVENTS)


def stream_hourly(s: SparkSession, d: str) -> DataFrame:
    from seqnorm.streaming import detector

    return rounded(detector.run_to_table(detector.hourly_stream(_event_stream(s, d)), scratch(s, "stream")), "x", digits=2)


def stream_session(s: SparkSession, d: str) -> DataFrame:
    from seqnorm.streaming import detector

    return detector.run_to_table(detector.session_stream(_event_stream(s, d)), scratch(s, "stream"))


def stream_dedup(s: SparkSession, d: str) -> DataFrame:
    from seqnorm.streaming import detector

    twice = _event_stream(s, d).withColumn("copy", F.explode(F.array(F.lit(0), F.lit(1))))
    return detector.run_to_table(detector.dedup_stream(twice).select("event_id", "value"), scratch(s, "stream"))


def stream_detect(s: SparkSession, d: str) -> DataFrame:
    """Live detection on a pulse with a change of concept; a row per window, and drift events."""
    from seqnorm.streaming import detector

    n = workloads._n(s, d)
    noise = (F.col("value") - 50.0) / 50.0
    e = _event_stream(s, d).select(F.lit("live").alias("series_id"), F.col("event_id").alias("pos"), noise.alias("noise"))
    pts = e.withColumn("x", inject.shape((F.col("pos") >= n // 2).cast("int"), F.col("pos")) + 0.05 * F.col("noise")).select("series_id", "pos", "x")
    out = detector.run_to_table(detector.detect_stream_plain(pts, Params(), n // 5), scratch(s, "stream"))
    return rounded(out.select("start", "score", "nearest", "no_active", "event", "pattern_id"), "score")


def stream_detect_equals_batch(s: SparkSession, d: str) -> DataFrame:
    """Live detection with a delay against a batch run over the same points: is each window's score and activity the same?"""
    from seqnorm.operators import detect
    from seqnorm.streaming import detector

    n, p = workloads._n(s, d), Params(delta=2 * workloads.ELL)
    carry = lambda e: e.select(F.lit("live").alias("series_id"), F.col("event_id").alias("pos"), (inject.shape((F.col("event_id") >= n // 2).cast("int"), F.col("event_id")) + 0.001 * (F.col("value") - 50.0)).alias("x"))
    live = detector.run_to_table(detector.detect_stream_plain(carry(_event_stream(s, d)), p, max(p.ell_m, int(n * 0.2))), scratch(s, "stream"))
    whole = detect.scores(detect.online(carry(_events(s, d)), p, events=False)).select("start", F.col("score").alias("b_score"), F.col("no_active").alias("b_none"))
    pairs = detect.scores(live).join(whole, "start", "left")
    close = F.abs(F.col("score") - F.col("b_score")) <= 1e-6 * F.greatest(F.lit(1.0), F.col("b_score"))
    return pairs.select("start", F.coalesce(close & (F.col("no_active") == F.col("b_none")), F.lit(False)).alias("same"))


def stream_late_count(s: SparkSession, d: str) -> DataFrame:
    """Events in five arrivals, a tenth of them one arrival late: rows and late rows of each type."""
    from seqnorm.streaming import detector

    n, folder = workloads._n(s, d), scratch(s, "arrivals")
    arrival = F.floor(F.col("event_id") * 4 / n).cast("int") + (inject.u(F.col("event_id"), "late") < 0.1).cast("int")
    dealt = _events(s, d).select("event_type", F.col("ts").cast("timestamp").alias("ts"), arrival.alias("arrival"))
    for k in range(5):  # written one after the other, as files come in the order of their times
        dealt.filter(F.col("arrival") == k).drop("arrival").coalesce(1).write.mode("append").parquet(folder)
    arrivals = s.readStream.schema("event_type string, ts timestamp").option("maxFilesPerTrigger", 1).parquet(folder)
    found = detector.run_to_table(detector.late_rows(arrivals, "event_type"), scratch(s, "stream"))
    return found.groupBy(F.col("key").alias("event_type")).agg(F.sum("rows").alias("n"), F.sum("late").alias("late"))


# -- all of them -------------------------------------------------------------------------------------


def _workloads() -> dict[str, Query]:
    w = workloads
    named: dict[str, Query] = {
        "x1a": w.x1, "x1b": lambda s, d: w.x1(s, d, "services"), "x2a": w.x2, "x2b": lambda s, d: w.x2(s, d, "services"), "x3": w.x3, "x4": w.x4,
        "x5a": w.x5a, "x5b": w.x5b, "x6a": w.x6, "x6b": lambda s, d: w.x6(s, d, "seasonal"), "x7a": w.x7a, "x7b": w.x7b, "x7c": w.x7c, "x7d": w.x7d,
        "x8": w.x8, "x9": w.x9, "x10": w.x10, "x12": w.x12, "x13": w.x13, "x14": w.x14, "x15": w.x15, "ablations": w.ablations,
    }

    def tidy(f: Query) -> Query:
        def run(s: SparkSession, d: str) -> DataFrame:
            out = f(s, d)
            return rounded(out, "value") if "value" in out.columns else out

        return run

    return {k: tidy(f) for k, f in named.items()}


def queries() -> dict[str, Query]:
    import sys

    here = sys.modules[__name__]
    plain = (
        "windows_hourly windows_by_type segments_hourly segments_daily blocks_equal_windows dist_emb_zm dist_emb_zm_all dist_emb_zn dist_sbd_emb dist_dtw_small dist_zm_pairs"
        " dist_zn_pairs dist_min_place adjacent_gap_links chain_cut_toy cut_toy_rules ca_rounds_daily ca_clusters_daily centroids_fixed tau_fixed win_fixed"
        " unclustered_fixed phi_hourly phi_avg_hourly active_flags_hourly active_flags_trained active_delta_hourly drift_events_hourly score_nearest_active"
        " score_no_active_fallback score_trailing_min score_centered score_weighted_sum score_offline_nearest_time alarms_per_series fit_events"
        " detect_online_carrier detect_offline_carrier detect_blocks_carrier detect_sql_udtf discord_left_hourly profile_full_hourly static_model_score batch_ids"
        " adaptive_window_daily auc_carrier auc_binned roc_points confusion fp_after_drift dissim_matrix anom_dissim unclustered_by_rmin by_region dataset_card"
        " stability op_range_join op_semi op_anti op_cross_pivot op_unpivot op_agg_stats op_grouping_sets op_cube op_rollup op_rank_suite op_range_frame op_rolling"
        " op_running op_islands op_topk op_topk_per op_percentile op_count_distinct op_json_props op_tumbling op_sliding op_session op_lateral_topk op_full_outer"
        " op_sample_md5 stream_hourly stream_session stream_dedup stream_detect stream_detect_equals_batch stream_late_count op_range_join_lineitem"
    ).split()
    out = _points() | {name: getattr(here, name) for name in plain} | _injectors() | _workloads()
    out |= {f"link_{k}": _links(k) for k in ("single", "complete", "average", "centroid", "ward")}
    out |= {"ca_ward_norepair_daily": _ca(False, 1), "ca_repair_daily": _ca(True, 1), "ca_k5_daily": _ca(True, 5)}
    out |= {f"freq_{m}_fixed": _freq(m) for m in ("overlap", "majority", "contain")}
    out |= {"label_radius": _labelled("radius"), "label_threshold": _labelled("threshold", threshold=1000.0), "label_topk": _labelled("topk", k=20), "label_quantile": _labelled("quantile", q=0.95)}
    out |= {"admit_dissimilar": _admission("dissimilar"), "admit_frequent": _admission("frequent"), "admit_both": _admission("admitted")}
    out |= {"auc_doc_toxic": _auc_doc(lambda: F.col("toxic")), "auc_doc_quality": _auc_doc(lambda: 1 - F.col("quality"))}
    out |= {f"dist_emb_{k}_all": _search(k) for k in ("zn", "sbd", "dtw")}
    out |= {f"op_asof_{k}_all": _asof_all(k) for k in ("backward", "forward", "nearest")}
    out |= {f"op_asof_{k}": _asof(k) for k in ("backward", "forward", "nearest")}
    out |= {
        "static_weighted_carrier": _baseline(detectors.static_weighted),
        "batch_shape_carrier": _baseline(detectors.batch_shape),
        "discord_carrier": _baseline(detectors.backward_discord),
        "discord_bounded_carrier": _baseline(detectors.backward_discord, lookback=1000, block=2048),
        "transformer_carrier": _baseline(detectors.transformer),
        "op_union": lambda s, d: _half(s, d, 150).union(_half(s, d, 200)),
        "op_intersect": lambda s, d: _half(s, d, 100).intersect(_half(s, d, 120)),
        "op_except": lambda s, d: _half(s, d, 50).subtract(_half(s, d, 120)),
        "op_except_all": lambda s, d: _half(s, d, 50).exceptAll(_half(s, d, 120)),
    }
    return out


def oracle_sql() -> dict[str, str]:
    return oracles.all_sql()
