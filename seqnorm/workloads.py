"""The experiments on carriers made from the given tables: (setting, method, metric, value)."""

from __future__ import annotations

import time
from collections.abc import Callable, Iterable, Iterator, Sequence
from dataclasses import replace

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from seqnorm.baselines import kernels
from seqnorm.functions import distance as D
from seqnorm.operators import inject, metrics
from seqnorm.operators.living import Detected, Params, fit_series, offline_series, scan_series
from seqnorm.session import ship
from seqnorm.sources import points as sources

ALL = ("offline", "online", "static", "batch_shape", "discord", "transformer")
OURS = ("offline", "online")
ELL = inject.PERIOD


def _online(x: np.ndarray, p: Params) -> Detected:
    return scan_series(x, fit_series(x[: max(p.ell_m, len(x) // 5)], p), p)


def score_of(method: str, x: np.ndarray, p: Params) -> tuple[np.ndarray, int, dict[str, float]]:
    """(score of each window, point of a window that its score stands for, counters)."""
    ell = p.ell
    if method in OURS:
        found = offline_series(x, p, keep=False) if method == "offline" else _online(x, p)
        counters = {"patterns": len(found.model.patterns), "births": len(found.births), "epochs": found.epochs, "splits": found.model.splits, "unclustered": len(found.model.unclustered), "evaluations": found.evaluations}
        return found.score, 0 if p.align == "trailing" else ell // 2, counters
    if method == "static":
        shapes, weights = kernels.static_fit(x, ell, p.mult)
        return kernels.static_score(x, shapes, weights, ell), ell // 2, {}
    if method == "batch_shape":
        return kernels.batch_shape(x, ell, p.mult), ell // 2, {}
    if method == "discord":
        return kernels.backward_discord(x, ell), ell // 2, {}
    if method == "transformer":
        return kernels.transformer_score(x, ell, epochs=3), ell // 2, {}
    raise ValueError(f"unknown method {method}")


RAW = "setting string, method string, series_id string, metric string, value double"


def _groups(batches: Iterable[pa.RecordBatch]) -> Iterator[tuple[int, str, np.ndarray, np.ndarray]]:
    """(number, series, x, y) of each group of rows that come sorted by (g, series_id, pos), in batches cut anywhere."""
    key, xs, ys = None, [], []
    for b in batches:
        if not b.num_rows:
            continue
        g, series = b.column("g").to_numpy(), b.column("series_id")
        series = series if pa.types.is_dictionary(series.type) else series.dictionary_encode()
        code, names = series.indices.to_numpy(), series.dictionary.to_pylist()
        x, y = (b.column(c).to_numpy(zero_copy_only=False) for c in "xy")
        edges = np.r_[0, np.flatnonzero((np.diff(g) != 0) | (np.diff(code) != 0)) + 1, len(g)]
        for lo, hi in zip(edges, edges[1:]):
            now = (int(g[lo]), names[code[lo]])
            if now != key:
                if xs:
                    yield *key, np.concatenate(xs), np.concatenate(ys)
                key, xs, ys = now, [], []
            xs.append(x[lo:hi].copy())
            ys.append(y[lo:hi].copy())
    if xs:
        yield *key, np.concatenate(xs), np.concatenate(ys)


PACKED = "s int, series_id string, lo bigint, pos binary, x binary, y binary"
NO_Y = -128  # a missing truth among packed ones


def _pack(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Rows (s, series_id, pos, x, y) as one row for each series of a batch, with the points' bytes in order of pos; pos is left
    empty where it has no gaps.  Shuffles and sorts then take a few bytes a point, and few rows."""
    for b in batches:
        s, pos, series = b.column("s").to_numpy(), b.column("pos").to_numpy(), b.column("series_id").dictionary_encode()
        code, names = series.indices.to_numpy(), series.dictionary.to_pylist()
        x, y = b.column("x").to_numpy(zero_copy_only=False), b.column("y").fill_null(NO_Y).to_numpy()
        order = np.lexsort((pos, code, s))
        s, pos, code, x, y = s[order], pos[order], code[order], x[order], y[order]
        edges = np.r_[0, np.flatnonzero((np.diff(s) != 0) | (np.diff(code) != 0)) + 1, len(s)] if len(s) else []
        rows = []
        for lo, hi in zip(edges, edges[1:]):
            at = pos[lo:hi]
            dense = (np.diff(at) == 1).all()
            rows.append((int(s[lo]), names[code[lo]], int(at[0]), b"" if dense else at.tobytes(), x[lo:hi].tobytes(), y[lo:hi].tobytes()))
        yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*rows) if rows else [()] * 6, (pa.int32(), pa.string(), pa.int64(), pa.binary(), pa.binary(), pa.binary()))], ["s", "series_id", "lo", "pos", "x", "y"])


def _unpack(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Rows (g, series_id, x, y) sorted by (g, series_id, pos) from packed ones sorted by (g, series_id, lo); those whose points
    lie among each other are put together first."""
    key, held, last = None, [], 0

    def points() -> pa.RecordBatch:
        pos, x, y = (np.concatenate(c) if len(c) > 1 else c[0] for c in zip(*held))
        if len(held) > 1:
            order = np.argsort(pos, kind="stable")
            x, y = x[order], y[order]
        y = pa.array(y, mask=y == NO_Y)
        return pa.RecordBatch.from_arrays([pa.array(np.full(len(x), key[0], np.int32)), pa.DictionaryArray.from_arrays(np.zeros(len(x), np.int32), [key[1]]), pa.array(x), y], ["g", "series_id", "x", "y"])

    for b in batches:
        for g, series, lo, pos, x, y in zip(*(b.column(c) for c in ("g", "series_id", "lo", "pos", "x", "y"))):
            x, y = np.frombuffer(x.as_buffer(), float), np.frombuffer(y.as_buffer(), np.int8)
            pos = np.frombuffer(pos.as_buffer(), np.int64) if len(pos.as_buffer()) else np.arange(lo.as_py(), lo.as_py() + len(x))
            now = (g.as_py(), series.as_py())
            if held and (now != key or pos[0] > last):
                yield points()
                held, last = [], 0
            last = max(last, int(pos[-1])) if held else int(pos[-1])
            key = now
            held.append((pos, x, y))
    if held:
        yield points()


def auc_of(score: np.ndarray, y: np.ndarray) -> float | None:
    """Exact AUC, ties counted half; None without both kinds of rows."""
    known = ~np.isnan(score)
    high, low = score[known & (y > 0)], score[known & (y <= 0)]
    low.sort()
    if not len(high) or not len(low):
        return None
    return float(np.searchsorted(low, high, "left").sum() + np.searchsorted(low, high, "right").sum()) / 2.0 / len(high) / len(low)


def places(work: Sequence[tuple[str, str]]) -> list[int]:
    """The turn of each (distance, method), the ones with the most work first."""
    slow = ("dtw", "sbd")
    methods = ("transformer", "batch_shape", "static", "online", "discord", "offline")
    cost = [(slow.index(d) if d in slow and m in OURS else len(slow), methods.index(m)) for d, m in work]
    turn = [0] * len(work)
    for i, at in enumerate(sorted(range(len(work)), key=cost.__getitem__)):
        turn[at] = i
    return turn


def scored(frame: DataFrame, params: dict[str, Params], methods: Sequence[str] = ALL) -> DataFrame:
    """AUC, counters and seconds of every method on every (setting, series) of frame, each score against the truth of the
    point it stands for.

    Points are packed before they are dealt out, once for all methods.  A task takes the groups (setting, method, series) of a
    partition one after another from sorted rows, and holds the numbers of one series only.  Each (setting, method) has partitions of its own, as groups hold few bytes and much
    work, and those with the most work come first, so that none of them is left to the end."""
    ship(frame.sparkSession)
    pairs = [(s, m) for s in params for m in methods]
    first = F.array_position(F.array(*map(F.lit, params)), F.col("setting")).cast("int") - 1
    points = frame.select(first.alias("s"), F.coalesce("series_id", F.lit("")).alias("series_id"), F.col("pos").cast("bigint").alias("pos"), F.col("x").cast("double").alias("x"), F.col("y_true").cast("tinyint").alias("y"))
    number = F.explode(F.sequence(F.col("s") * len(methods), (F.col("s") + 1) * len(methods) - 1))
    tasks = points.mapInArrow(_pack, PACKED).select(number.alias("g"), "series_id", "lo", "pos", "x", "y")
    fan, place = max(1, min(16, 256 // len(pairs))), places([(params[s].distance, m) for s, m in pairs])
    at = F.element_at(F.array(*map(F.lit, place)), F.col("g") + 1) * fan + F.pmod(F.hash("series_id"), F.lit(fan))
    tasks = tasks.repartitionById(fan * len(pairs), at)

    def run(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for g, series, x, y in _groups(_unpack(batches)):
            setting, method = pairs[g]
            began = time.perf_counter()
            score, shift, counters = score_of(method, x, params[setting])
            counters["seconds"] = time.perf_counter() - began
            rows = {"auc": auc_of(score, y[shift : shift + len(score)])} | {k: float(v) for k, v in counters.items()}
            del x, y, score  # before the next group's points come
            yield pa.RecordBatch.from_pydict({"setting": [setting] * len(rows), "method": [method] * len(rows), "series_id": [series] * len(rows), "metric": list(rows), "value": pa.array(rows.values(), pa.float64())})

    return tasks.sortWithinPartitions("g", "series_id", "lo").mapInArrow(run, RAW)


def results(raw: DataFrame, counters: bool = False) -> DataFrame:
    """AUC of each (setting, method), the mean over series; with counters, also their means (seconds with least and most)."""
    means = raw.filter("value is not null").groupBy("setting", "method", "metric").agg(F.avg("value").alias("value"), F.min("value").alias("low"), F.max("value").alias("high"))
    if not counters:
        return means.filter("metric = 'auc'").select("setting", "method", "metric", "value")
    ends = F.array(*[F.struct(F.concat("metric", F.lit(e)).alias("metric"), F.col(c).alias("value")) for e, c in (("", "value"), ("_min", "low"), ("_max", "high"))])
    found = F.explode(F.when(F.col("metric") == "seconds", ends).otherwise(F.slice(ends, 1, 1)))
    return means.select("setting", "method", found.alias("found")).select("setting", "method", "found.metric", "found.value")


def union(frames: dict[str, DataFrame]) -> DataFrame:
    keep = ["series_id", "pos", "x", "y_true"]
    parts = [f.select(F.lit(name).alias("setting"), *keep) for name, f in frames.items()]
    out = parts[0]
    for p in parts[1:]:
        out = out.unionByName(p)
    return out


def run(frames: dict[str, DataFrame], params: Params | dict[str, Params] = Params(), methods: Sequence[str] = ALL, counters: bool = False) -> DataFrame:
    per = params if isinstance(params, dict) else dict.fromkeys(frames, params)
    return results(scored(union(frames), per, methods), counters)


# -- carriers ----------------------------------------------------------------------------------------


def _n(spark: SparkSession, sf_dir: str) -> int:
    return spark.read.parquet(f"{sf_dir}/events.parquet").count()


def heart(spark: SparkSession, sf_dir: str, concept=None, transition=None, sigma: float = 0.05, names: Sequence[str] = tuple("ABCD")) -> DataFrame:  # noqa: ANN001
    return inject.build(inject.spine(spark, sf_dir), F.lit(0) if concept is None else concept, sigma, ELL, names, transition)


def services(spark: SparkSession, sf_dir: str, concept, transition=None) -> DataFrame:  # noqa: ANN001
    return inject.build(inject.spine(spark, sf_dir, True), concept, 0.15, ELL, tuple("AGCE"), transition)


def weekly(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Daily sums with a weekday and weekend factor, brought to a scale of one."""
    d = sources.daily_lineitem(spark, sf_dir)
    level = d.agg(F.avg("x").alias("m"))
    factor = F.when(F.col("pos") % 7 < 5, 1.0 + 0.3 * F.sin(2 * np.pi * (F.col("pos") % 7) / 5)).otherwise(0.3)
    x = F.col("x") / F.col("m")
    out = d.crossJoin(F.broadcast(level)).select("series_id", "pos", (factor * (0.7 + 0.3 * x)).alias("x"))
    return out.withColumns({"noise": F.lit(0.0), "concept": F.lit(0), "in_transition": F.lit(False), "y_true": F.lit(0).cast("tinyint")})


def seasonal(spark: SparkSession, sf_dir: str) -> DataFrame:
    """A daily wave whose form drifts slowly over the series, with the events' noise."""
    c = inject.spine(spark, sf_dir)
    slow = F.sin(2 * np.pi * F.col("pos") / 4000)
    theta = 2 * np.pi * (F.col("pos") % 24) / 24
    x = F.sin(theta) + 0.6 * slow * F.sin(2 * theta) + 0.08 * F.col("noise")
    return c.select("series_id", "pos", x.alias("x"), "noise").withColumns({"concept": F.lit(0), "in_transition": F.lit(False), "y_true": F.lit(0).cast("tinyint")})


def carriers(spark: SparkSession, sf_dir: str) -> dict[str, tuple[DataFrame, int]]:
    """The four carriers of the parameter sweeps, with their window lengths."""
    s = lambda df, ell: inject.scale(df, 0.05, ell=ell)
    n = _n(spark, sf_dir)
    return {
        "weekly": (s(weekly(spark, sf_dir), 7), 7),
        "seasonal": (s(seasonal(spark, sf_dir), 24), 24),
        "multi": (s(heart(spark, sf_dir, inject.recurring(500, 4)), ELL), ELL),
        "local": (s(heart(spark, sf_dir, inject.abrupt([n // 4, n // 2, 3 * n // 4], 4)), ELL), ELL),
    }


# -- experiments -------------------------------------------------------------------------------------


def x1(spark: SparkSession, sf_dir: str, kind: str = "heart", sweep: Sequence[int] = tuple(range(2, 12)), methods: Sequence[str] = ALL) -> DataFrame:
    """Abrupt drifts: n_d cuts, four concepts in turn, scale anomalies."""
    n = _n(spark, sf_dir) // (1 if kind == "heart" else 5)
    make = heart if kind == "heart" else services
    return run({f"n_d={d}": inject.scale(make(spark, sf_dir, inject.abrupt(inject.cuts(n, d, 1), 4)), 0.05) for d in sweep}, methods=methods)


def x2(spark: SparkSession, sf_dir: str, kind: str = "heart", sweep: Sequence[int] = (10, 20, 30, 40, 50), methods: Sequence[str] = ALL) -> DataFrame:
    """Gradual drifts: five hand-overs that fill a share of the series."""
    n = _n(spark, sf_dir) // (1 if kind == "heart" else 5)
    make, frames = heart if kind == "heart" else services, {}
    for share in sweep:
        concept, inside = inject.gradual(inject.cuts(n, 5, 1), share / 100 * n / 5, 4, 1)
        frames[f"share={share}"] = inject.scale(make(spark, sf_dir, concept, inside), 0.05)
    return run(frames, methods=methods)


def x3(spark: SparkSession, sf_dir: str, ratios: Sequence[tuple[int, int]] = ((1, 9), (5, 5), (8, 2), (9, 1)), shares: Sequence[int] = (1, 5, 10, 15, 20, 25, 30), methods: Sequence[str] = ALL) -> DataFrame:
    """Temporal context: A then B, with windows of B that look like A."""
    n = _n(spark, sf_dir)
    return run({f"{a}:{b} {s}%": inject.lookalike(heart(spark, sf_dir, inject.ratio(n, a, b)), s / 100) for a, b in ratios for s in shares}, methods=methods)


def x4(spark: SparkSession, sf_dir: str, sweep: Sequence[int] = (20, 40, 60, 80, 100), methods: Sequence[str] = ALL) -> DataFrame:
    """Several normal patterns: 10 periods of A in turn with longer chunks of B; anomalies in B."""
    return run({f"b={b}": inject.scale(heart(spark, sf_dir, inject.alternate(b)), 0.05, where=F.col("concept") == 1) for b in sweep}, methods=methods)


def x5a(spark: SparkSession, sf_dir: str, laws: Sequence[str] = ("uniform", "gauss", "rayleigh", "invrayleigh"), shares: Sequence[int] = (5, 10, 15, 20, 25, 30), methods: Sequence[str] = ALL) -> DataFrame:
    """Where anomalies are placed in time, on the weekly carrier."""
    base = weekly(spark, sf_dir)
    n = base.count()
    return run({f"{law} {s}%": inject.place(base, law, s / 100, n, ell=7) for law in laws for s in shares}, Params(ell=7), methods)


def x5b(spark: SparkSession, sf_dir: str, sweep: Sequence[float] = (0.1, 0.5, 1.0, 1.5, 2.0, 2.5, 3.0), methods: Sequence[str] = OURS) -> DataFrame:
    """How far anomalies lie from normal: factors around s, with the anomalies' distance to their nearest normal pattern."""
    base = weekly(spark, sf_dir)
    frames = {f"s={s}": inject.scaled_normal(base, s, ell=7) for s in sweep}
    p = Params(ell=7)
    out = run(frames, p, methods)
    ship(spark)

    def far(g: pd.DataFrame) -> pd.DataFrame:
        g = g.sort_values("pos")
        x, y = g["x"].to_numpy(float), g["y_true"].to_numpy()
        shapes = [q.shape for q in fit_series(np.where(y > 0, np.nan_to_num(g["clean"].to_numpy(float)), x), p).patterns]
        d = np.min([D.profile(x, s, 7) for s in shapes], axis=0)[::7]
        hit = y[: len(d) * 7 : 7] > 0
        between = [D.zm(a, b) for i, a in enumerate(shapes) for b in shapes[:i]] or [0.0]
        rows = [("anomaly_mean", d[hit].mean() if hit.any() else 0.0), ("anomaly_sd", d[hit].std() if hit.any() else 0.0), ("normal_mean", float(np.mean(between))), ("normal_max", float(np.max(between)))]
        return pd.DataFrame({"setting": g["setting"].iloc[0], "method": "distance", "metric": [r[0] for r in rows], "value": [float(r[1]) for r in rows]})

    clean = base.select("pos", F.col("x").alias("clean"))
    dist = union(frames).join(clean, "pos").groupBy("setting").applyInPandas(far, "setting string, method string, metric string, value double")
    return out.unionByName(dist)


def x6(spark: SparkSession, sf_dir: str, kind: str = "weekly", sweep: Sequence[int] = (1, 5, 10, 15, 20, 25, 30), methods: Sequence[str] = ALL) -> DataFrame:
    """Share of anomalies."""
    base, ell = (weekly(spark, sf_dir), 7) if kind == "weekly" else (seasonal(spark, sf_dir), 24)
    return run({f"{s}%": inject.scale(base, s / 100, ell=ell) for s in sweep}, Params(ell=ell), methods)


def sweep_params(spark: SparkSession, sf_dir: str, settings: dict[str, Callable[[Params], Params]], methods: Sequence[str] = ("offline",), names: Sequence[str] = ("weekly", "seasonal", "multi", "local")) -> DataFrame:
    frames, params = {}, {}
    for name, (df, ell) in carriers(spark, sf_dir).items():
        if name in names:
            for label, change in settings.items():
                frames[f"{name} {label}"] = df
                params[f"{name} {label}"] = change(Params(ell=ell))
    return run(frames, params, methods, counters=True)


def x7a(spark: SparkSession, sf_dir: str, sweep: Sequence[int] = (1, 2, 3, 5, 10, 15, 20)) -> DataFrame:
    return sweep_params(spark, sf_dir, {f"k={k}": lambda p, k=k: replace(p, k=k) for k in sweep})


def x7b(spark: SparkSession, sf_dir: str, sweep: Sequence[int] = (10, 20, 30, 40, 50)) -> DataFrame:
    return sweep_params(spark, sf_dir, {f"W={w}": lambda p, w=w: replace(p, win_max=w) for w in sweep}, ("online",))


def x7c(spark: SparkSession, sf_dir: str, sweep: Sequence[int] = (2, 3, 4)) -> DataFrame:
    return sweep_params(spark, sf_dir, {f"L={m}": lambda p, m=m: replace(p, mult=m) for m in sweep}, OURS)


def x7d(spark: SparkSession, sf_dir: str, sweep: Sequence[float] = (0.001, 0.01, 0.02, 0.04, 0.06, 0.08, 0.1)) -> DataFrame:
    return sweep_params(spark, sf_dir, {f"R={r}": lambda p, r=r: replace(p, r_min=r) for r in sweep})


def x8(spark: SparkSession, sf_dir: str, methods: Sequence[str] = ALL) -> DataFrame:
    """Run time of every method on the services carrier: mean, least and most seconds over its series."""
    n = _n(spark, sf_dir) // 5
    return run({"services": inject.scale(services(spark, sf_dir, inject.abrupt(inject.cuts(n, 5, 1), 4)), 0.05)}, methods=methods, counters=True).filter("metric like 'seconds%' or metric = 'auc'")


def x9(spark: SparkSession, sf_dir: str, methods: Sequence[str] = ("online",)) -> DataFrame:
    """Delay buffer: 0, one window, half and all of the currency window, on abrupt and gradual drifts."""
    n = _n(spark, sf_dir)
    cuts = inject.cuts(n, 5, 1)
    concept, inside = inject.gradual(cuts, 0.3 * n / 5, 4, 1)
    carried = {"abrupt": inject.scale(heart(spark, sf_dir, inject.abrupt(cuts, 4)), 0.05), "gradual": inject.scale(heart(spark, sf_dir, concept, inside), 0.05)}
    deltas = {"0": 0, "ell": ELL, "W/2": 4 * ELL, "W": 8 * ELL}
    settings = {f"{name} delta={k}": (df, Params(delta=v)) for name, df in carried.items() for k, v in deltas.items()}
    return run({k: df for k, (df, _) in settings.items()}, {k: p for k, (_, p) in settings.items()}, methods)


def x10(spark: SparkSession, sf_dir: str, kinds: Sequence[str] = ("zm", "zn", "sbd", "dtw")) -> DataFrame:
    """Distances: on abrupt drifts and on look-alikes."""
    n = _n(spark, sf_dir)
    a = inject.scale(heart(spark, sf_dir, inject.abrupt(inject.cuts(n, 5, 1), 4)), 0.05)
    b = inject.lookalike(heart(spark, sf_dir, inject.ratio(n, 5, 5)), 0.1)
    frames, params = {}, {}
    for name, df in (("abrupt", a), ("context", b)):
        for kind in kinds:
            frames[f"{name} {kind}"], params[f"{name} {kind}"] = df, Params(distance=kind)
    return run(frames, params, OURS)


def x11(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Heat map: zero-mean distances between concepts and their scaled anomalies, each the mean period of its windows of a
    carrier that takes the four concepts in turn."""
    c = inject.scale(heart(spark, sf_dir, inject.recurring(500, 4)), 0.05)
    name = F.concat(F.substring(F.lit("ABCD"), F.col("concept") + 1, F.lit(1)), F.when(F.col("y_true") > 0, "*").otherwise(""))
    items = c.groupBy(name.alias("name"), (F.col("pos") % ELL).alias("i")).agg(F.avg("x").alias("v"))
    arrays = items.groupBy("name").agg(F.array_sort(F.collect_list(F.struct("i", "v"))).alias("s")).select("name", F.transform("s", lambda e: e["v"]).alias("xs"))
    return metrics.dissim_matrix(arrays)


def x12(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Traces: a recurring switch A, B, A and a birth A, B, C where C is new; the drift events with their places."""
    from seqnorm.operators import detect

    n = _n(spark, sf_dir)
    edge = n // 10
    piece = F.when(F.col("pos") < edge, 0).when(F.col("pos") < 2 * edge, 1)
    recur = piece.when(F.col("pos") < 6 * edge, 0).otherwise(1)
    birth = piece.when(F.col("pos") < 5 * edge, 0).otherwise(2)
    out = None
    for name, concept in (("recurring", recur), ("birth", birth)):
        df = heart(spark, sf_dir, concept).withColumn("series_id", F.lit(name))
        e = detect.drift_events(detect.online(df, Params()))
        out = e if out is None else out.unionByName(e)
    return out


def x13(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Dataset card of the carriers, with drifts counted by an adaptive window."""
    from seqnorm.baselines.detectors import adaptive_window

    out = None
    for name, (df, ell) in carriers(spark, sf_dir).items():
        named = df.withColumn("series_id", F.lit(name))
        c = metrics.card(named, adaptive_window(named, ell))
        out = c if out is None else out.unionByName(c)
    return out


def x14(spark: SparkSession, sf_dir: str) -> DataFrame:
    """A slow rhythm turns into a fast one, with one look-alike window: rank of that window's score for each method."""
    n = _n(spark, sf_dir)
    at, period = (3 * n // 4) // ELL * ELL, ELL
    c = inject.spine(spark, sf_dir)
    theta = 2 * np.pi * (F.col("pos") % period) / period
    fast = F.col("pos") >= n // 2
    wave = F.when(fast, F.sin(2 * theta)).otherwise(F.sin(theta))
    odd = (F.col("pos") >= at) & (F.col("pos") < at + period)
    df = c.select("series_id", "pos", (F.when(odd, F.sin(theta)).otherwise(wave) + 0.05 * F.col("noise")).alias("x"), odd.cast("tinyint").alias("y_true"), F.lit(False).alias("in_transition"))
    return run({"rhythm": df})


def natural(spark: SparkSession, sf_dir: str) -> dict[str, tuple[DataFrame, int]]:
    """Columns of the given tables as they are, with a length of subsequences for each."""
    vectors = sources.vectors(spark, sf_dir).select("series_id", "start", F.posexplode("xs").alias("i", "x"))
    return {
        "hourly": (sources.hourly(spark, sf_dir), 24),
        "daily_lineitem": (sources.daily_lineitem(spark, sf_dir), 7),
        "daily_orders": (sources.daily_orders(spark, sf_dir), 7),
        "by_type": (sources.by_type(spark, sf_dir), 24),
        "by_user": (sources.by_user(spark, sf_dir), 4),
        "doc_len": (sources.doc_lengths(spark, sf_dir), 24),
        "page_len": (sources.page_lengths(spark, sf_dir), 24),
        "turn_len": (sources.turn_lengths(spark, sf_dir), 2),
        "embeddings": (vectors.select("series_id", (F.col("start") * 64 + F.col("i")).cast("bigint").alias("pos"), "x"), 64),
    }


def x15(spark: SparkSession, sf_dir: str, methods: Sequence[str] = OURS) -> DataFrame:
    """Natural columns without injected anomalies: series, points, windows, windows without an active pattern, drift events
    and mean score of both modes.  Series too short for one subsequence have points and no windows."""
    from seqnorm.operators import detect

    out = None
    for name, (df, ell) in natural(spark, sf_dir).items():
        p, df = Params(ell=ell), df.filter("x is not null")
        sizes = df.groupBy("series_id").agg(F.count(F.lit(1)).alias("n")).agg(F.count(F.lit(1)).alias("series"), F.sum("n").alias("points"))
        parts = [(m, detect.offline(df, p) if m == "offline" else detect.online(df, p)) for m in methods]
        rows = [sizes.select(F.lit("data").alias("method"), F.create_map(F.lit("series"), F.col("series").cast("double"), F.lit("points"), F.col("points").cast("double")).alias("m"))]
        for method, found in parts:
            scored_ = F.col("event").isNull()
            total = found.agg(
                F.count_if(scored_).cast("double").alias("windows"), F.count_if(scored_ & F.col("no_active")).cast("double").alias("no_active"),
                F.count_if(~scored_).cast("double").alias("events"), F.avg(F.when(scored_, F.col("score"))).alias("mean_score"),
            )
            rows.append(total.select(F.lit(method).alias("method"), F.create_map(*[c for n in total.columns for c in (F.lit(n), F.col(n))]).alias("m")))
        for r in rows:
            one = r.select(F.lit(name).alias("setting"), "method", F.explode("m").alias("metric", "value"))
            out = one if out is None else out.unionByName(one)
    return out


def ablations(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Parts of the method turned off one at a time."""
    n = _n(spark, sf_dir)
    df = inject.scale(heart(spark, sf_dir, inject.abrupt(inject.cuts(n, 5, 1), 4)), 0.05)
    p = Params()
    kinds = {"full": p, "without_time": replace(p, contiguous=False), "without_repair": replace(p, repair=False), "k=5": replace(p, k=5), "z_norm": replace(p, distance="zn"), "weighted": replace(p, weighted=True), "lazy": replace(p, scan="lazy"), "frozen": replace(p, births=False), "all_active": replace(p, all_active=True)}
    return run(dict.fromkeys(kinds, df), kinds, ("online",))
