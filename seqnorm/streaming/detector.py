"""Live detection: one key per series, its model and its last points as state."""

from __future__ import annotations

import pickle
from collections.abc import Iterator
from dataclasses import replace

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.streaming import StatefulProcessor

from seqnorm.functions import distance as D
from seqnorm.operators.living import Living, Params, accept, eta_of, fit_series, full, relearn, rolling_mean, window_score
from seqnorm.session import ship

OUT = "series_id string, start bigint, score double, nearest int, no_active boolean, event string, pattern_id int"


NAMES = ["start", "score", "nearest", "no_active", "event", "pattern_id"]


class LiveSeries:
    """Scores and drift events of the points of one series as they come in order, a stretch of windows at a time.

    Until `train_points` points have come they are collected; the model is then learned from them, and all windows from
    the first one on are scored, so that a stream gives what a batch run over the same points gives, however its points are
    dealt over micro-batches.  With a delay, a window is held back until the points it may look ahead to have come; `flush`
    gives the last windows at the end of a series, which see only what there is.  With a lazy scan inactive patterns are
    looked at only where no active one is left, a window at a time."""

    def __init__(self, params: Params, train_points: int, step: int = 1 << 15):
        if params.weighted or params.align != "trailing":
            raise ValueError("live scores are trailing ones of the nearest active pattern")
        self.params, self.train_points, self.step = params, train_points, step
        self.model: Living | None = None
        self.waiting: list[np.ndarray] = []  # points before training
        self.x = np.zeros(0)
        self.base = 0  # position of x[0]
        self.next = 0  # next window
        self.last_pos = -1
        self.late = 0
        self.evaluations = 0
        self.dists: list[np.ndarray] = []  # of each pattern, from window first[i] on
        self.phis: list[np.ndarray] = []
        self.first: list[int] = []
        self.was: list[bool] = []
        self.retry = 0

    def push(self, pos: int, value: float) -> Iterator[tuple]:
        for f in self.push_all(np.array([pos]), np.array([value], float)):
            if len(f) and f["event"].iloc[0] != "late":
                yield from _tuples(f)

    def push_all(self, pos: np.ndarray, values: np.ndarray) -> Iterator[pd.DataFrame]:
        """A frame of scores and events for each stretch; a point that comes after a later one is dropped, with an event."""
        late = pos <= np.maximum.accumulate(np.r_[self.last_pos, pos])[:-1]
        if late.any():
            self.late += int(late.sum())
            yield _frame(events=[(int(q), "late", -1) for q in pos[late]])
        if late.all():
            return
        self.last_pos = int(pos[~late].max())
        fresh = np.asarray(values, float)[~late]
        if self.model is None:
            self.waiting.append(fresh)
            need = max(self.train_points, self.params.ell_m)
            if sum(map(len, self.waiting)) < need:
                return
            self._learn(need)
        else:
            self.x = np.concatenate([self.x, fresh])
        yield from self._upto(self.base + len(self.x) - self.params.ell - self.params.delta + 1)
        back = max(self.model.win, int(max(self.model.win, 2 * self.params.ell_m) * self.params.relearn_mult))
        keep = back + 2 * self.params.ell + self.params.delta
        if len(self.x) > 2 * keep:
            drop = len(self.x) - keep
            self.x, self.base = self.x[drop:].copy(), self.base + drop

    def flush(self) -> Iterator[tuple]:
        """The windows still held back, when no more points will come; a series too short for training is learned whole."""
        if self.model is None:
            if sum(map(len, self.waiting)) < self.params.ell:
                return
            self._learn(None)
        for f in self._upto(self.base + len(self.x) - self.params.ell + 1):
            yield from _tuples(f)

    def _learn(self, need: int | None) -> None:
        self.x, self.waiting = np.concatenate(self.waiting), []
        self.model = fit_series(self.x[:need], self.params)
        self.retry = 2 * self.params.ell_m
        for _ in self.model.patterns:
            self._track(self.params.scan == "lazy")

    def _track(self, active: bool) -> None:
        self.dists.append(np.zeros(0))
        self.phis.append(np.zeros(0))
        self.first.append(0)
        self.was.append(active)

    def _upto(self, end: int) -> Iterator[pd.DataFrame]:
        """Windows from the next one to `end`, without it."""
        while self.next < end:
            lo, hi = self.next, min(end, self.next + self.step)
            if self.params.scan == "lazy":
                events, *columns = zip(*(self._window(j) for j in range(lo, hi)))
                yield _frame(sum(events, []), lo, *map(np.array, columns))
            else:
                yield self._stretch(lo, hi)
            self.next = hi

    def _bring(self, i: int, j: int, last: int, ready: tuple[int, np.ndarray, np.ndarray] | None = None) -> int:
        """Bring a pattern's memberships, those that windows from j on need, up to window `last`, or the latest that there is."""
        params, p = self.params, self.model.patterns[i]
        last = min(last, self.base + len(self.x) - params.ell)
        keep = max(0, j - max(self.model.win, params.ell))
        upto = self.first[i] + len(self.dists[i])
        if upto < keep or not len(self.dists[i]):
            self.dists[i], self.phis[i], self.first[i], upto = np.zeros(0), np.zeros(0), keep, keep
        old = max(0, keep - self.first[i])
        self.first[i] += old
        d = np.zeros(0)
        if upto <= last:
            if ready is not None and upto >= ready[0]:
                pieces = D.prepare(D.sliding(p.shape, params.ell), params.distance)
                d = D.least_euclid(ready[1][upto - ready[0] : last + 1 - ready[0]], pieces, squares=ready[2][upto - ready[0] : last + 1 - ready[0]])
            else:
                d = D.profile(self.x[upto - self.base : last + params.ell - self.base], p.shape, params.ell, params.distance)
            self.evaluations += len(d)
        if old or len(d):
            self.dists[i] = np.concatenate([self.dists[i][old:], d])
            self.phis[i] = np.concatenate([self.phis[i][old:], D.phi(d, p.tau, eta_of(p, params))])
        return last

    def _look(self, i: int, j: int) -> bool:
        """Bring a pattern's memberships up to window j and what lies ahead of it; is it frequent enough to be active?"""
        params, p = self.params, self.model.patterns[i]
        last = self._bring(i, j, j + params.ahead)
        if params.all_active or params.warmup == "hold" and j < self.model.win:
            return True
        lo = max(0, j - self.model.win) - self.first[i]
        return float(np.mean(self.phis[i][lo : last + 1 - self.first[i]])) >= p.freq - 1e-12

    def _born(self, j: int) -> str | None:
        """What comes of a proposal at window j: a pattern 'born', one 'refused', or none."""
        params, model = self.params, self.model
        candidate = relearn(self.x, j, self.base, model, params)
        self.retry = j + (params.retry_every or params.ell)
        if candidate is None or not accept(candidate, model, params):
            return None
        if full(model, params):
            return "refused"
        model.patterns.append(replace(candidate, born_at=j, origin="born", members=[]))
        self._track(False)
        return "born"

    def _stretch(self, lo: int, hi: int) -> pd.DataFrame:
        """Windows from lo to hi, without hi; a birth changes only what comes after it."""
        params, model, ell = self.params, self.model, self.params.ell
        win, ahead, ready = model.win, params.ahead, None
        if hi - lo > win and params.distance in ("zm", "zn"):  # windows are made ready once for all patterns
            at = max(self.base, lo - max(win, ell))
            rows = D.prepare(D.sliding(self.x[at - self.base : hi + ahead + ell - 1 - self.base], ell), params.distance)
            ready = (at, rows, np.einsum("ij,ij->i", rows, rows))

        def look(i: int, ask: int) -> np.ndarray:
            """Activity over the stretch, none before the first window asked about."""
            self._bring(i, ask, hi - 1 + ahead, ready)
            p, first = model.patterns[i], self.first[i]
            avg = rolling_mean(self.phis[i], win, ahead)[ask - first : hi - first]
            on = avg >= p.freq - 1e-12
            if params.all_active:
                on[:] = True
            elif params.warmup == "hold":
                on |= np.arange(ask, hi) < win
            return np.r_[np.zeros(ask - lo, bool), on]

        act, born, events = [look(i, lo) for i in range(len(model.patterns))], {}, []
        while params.births:
            none = ~np.logical_or.reduce(act) if act else np.ones(hi - lo, bool)
            none[: max(0, self.retry - lo)] = False
            if not none.any():
                break
            j = int(none.argmax()) + lo
            came = self._born(j)
            if came == "refused":
                events.append((j, "refused", -1))
            elif came == "born":
                born[len(act)] = j
                events.append((j, "born", len(act)))
                act.append(look(len(act), j))
                act[-1][j - lo] = True
        for i, on in enumerate(act):
            start = born.get(i, lo)
            before = on[start - lo] if i in born or not lo else self.was[i]  # a birth, and the first window's state, are no change
            changed = np.flatnonzero(np.diff(np.r_[before, on[start - lo :]].astype(np.int8)))
            events += [(int(k) + start, "on_recurring" if on[k + start - lo] else "off", i) for k in changed]
        self.was = [bool(on[-1]) for on in act]
        if not act:
            return _frame(events, lo, np.zeros(hi - lo), np.full(hi - lo, -1), np.ones(hi - lo, bool))
        from_ = max(0, lo - ell)
        d = np.full((hi - from_, len(act)), np.inf)
        for i, f in enumerate(self.first):
            d[max(0, f - from_) :, i] = self.dists[i][max(0, from_ - f) : hi - f]
        on = np.stack(act, 1)
        none = ~on.any(1)
        masked = np.where(on | none[:, None], d[lo - from_ :], np.inf)
        for i, j in born.items():
            masked[: j - lo, i] = np.inf
        near = masked.argmin(1)
        score = window_score(d, np.r_[np.full(lo - from_, -1), near], ell, params.align)[lo - from_ :]
        return _frame(events, lo, score, near, none)

    def _window(self, j: int) -> tuple[list, float, int, bool]:
        """(events, score, nearest, no active pattern) of one window of a lazy scan."""
        params, every, born, events = self.params, range(len(self.model.patterns)), None, []
        active = [self.was[i] and self._look(i, j) for i in every]
        if not any(active):
            active = [self._look(i, j) for i in every]
        if not any(active) and params.births and j >= self.retry:
            came = self._born(j)
            if came == "refused":
                events.append((j, "refused", -1))
            elif came == "born":
                born = len(active)
                self._look(born, j)
                active.append(True)
        for i, (now, before) in enumerate(zip(active, self.was)):
            if i == born:
                events.append((j, "born", i))
            elif j and now != before:
                events.append((j, "on_recurring" if now else "off", i))
        self.was = active
        none = not any(active)
        here = {i: self.dists[i][j - self.first[i]] for i in range(len(active)) if active[i] or none}
        q = min(here, key=lambda i: (here[i], i), default=-1)
        at = j - self.first[q] if q >= 0 else 0
        score = float(self.dists[q][max(0, at - params.ell) : at + 1].min()) if q >= 0 else 0.0
        return events, score, q, none


def _frame(events: list[tuple[int, str, int]] = (), lo: int = 0, score: np.ndarray = np.zeros(0), near: np.ndarray = np.zeros(0, int), none: np.ndarray = np.zeros(0, bool)) -> pd.DataFrame:
    """Rows in the order of their windows, a window's events before its score."""
    events, n = sorted(events, key=lambda e: (e[0], e[1] != "refused", e[2])), len(score)
    start = np.r_[np.array([e[0] for e in events], int), np.arange(lo, lo + n)]
    pattern = np.r_[np.array([e[2] for e in events], int), near]
    blank = np.full(len(events), -1)
    columns = [start, np.r_[np.full(len(events), np.nan), score], np.r_[blank, near], np.r_[np.zeros(len(events), bool), none], np.array([e[1] for e in events] + [None] * n, object), pattern]
    f = pd.DataFrame(dict(zip(NAMES, columns))).astype({"score": "float64", "nearest": "int32", "pattern_id": "int32"})
    return f.iloc[np.argsort(start, kind="stable")] if events else f


def _tuples(f: pd.DataFrame) -> Iterator[tuple]:
    for start, score, near, none, event, pattern in zip(*(f[c].tolist() for c in NAMES)):
        yield start, None if event else score, near, none, event, pattern


def feed(live: LiveSeries, frames: Iterator[pd.DataFrame], series: object) -> Iterator[pd.DataFrame]:
    """What a micro-batch's points give, a frame for each stretch."""
    pos, x = (np.concatenate(c) for c in zip(*((f["pos"].to_numpy(), f["x"].to_numpy(float)) for f in frames)))
    order = np.argsort(pos, kind="stable")
    for f in live.push_all(pos[order], x[order]):
        f.insert(0, "series_id", series)
        yield f


class Detector(StatefulProcessor):
    """State of a series: its points, memberships and patterns; points and memberships are bounded by the window, patterns only by max_patterns where given."""

    def __init__(self, params: Params, train_points: int):
        self.params, self.train_points = params, train_points

    def init(self, handle) -> None:  # noqa: ANN001
        self.state = handle.getValueState("series", "live binary")

    def handleInputRows(self, key, rows, timerValues) -> Iterator[pd.DataFrame]:  # noqa: ANN001, N802, N803
        live: LiveSeries = pickle.loads(self.state.get()[0]) if self.state.exists() else LiveSeries(self.params, self.train_points)
        yield from feed(live, rows, key[0])
        self.state.update((pickle.dumps(live),))

    def handleExpiredTimer(self, key, timerValues, expiredTimerInfo) -> Iterator[pd.DataFrame]:  # noqa: ANN001, N802, N803
        return iter([])

    def close(self) -> None:
        pass


def detect_stream(points: DataFrame, params: Params, train_points: int) -> DataFrame:
    """points (series_id, pos, x) as a stream to scores and drift events.  The session needs the RocksDB state store."""
    ship(points.sparkSession)
    return points.groupBy("series_id").transformWithStateInPandas(Detector(params, train_points), OUT, "Append", "None")


def detect_stream_plain(points: DataFrame, params: Params, train_points: int) -> DataFrame:
    """The same with applyInPandasWithState, for sessions with the default state store."""
    from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

    ship(points.sparkSession)

    def run(key: tuple, frames: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        live = pickle.loads(state.get[0]) if state.exists else LiveSeries(params, train_points)
        yield from feed(live, frames, key[0])
        state.update((pickle.dumps(live),))

    return points.groupBy("series_id").applyInPandasWithState(run, OUT, "live binary", "append", GroupStateTimeout.NoTimeout)


def hourly_stream(events: DataFrame, delay: str = "1 hour") -> DataFrame:
    """Sums per hour of an event stream; an hour comes out when the watermark has passed it."""
    w = F.window("ts", "1 hour")
    return events.withWatermark("ts", delay).groupBy(w.alias("w")).agg(F.sum("value").alias("x"), F.count(F.lit(1)).alias("n")).select(F.unix_seconds("w.start").alias("start_s"), "x", "n")


def session_stream(events: DataFrame, gap: str = "30 minutes", delay: str = "1 hour") -> DataFrame:
    w = F.session_window("ts", gap)
    return events.withWatermark("ts", delay).groupBy("event_type", w.alias("w")).agg(F.count(F.lit(1)).alias("n")).select("event_type", F.unix_seconds("w.start").alias("start_s"), "n")


def dedup_stream(events: DataFrame, key: str = "event_id", delay: str = "1 hour") -> DataFrame:
    return events.withWatermark("ts", delay).dropDuplicatesWithinWatermark([key])


def late_rows(events: DataFrame, key: str, ts: str = "ts", delay_s: int = 3600) -> DataFrame:
    """(key, rows, late) of each micro-batch: rows that are more than the delay behind the latest of their key in earlier
    micro-batches, which a watermark of that delay for the key would drop.  The state is one number a key."""
    from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

    rows = events.select(F.col(key).cast("string").alias("key"), F.unix_micros(F.col(ts).cast("timestamp")).alias("us")).filter("us is not null")

    def run(k: tuple, frames: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
        bound = state.get[0] - delay_s * 1_000_000 if state.exists else None
        n = late = 0
        top = state.get[0] if state.exists else None
        for f in frames:
            n += len(f)
            late += int((f["us"] < bound).sum()) if bound is not None else 0
            top = int(f["us"].max()) if top is None else max(top, int(f["us"].max()))
        state.update((top,))
        yield pd.DataFrame({"key": [k[0]], "rows": [n], "late": [late]})

    return rows.groupBy("key").applyInPandasWithState(run, "key string, rows bigint, late bigint", "top bigint", "append", GroupStateTimeout.NoTimeout)


def run_to_table(stream: DataFrame, folder: str, mode: str = "append") -> DataFrame:
    """Run a stream over what is there and read back what it wrote."""
    spark = stream.sparkSession
    q = stream.writeStream.outputMode(mode).format("parquet").option("path", f"{folder}/out").option("checkpointLocation", f"{folder}/state").trigger(availableNow=True).start()
    q.awaitTermination()
    return spark.read.schema(stream.schema).parquet(f"{folder}/out")
