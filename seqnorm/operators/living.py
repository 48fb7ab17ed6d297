"""The living model of one series in NumPy: training, detection in epochs, the offline mode.  Operators in model.py and
detect.py run these kernels for each series of a DataFrame."""

from __future__ import annotations

from collections.abc import Iterable, Iterator
from dataclasses import dataclass, field, replace

import numpy as np

from seqnorm.functions import distance as D
from seqnorm.operators.contig import branch_cut, cluster, free_forest


@dataclass(frozen=True)
class Params:
    ell: int = 50
    mult: int = 2
    k: int = 1
    r_min: float = 0.01
    win_max: int = 20  # in windows of length ell
    eta: float | None = None  # None: one over a pattern's radius
    distance: str = "zm"
    linkage: str = "ward"
    cut_rule: str = "mean_jump"
    repair: bool = True
    sigmas: float = 3.0
    tau_len: str = "segment"
    presence: str = "overlap"
    warmup: str = "partial"
    delta: int = 0
    retry_every: int | None = None
    relearn_mult: float = 1.0
    max_patterns: int | None = None  # with a limit, admitted patterns beyond it are refused and reported
    min_separation: float | None = None
    births: bool = True
    all_active: bool = False
    weighted: bool = False
    align: str = "trailing"
    contiguous: bool = True
    scan: str = "all"  # lazy: inactive patterns are looked at, and may come back, only where no active one is left

    @property
    def ell_m(self) -> int:
        return self.mult * self.ell

    @property
    def ahead(self) -> int:
        """Windows after the current one that the delay lets a membership's mean see."""
        return max(0, self.delta - self.ell)


@dataclass
class Pattern:
    shape: np.ndarray
    tau: float
    freq: float
    members: list[int]  # segments
    born_at: int = -1
    origin: str = "trained"


@dataclass
class Living:
    patterns: list[Pattern]
    win: int
    unclustered: list[int] = field(default_factory=list)
    splits: int = 0

    def copy(self) -> "Living":
        return replace(self, patterns=list(self.patterns))


def eta_of(p: Pattern, params: Params) -> float:
    return params.eta if params.eta is not None else 1.0 / max(p.tau, 1e-12)


def rolling_mean(v: np.ndarray, before: int, after: int = 0) -> np.ndarray:
    """Mean of v over [j - before, j + after], over what exists of it."""
    total = np.concatenate([[0.0], np.cumsum(v)])
    at = np.arange(len(v))
    lo, hi = np.maximum(at - before, 0), np.minimum(at + after + 1, len(v))
    return (total[hi] - total[lo]) / np.maximum(hi - lo, 1)


STEP = 1 << 15  # windows of a long series that are worked on at a time


def presence_of(phi: np.ndarray | Iterable[np.ndarray], members: list[int], win: int, ell_m: int, ell: int, mode: str, base: int = 0) -> float:
    """Smallest mean membership over windows of `win` starts that meet the cluster's span as `mode` asks; phi, which may come in
    stretches of at least `win`, begins with that of window `base`."""
    parts = [phi] if isinstance(phi, np.ndarray) else phi
    first, last = min(members) * ell_m, (max(members) + 1) * ell_m - 1
    least, total, count, held = np.inf, 0.0, 0, np.zeros(0)
    for part in parts:
        part = np.concatenate([held, part])
        win = max(1, min(win, len(part)))
        means = np.convolve(part, np.ones(win) / win, "valid")
        lo = np.arange(len(means)) + base + count
        hi = lo + win + ell - 2  # last point of the window's last subsequence
        common = np.minimum(hi, last) - np.maximum(lo, first) + 1
        span = min(last - first + 1, win + ell - 1)
        ok = {"overlap": common > 0, "majority": 2 * common >= span, "contain": common >= span}[mode]
        least = min(least, means[ok].min(initial=np.inf))
        total, count, held = total + means.sum(), count + len(means), part[len(means) :]
    return float(least) if np.isfinite(least) else float(total / count)


def memberships(x: np.ndarray, p: "Pattern", params: "Params", lo: int, hi: int, step: int) -> Iterator[np.ndarray]:
    """Memberships of the windows from lo to hi, without hi, in stretches of at least `step`."""
    while lo < hi:
        end = hi if hi - lo < 2 * step else lo + step
        yield D.phi(D.profile(x[lo : end + params.ell - 1], p.shape, params.ell, params.distance), p.tau, eta_of(p, params))
        lo = end


def tree_without_time(rows: np.ndarray, params: Params) -> list[list[int]]:
    """Clustering without the neighbourhood: any two clusters may join."""
    if params.linkage == "ward":
        return branch_cut(free_forest(rows), params.cut_rule)
    return cluster(rows, params.cut_rule, linkage=params.linkage, k=len(rows), repair=False)[1]


def mean_of(rows: np.ndarray, members: list[int]) -> np.ndarray:
    """The members' mean; many members are summed a stretch at a time."""
    if len(members) <= STEP:
        return rows[members].mean(0)
    return np.sum([rows[members[at : at + STEP]].sum(0) for at in range(0, len(members), STEP)], 0) / len(members)


def fit_series(x: np.ndarray, params: Params, win: int | None = None) -> Living:
    """Patterns, radii, presence bounds and the currency window from a stretch of points."""
    ell, ell_m = params.ell, params.ell_m
    s = len(x) // ell_m
    if s == 0:
        return Living([], params.win_max * ell)
    rows = x[: s * ell_m].reshape(s, ell_m)
    kind = params.distance if params.distance in ("zm", "zn") else "zm"
    ready = D.prepare(rows, kind)
    splits = 0
    if s == 1:
        found = [[0]]
    elif params.contiguous:
        forest, found = cluster(ready, params.cut_rule, linkage=params.linkage, k=params.k, repair=params.repair)
        splits = forest.splits
        del forest
    else:
        found = tree_without_time(ready, params)
    least = max(2, int(np.ceil(params.r_min * s)))
    kept = [c for c in found if len(c) >= least]
    rest = sorted(i for c in found if len(c) < least for i in c)
    if not kept:
        kept = [max(found, key=len)]
        rest = sorted(set(range(s)) - set(kept[0]))
    size = win or min(params.win_max * ell, 2 * min(map(len, kept)) * ell_m)
    patterns = []
    for members in kept:
        shape = mean_of(ready, members)
        if params.tau_len == "segment":
            centre = D.prepare(shape[None], kind)
            d = np.concatenate([np.linalg.norm(ready[members[at : at + STEP]] - centre, axis=1) for at in range(0, len(members), STEP)]) if kind == params.distance else D.to_shape(rows[members], shape, params.distance)
        else:
            inside = np.concatenate([np.arange(m * ell_m, (m + 1) * ell_m - ell + 1) for m in members])
            d = D.placements(D.sliding(x, ell)[inside], shape, params.distance).min(1)
        patterns.append(Pattern(shape, float(d.mean() + params.sigmas * d.std()), 0.0, members))
    n = len(x) - ell + 1
    width = max(1, min(size, n))
    for p in patterns:  # only windows of `width` starts that meet the cluster's span count, so only their distances are needed
        lo = min(max(0, min(p.members) * ell_m - width - ell), n - width)
        hi = min(n, (max(p.members) + 1) * ell_m + width)
        p.freq = presence_of(memberships(x, p, params, lo, hi, max(STEP, width)), p.members, size, ell_m, ell, params.presence, lo)
    return Living(patterns, int(size), rest, splits)


@dataclass
class Detected:
    score: np.ndarray
    nearest: np.ndarray
    no_active: np.ndarray
    active: np.ndarray  # (windows, patterns)
    dist: np.ndarray  # (windows, patterns)
    phi_avg: np.ndarray
    model: Living
    births: list[tuple[int, int]]  # (window, pattern)
    epochs: int = 0
    evaluations: int = 0
    refused: list[int] = field(default_factory=list)  # windows at which max_patterns kept an admitted pattern out


def activity(phi: np.ndarray, freq: float, win: int, params: Params) -> tuple[np.ndarray, np.ndarray]:
    """(mean membership, active) of one pattern at every window."""
    avg = rolling_mean(phi, win, params.ahead)
    active = avg >= freq - 1e-12
    if params.warmup == "hold":
        active[:win] = True
    return avg, active


def window_score(d: np.ndarray, nearest: np.ndarray, ell: int, align: str) -> np.ndarray:
    """Smallest distance to the window's nearest pattern over the trailing (or centred) ell windows."""
    n, m = d.shape
    out = np.empty(n)
    before, after = (ell, 0) if align == "trailing" else (ell // 2, ell // 2)
    for q in range(m):
        mine = nearest == q
        if mine.any():
            padded = np.concatenate([np.full(before, np.inf), d[:, q], np.full(after, np.inf)])
            out[mine] = D.sliding(padded, before + after + 1).min(1)[mine]
    return out


def propose(x: np.ndarray, params: Params, win: int) -> Pattern | None:
    """The pattern of the largest cluster of a stretch; ties go to the more frequent, then to the earlier."""
    model = fit_series(x, params, win)
    return max(model.patterns, key=lambda p: (len(p.members), p.freq, -min(p.members)), default=None)


def accept(candidate: Pattern, model: Living, params: Params) -> bool:
    """Far from every pattern of the model, and more frequent than its least frequent one."""
    gaps = D.to_shape(np.array([p.shape for p in model.patterns]), candidate.shape, params.distance) if model.patterns else []
    far = all(g > p.tau for g, p in zip(gaps, model.patterns))
    if params.min_separation is not None:
        far = far and all(g > params.min_separation for g in gaps)
    return far and (not model.patterns or candidate.freq > min(p.freq for p in model.patterns))


def full(model: Living, params: Params) -> bool:
    return params.max_patterns is not None and len(model.patterns) >= params.max_patterns


def relearn(x: np.ndarray, j: int, base: int, model: Living, params: Params) -> Pattern | None:
    """What the points up to window j, and the delay's after it, propose; x[0] stands at position `base`."""
    back = int(max(model.win, 2 * params.ell_m) * params.relearn_mult)
    stretch = x[max(0, j + params.ell - back - base) : j + params.ell + params.delta - base]
    return propose(stretch, params, min(model.win, max(1, len(stretch) - params.ell + 1)))


class Ledger:
    """Distances of windows to patterns, worked out a chunk at a time and only where someone asks for them."""

    def __init__(self, x: np.ndarray, params: Params, win: int):
        self.x, self.params, self.n = x, params, len(x) - params.ell + 1
        self.win, self.step = win, max(params.ell, win // 4)
        self.patterns: list[Pattern] = []
        self.dist: list[np.ndarray] = []
        self.done: list[np.ndarray] = []
        self.evaluations = 0

    def add(self, p: Pattern) -> None:
        self.patterns.append(p)
        self.dist.append(np.full(self.n, np.inf))
        self.done.append(np.zeros(-(-self.n // self.step), bool))

    def get(self, i: int, lo: int, hi: int) -> np.ndarray:
        """Distances of the windows from lo to hi, without hi."""
        for c in range(lo // self.step, -(-hi // self.step)):
            if not self.done[i][c]:
                a, b = c * self.step, min(self.n, (c + 1) * self.step)
                self.dist[i][a:b] = D.profile(self.x[a : b + self.params.ell - 1], self.patterns[i].shape, self.params.ell, self.params.distance)
                self.done[i][c] = True
                self.evaluations += b - a
        return self.dist[i][lo:hi]

    def frequent(self, i: int, lo: int, hi: int) -> tuple[np.ndarray, np.ndarray]:
        """(mean membership, frequent enough to be active) of the windows from lo to hi, without hi."""
        first, last = max(0, lo - self.win), min(self.n, hi + self.params.ahead)
        p = self.patterns[i]
        avg = rolling_mean(D.phi(self.get(i, first, last), p.tau, eta_of(p, self.params)), self.win, self.params.ahead)[lo - first : hi - first]
        on = avg >= p.freq - 1e-12
        if self.params.warmup == "hold":
            on |= np.arange(lo, hi) < self.win
        return avg, on


def detect_lazily(x: np.ndarray, model: Living, params: Params) -> Detected:
    """Scores of all windows, active patterns first: an inactive pattern is looked at only where no active one is left, and
    comes back there if it is frequent enough.  All patterns are active at first.

    Patterns that lie idle cost nothing, but one that recurs beside an active pattern stays inactive until that one has
    gone, so activity and scores may differ from the full scan's.  Distances that nobody asked for are infinite in the
    result, memberships zero."""
    model, ell, n = model.copy(), params.ell, len(x) - params.ell + 1
    led = Ledger(x, params, model.win)
    for p in model.patterns:
        led.add(p)
    on = [np.zeros(n, bool) for _ in model.patterns]
    avg = [np.zeros(n) for _ in model.patterns]
    births, refused, epochs, at, j = [], [], 1, 2 * params.ell_m, 0
    alive = set(range(len(model.patterns)))
    while j < n:
        # a stretch ends with its chunk, with the last active pattern, or where an inactive one comes back
        e = min(n, (j // led.step + 1) * led.step)
        looked = sorted(alive) or list(range(len(model.patterns)))
        seen = {i: led.frequent(i, j, e) for i in looked}
        if alive:
            ends = {i: int(np.argmin(f)) + j if not f.all() else e for i, (_, f) in seen.items()}
            upto = max(ends.values())
            for i, (a, _) in seen.items():
                on[i][j : ends[i]] = True
                avg[i][j:upto] = a[: upto - j]
            alive = {i for i in alive if ends[i] >= e} if upto >= e else set()
            j = upto
            continue
        back = np.logical_or.reduce([f for _, f in seen.values()]) if seen else np.zeros(e - j, bool)
        upto = int(back.argmax()) + j if back.any() else e
        tried = max(j, at) if params.births else e
        if tried < upto:
            epochs += 1
            candidate = relearn(x, tried, 0, model, params)
            at = tried + (params.retry_every or ell)
            upto = tried + 1
            if candidate is not None and accept(candidate, model, params):
                if full(model, params):
                    refused.append(tried)
                else:
                    model.patterns.append(replace(candidate, born_at=tried, origin="born", members=[]))
                    births.append((tried, len(model.patterns) - 1))
                    led.add(model.patterns[-1])
                    on.append(np.zeros(n, bool))
                    avg.append(np.zeros(n))
                    on[-1][tried] = True
                    avg[-1][tried] = led.frequent(len(on) - 1, tried, tried + 1)[0][0]
                    alive = {len(on) - 1}
        elif back.any():
            alive = {i for i, (_, f) in seen.items() if f[upto - j]}
        for i, (a, _) in seen.items():
            avg[i][j:upto] = a[: upto - j]
        j = upto
    m = len(model.patterns)
    if not m:
        return Detected(np.zeros(n), np.full(n, -1), np.ones(n, bool), np.zeros((n, 0), bool), np.zeros((n, 0)), np.zeros((n, 0)), model, births, epochs, 0, refused)
    active = np.stack(on, 1)
    none = ~active.any(1)
    born = {q: j for j, q in births}
    for q in range(m):
        for lo, hi in runs_of((active[:, q] | none) & (np.arange(n) >= born.get(q, 0))):
            led.get(q, max(0, lo - ell), hi)
    d = np.stack(led.dist, 1)
    masked = np.where(active | none[:, None], d, np.inf)
    for at_, q in births:
        masked[:at_, q] = np.inf
    nearest = masked.argmin(1)
    return Detected(window_score(d, nearest, ell, params.align), nearest, none, active, d, np.stack(avg, 1), model, births, epochs, led.evaluations, refused)


def runs_of(flags: np.ndarray) -> list[tuple[int, int]]:
    """Start and end (without it) of every run of true flags."""
    edges = np.flatnonzero(np.diff(np.r_[False, flags, False].astype(np.int8)))
    return list(zip(edges[::2].tolist(), edges[1::2].tolist()))


def detect_series(x: np.ndarray, model: Living, params: Params) -> Detected:
    """Scores of all windows.  For given patterns everything is a function of position; a birth changes only what comes
    after it, so each epoch ends at the first window without an active pattern whose proposal is admitted."""
    if params.scan == "lazy" and len(x) >= params.ell:
        if params.weighted or params.all_active or params.align != "trailing":
            raise ValueError("a lazy scan knows no weighted, all-active or centred scores")
        return detect_lazily(x, model, params)
    model, ell, n = model.copy(), params.ell, len(x) - params.ell + 1
    births: list[tuple[int, int]] = []
    refused: list[int] = []
    if n <= 0:
        z = np.zeros(0)
        return Detected(z, z.astype(int), z.astype(bool), np.zeros((0, len(model.patterns)), bool), np.zeros((0, len(model.patterns))), np.zeros((0, len(model.patterns))), model, births)
    dist, avg, act, evaluations = [], [], [], 0

    def look(p: Pattern, from_: int = 0) -> None:
        nonlocal evaluations
        d = D.profile(x, p.shape, ell, params.distance)
        evaluations += len(d)
        a, on = activity(D.phi(d, p.tau, eta_of(p, params)), p.freq, model.win, params)
        if params.all_active:
            on[:] = True
        on[:from_] = False
        dist.append(d)
        avg.append(a)
        act.append(on)

    for p in model.patterns:
        look(p)
    pace, epochs, at = params.retry_every or ell, 1, 0
    if params.births:
        # before a first full segment has been seen there is nothing to learn from
        while True:
            none = ~np.logical_or.reduce(act) if act else np.ones(n, bool)
            none[: max(at, 2 * params.ell_m)] = False
            if not none.any():
                break
            j = int(none.argmax())
            epochs += 1
            candidate = relearn(x, j, 0, model, params)
            if candidate is not None and accept(candidate, model, params) and full(model, params):
                refused.append(j)
            elif candidate is not None and accept(candidate, model, params):
                born = replace(candidate, born_at=j, origin="born", members=[])
                model.patterns.append(born)
                births.append((j, len(model.patterns) - 1))
                look(born, j)
                act[-1][j] = True
            at = j + pace
    if not dist:
        return Detected(np.zeros(n), np.full(n, -1), np.ones(n, bool), np.zeros((n, 0), bool), np.zeros((n, 0)), np.zeros((n, 0)), model, births, epochs, evaluations, refused)
    d, on = np.stack(dist, 1), np.stack(act, 1)
    no_active = ~on.any(1)
    masked = np.where(on | no_active[:, None], d, np.inf)
    for j, q in births:
        masked[:j, q] = np.inf
    nearest = masked.argmin(1)
    if params.weighted:
        weight = np.array([max(1, len(p.members)) for p in model.patterns], float)
        score = d @ (weight / weight.sum())
    else:
        score = window_score(d, nearest, ell, params.align)
    return Detected(score, nearest, no_active, on, d, np.stack(avg, 1), model, births, epochs, evaluations, refused)


def scan_series(x: np.ndarray, model: Living, params: Params, step: int = STEP) -> Detected:
    """The scores of `detect_series` for series of any length, worked out a stretch of windows at a time.

    A stretch needs the currency window and ell windows before it and the delay's windows after it, and a birth changes only what
    comes after it.  Memory beyond the scores goes with the stretch; activity, distances and memberships are not kept."""
    ell, n = params.ell, len(x) - params.ell + 1
    if n <= step or not model.patterns or params.scan == "lazy" or params.weighted or params.align != "trailing":
        return detect_series(x, model, params)
    model, win, ahead, pace = model.copy(), model.win, params.ahead, params.retry_every or ell
    births: list[tuple[int, int]] = []
    refused: list[int] = []
    score, nearest, no_active = np.empty(n), np.empty(n, np.int32), np.zeros(n, bool)
    epochs, evaluations, at = 1, 0, 2 * params.ell_m
    for lo in range(0, n, step):
        hi = min(n, lo + step)
        dist, act = [], []
        base, end = max(0, lo - max(win, ell)), min(n, hi + ahead)
        if params.distance in ("zm", "zn"):  # windows are made ready once for all patterns
            ready = D.prepare(D.sliding(x[base : end + ell - 1], ell), params.distance)
            squares = np.einsum("ij,ij->i", ready, ready)

        def look(p: Pattern, born: int) -> None:
            """Distances from what the first window asked about needs, infinite before; activity from `born` on."""
            nonlocal evaluations
            ask = max(lo, born)
            first = max(0, ask - max(win, ell))
            if params.distance in ("zm", "zn"):
                pieces = D.prepare(D.sliding(p.shape, ell), params.distance)
                d = D.least_euclid(ready[first - base :], pieces, squares=squares[first - base :])
            else:
                d = D.profile(x[first : end + ell - 1], p.shape, ell, params.distance)
            evaluations += len(d)
            on = activity(D.phi(d, p.tau, eta_of(p, params)), p.freq, win, params)[1][ask - first : hi - first]
            if params.all_active:
                on = np.ones(hi - ask, bool)
            act.append(np.r_[np.zeros(ask - lo, bool), on])
            dist.append(np.r_[np.full(first - max(0, lo - ell), np.inf), d[: hi - first]] if first > lo - ell else d[max(0, lo - ell) - first : hi - first])

        for p in model.patterns:
            look(p, 0)
        while params.births:
            none = ~np.logical_or.reduce(act)
            none[: max(0, at - lo)] = False
            if not none.any():
                break
            j = int(none.argmax()) + lo
            epochs += 1
            candidate = relearn(x, j, 0, model, params)
            if candidate is not None and accept(candidate, model, params):
                if full(model, params):
                    refused.append(j)
                else:
                    model.patterns.append(replace(candidate, born_at=j, origin="born", members=[]))
                    births.append((j, len(model.patterns) - 1))
                    look(model.patterns[-1], j)
                    act[-1][j - lo] = True
            at = j + pace
        before = lo - max(0, lo - ell)
        d, on = np.stack(dist, 1), np.stack(act, 1)
        none = ~on.any(1)
        masked = np.where(on | none[:, None], d[before:], np.inf)
        for j, q in births:
            masked[: max(0, j - lo), q] = np.inf
        near = masked.argmin(1)
        score[lo:hi] = window_score(d, np.r_[np.full(before, -1), near], ell, params.align)[before:]
        nearest[lo:hi], no_active[lo:hi] = near, none
    kept = np.zeros((n, 0))
    return Detected(score, nearest, no_active, kept.astype(bool), kept, kept, model, births, epochs, evaluations, refused)


def offline_series(x: np.ndarray, params: Params, keep: bool = True, step: int = STEP) -> Detected:
    """Train on everything; each window is compared with the pattern that has the member nearest in time (the earlier on a tie).

    Unless activity and distances are to be kept, a pattern's distances are worked out only where windows are compared with it,
    and windows are worked on in stretches, so that memory beyond the scores doesn't grow with them."""
    model = fit_series(x, params)
    ell, n = params.ell, len(x) - params.ell + 1
    if n <= 0 or not model.patterns:
        return detect_series(x, model, replace(params, births=False))
    owner = np.full(len(x) // params.ell_m, -1)
    for q, p in enumerate(model.patterns):
        owner[p.members] = q
    known = np.flatnonzero(owner >= 0)
    nearest = np.empty(n, np.int32)
    for lo in range(0, n, step):
        seg = np.clip((np.arange(lo, min(n, lo + step)) + ell // 2) / params.ell_m - 0.5, 0, None)
        right = np.clip(np.searchsorted(known, seg), 0, len(known) - 1)
        left = np.maximum(right - 1, 0)
        pick = np.where(np.abs(known[left] - seg) <= np.abs(known[right] - seg), left, right)
        nearest[lo : lo + step] = owner[known[pick]]
    if not keep and params.align == "trailing":
        score, evaluations = np.empty(n), 0
        edges = np.r_[0, np.flatnonzero(np.diff(nearest)) + 1, n].tolist()
        for lo, hi in zip(edges, edges[1:]):
            p, before = model.patterns[nearest[lo]], np.full(ell, np.inf)
            at = max(0, lo - ell)  # the ell windows before a run are looked at, not scored
            while at < hi:
                end = min(hi, max(at, lo) + step)
                d = D.profile(x[at : end + ell - 1], p.shape, ell, params.distance)
                evaluations += len(d)
                padded = np.concatenate([before, d])
                score[max(at, lo) : end] = D.sliding(padded, ell + 1).min(1)[max(at, lo) - at :]
                at, before = end, padded[len(padded) - ell :]
        kept = np.zeros((n, 0))
        return Detected(score, nearest, np.zeros(n, bool), kept.astype(bool), kept, kept, model, [], 1, evaluations)
    d = np.stack([D.profile(x, p.shape, ell, params.distance) for p in model.patterns], 1)
    score = window_score(d, nearest, ell, params.align)
    on = np.zeros_like(d, bool)
    on[np.arange(n), nearest] = True
    return Detected(score, nearest, np.zeros(n, bool), on, d, np.zeros_like(d), model, [], 1, d.size)
