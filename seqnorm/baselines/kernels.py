"""The compared detectors as NumPy kernels of one series."""

from __future__ import annotations

import numpy as np

from seqnorm.functions import distance as D


def centred_mean(v: np.ndarray, width: int) -> np.ndarray:
    total = np.concatenate([[0.0], np.cumsum(v)])
    at = np.arange(len(v))
    lo, hi = np.maximum(at - width // 2, 0), np.minimum(at + width // 2 + 1, len(v))
    return (total[hi] - total[lo]) / (hi - lo)


# -- static weighted model ---------------------------------------------------------------------------


def static_fit(x: np.ndarray, ell: int, mult: int = 2, sample: int = 5000, select: str = "random", weight: str = "freq", seed: int = 3) -> tuple[list[np.ndarray], np.ndarray]:
    """(patterns, weights): clusters of sampled windows without any constraint in time, cut at the largest relative jump."""
    length = ell * mult
    windows = D.sliding(x, length) if len(x) >= length else np.zeros((0, length))
    if not len(windows):
        return [], np.zeros(0)
    rng = np.random.default_rng(seed)
    at = np.sort(rng.permutation(len(windows))[:sample])
    ready = D.prepare(windows[at], "zn")
    if select == "motif":  # those with a close match elsewhere
        d = D._euclid(ready, ready)
        d[np.abs(at[:, None] - at[None, :]) < length // 2] = np.inf
        good = np.argsort(d.min(1))[: max(2, len(at) // 2)]
        at, ready = at[good], ready[good]
    groups = _free_clusters(ready)
    shapes = [ready[g].mean(0) for g in groups]
    w = np.array([len(g) for g in groups], float)
    if weight != "freq":
        cover = np.array([np.ptp(at[g]) + length for g in groups], float) / len(x)
        central = np.array([1.0 / (1e-9 + sum(np.linalg.norm(s - t) for t in shapes)) for s in shapes])
        w = w * w * cover * central
    return shapes, w / w.sum()


def _free_clusters(ready: np.ndarray) -> list[list[int]]:
    """Ward clustering of any rows by nearest-neighbour chains, cut at the largest relative jump of heights."""
    n = len(ready)
    size, mean = np.ones(n), np.array(ready, float)
    square = np.einsum("ij,ij->i", mean, mean)
    names = np.arange(n)  # of the rows kept: those joined away go when they are half of them
    gone = np.zeros(n, bool)
    joins, chain = [], []
    while len(names) - gone.sum() > 1:
        if 2 * gone.sum() > len(names):
            place = np.cumsum(~gone) - 1
            chain = [int(place[c]) for c in chain]
            names, size, mean, square, gone = names[~gone], size[~gone], mean[~gone], square[~gone], gone[~gone]
        if not chain:
            chain = [int(np.flatnonzero(~gone)[0])]
        while True:
            a = chain[-1]
            d = np.maximum(square + square[a] - 2.0 * (mean @ mean[a]), 0.0) * (2.0 * size[a] * size / (size[a] + size))
            d[gone] = np.inf
            d[a] = np.inf
            b = int(d.argmin())
            if len(chain) > 1 and (b == chain[-2] or np.isclose(d[b], d[chain[-2]])):
                b = chain[-2]
                joins.append((float(np.sqrt(d[b])), int(names[b]), int(names[a])))
                chain = chain[:-2]
                mean[b] = (size[a] * mean[a] + size[b] * mean[b]) / (size[a] + size[b])
                square[b] = mean[b] @ mean[b]
                size[b] += size[a]
                gone[a] = True
                break
            chain.append(b)
    joins.sort(key=lambda j: j[0])
    heights = np.array([j[0] for j in joins])
    if n < 3:
        keep = len(joins)
    else:
        tail = max(1, len(heights) // 2)  # jumps between small heights say nothing
        keep = tail + int(np.argmax(np.diff(heights)[tail - 1 :] / (heights[tail - 1 : -1] + 1e-9))) if len(heights) > tail else len(heights)
    owner = list(range(n))

    def find(i: int) -> int:
        while owner[i] != i:
            owner[i] = owner[owner[i]]
            i = owner[i]
        return i

    for _, a, b in joins[:keep]:
        owner[find(b)] = find(a)
    groups: dict[int, list[int]] = {}
    for i in range(n):
        groups.setdefault(find(i), []).append(i)
    return list(groups.values())


def static_score(x: np.ndarray, shapes: list[np.ndarray], weights: np.ndarray, ell: int, rows: int = 2048) -> np.ndarray:
    """Mean distance to the shapes; windows are made ready once for all of them."""
    n = len(x) - ell + 1
    if n <= 0 or not shapes:
        return np.zeros(max(n, 0))
    total, pieces = np.zeros(n), [D.prepare(D.sliding(np.asarray(s, float), ell), "zn") for s in shapes]
    for at in range(0, n, rows):
        ready = D.prepare(D.sliding(np.asarray(x[at : at + rows + ell - 1], float), ell), "zn")
        squares = np.einsum("ij,ij->i", ready, ready)
        for p, w in zip(pieces, weights):
            total[at : at + rows] += w * D.least_euclid(ready, p, rows, squares)
    return centred_mean(total, ell)


# -- batch shape model -------------------------------------------------------------------------------


def shape_distances(rows: np.ndarray, centre: np.ndarray, norms: np.ndarray | None = None, block: int = 1024) -> tuple[np.ndarray, np.ndarray]:
    """(shape-based distance, best shift) of rows to a centre, all centred; of equal shifts the least.

    At these lengths a product with the centre at all its shifts takes less time than a transform of each row.
    norms: those of the rows."""
    length, (best, shift) = len(centre), (np.empty(len(rows)), np.empty(len(rows), int))
    padded = np.zeros(3 * length - 2)
    padded[length - 1 : 2 * length - 1] = centre
    shifted = np.ascontiguousarray(D.sliding(padded, length)[::-1].T)  # columns by shift, from 1 - length to length - 1
    for at in range(0, len(rows), block):
        cross = rows[at : at + block] @ shifted
        i = cross.argmax(1)
        best[at : at + block], shift[at : at + block] = cross[np.arange(len(i)), i], i - (length - 1)
    size = (np.linalg.norm(rows, axis=1) if norms is None else norms) * np.linalg.norm(centre)
    return 1.0 - best / np.where(size < 1e-12, 1.0, size), shift


def k_shape(rows: np.ndarray, k: int, seed: int = 5, rounds: int = 10) -> tuple[np.ndarray, np.ndarray]:
    """(centres, owner): assign by shape-based distance, refine each centre by the leading direction of its aligned members.

    Members are aligned by the shifts that their assignment found."""
    rng = np.random.default_rng(seed)
    rows = D.prepare(rows, "zn")
    length = rows.shape[1]
    norms = np.linalg.norm(rows, axis=1)
    owner = rng.integers(0, k, len(rows))
    centres, shifts = np.zeros((k, length)), np.zeros((len(rows), k), int)
    for _ in range(rounds):
        for c in range(k):
            mine = np.flatnonzero(owner == c)
            if not len(mine):
                mine = rng.integers(0, len(rows), 1)
            aligned = rows[mine]
            if np.linalg.norm(centres[c]) > 0:
                aligned = np.take_along_axis(aligned, (np.arange(length) + shifts[mine, c][:, None]) % length, 1)
            aligned = D.prepare(aligned, "zn")
            v, products = aligned.sum(0) + 1e-9, aligned.T @ aligned
            for _ in range(15):
                v = products @ v
                v -= v.mean()
                v /= np.linalg.norm(v) + 1e-12
            centres[c] = (v if v @ aligned[0] >= 0 else -v) * np.sqrt(length)
        found = [shape_distances(rows, c, norms) for c in centres]
        d, shifts = (np.stack([f[i] for f in found], 1) for i in (0, 1))
        new = d.argmin(1)
        if (new == owner).all():
            break
        owner = new
    return centres, owner


def batch_fit(part: np.ndarray, ell: int, mult: int = 2, k: int = 4, sample: int | None = None) -> list[tuple[np.ndarray, float]]:
    """(centre, share) of the shapes of one batch; none if it is too short."""
    length = ell * mult
    if len(part) < length:
        return []
    windows = D.sliding(part, length)
    rows = windows[np.linspace(0, len(windows) - 1, min(sample or len(windows), len(windows))).astype(int)]
    fresh, owner = k_shape(rows, min(k, len(rows)))
    return [(centre, share) for c, centre in enumerate(fresh) if (share := float((owner == c).mean()))]


def batch_merge(centres: list[np.ndarray], weights: list[float], fresh: list[tuple[np.ndarray, float]], alpha: float = 0.5, decay: float = 0.8) -> tuple[list[np.ndarray], list[float]]:
    """The model after a batch with shapes of its own: known ones move, others are added."""
    centres, weights = list(centres), [w * decay for w in weights] if fresh else list(weights)
    for centre, share in fresh:
        d = [shape_distances(centre[None], old)[0][0] for old in centres]
        if d and min(d) < 0.2:
            i = int(np.argmin(d))
            _, shift = shape_distances(centre[None], centres[i])
            centres[i] = (1 - alpha) * centres[i] + alpha * np.roll(centre, -int(shift[0]))
            weights[i] += share
        else:
            centres.append(centre)
            weights.append(share)
    return centres, weights


def batch_score(part: np.ndarray, ell: int, centres: list[np.ndarray], weights: list[float], batch: int) -> np.ndarray:
    """Scores of the windows of a batch, of which `batch` at most are its own."""
    m = len(part) - ell + 1
    if not len(centres) or m <= 0:
        return np.zeros(min(max(m, 0), batch))
    w, s = np.array(weights) / sum(weights), np.zeros(m)
    ready = D.prepare(D.sliding(np.asarray(part, float), ell), "zn")
    squares = np.einsum("ij,ij->i", ready, ready)
    for c, share in zip(centres, w):
        s += share * D.least_euclid(ready, D.prepare(D.sliding(np.asarray(c, float), ell), "zn"), squares=squares)
    s = centred_mean(s, ell)[:batch]
    spread = s.std()
    return (s - s.mean()) / spread if spread > 0 else np.zeros(len(s))


def batch_shape(x: np.ndarray, ell: int, mult: int = 2, batch: int = 5000, k: int = 4, alpha: float = 0.5, decay: float = 0.8, sample: int | None = None, mode: str = "online") -> np.ndarray:
    """Scores of all windows with a shape model that every batch refreshes."""
    n = len(x) - ell + 1
    out = np.zeros(max(n, 0))
    if mode == "offline":
        batch = len(x)
    centres: list[np.ndarray] = []
    weights: list[float] = []
    for at in range(0, max(n, 0), batch):
        part = x[at : min(at + batch + ell - 1, len(x))]
        centres, weights = batch_merge(centres, weights, batch_fit(part, ell, mult, k, sample), alpha, decay)
        s = batch_score(part, ell, centres, weights, batch)
        out[at : at + len(s)] = s
    return out


# -- discords ----------------------------------------------------------------------------------------


class _Normed:
    """The z-normalised windows of a series by their deviations; squared distances come from products with the points, so no
    window is held."""

    def __init__(self, x: np.ndarray, ell: int, rows: int = 1 << 14):
        self.x, self.ell, self.rows = np.asarray(x, float) - np.mean(x), ell, rows
        windows = D.sliding(self.x, ell)
        deviation = np.concatenate([windows[at : at + rows].std(-1) for at in range(0, len(windows), rows)])
        flat = deviation < D.FLAT
        self.inverse, self.square = np.where(flat, 0.0, 1.0 / np.where(flat, 1.0, deviation)), np.where(flat, 0.0, float(ell))

    def window(self, j: int) -> np.ndarray:
        w = self.x[j : j + self.ell]
        return (w - w.mean()) * self.inverse[j]

    def squares(self, j: int, w: np.ndarray, lo: int, hi: int) -> np.ndarray:
        """Squared distances of window j, which is w, to the windows from lo to hi, without hi."""
        cross = np.correlate(self.x[lo : hi + self.ell - 1], w, "valid") * self.inverse[lo:hi]
        return np.maximum(self.square[lo:hi] + self.square[j] - 2 * cross, 0.0)

    def least(self, j: int, w: np.ndarray, lo: int, hi: int) -> float:
        return float(np.sqrt(min(self.squares(j, w, at, min(hi, at + self.rows)).min() for at in range(lo, hi, self.rows))))


def backward_discord(x: np.ndarray, ell: int, lookback: int | None = None, prune: bool = True, warmup: int = 4) -> np.ndarray:
    """Distance to the nearest window that ends before the window begins; the first `warmup` windows' lengths score 0.

    The search goes back in chunks of doubling length and ends early once the window can't be the discord; windows ahead
    that lie close to the current one are passed over (their score is an upper bound too)."""
    n = len(x) - ell + 1
    out = np.zeros(max(n, 0))
    if n <= 0:
        return out
    normed = _Normed(x, ell)
    best, bound = 0.0, np.full(n, np.inf)
    for j in range(warmup * ell, n):
        if prune and bound[j] < best:
            out[j] = bound[j]
            continue
        w = normed.window(j)
        hi, size, d = j - ell + 1, 2 * ell, bound[j]
        least = 0 if lookback is None else max(0, j - lookback)
        while hi > least:
            lo = max(least, hi - size)
            d = min(d, normed.least(j, w, lo, hi))
            if prune and d < best:
                break
            hi, size = lo, 2 * size
        out[j] = d if np.isfinite(d) else 0.0
        best = max(best, out[j])
        if prune:
            lo, hi = j + ell, min(n, j + 4 * ell)
            if lo < hi:
                bound[lo:hi] = np.minimum(bound[lo:hi], np.sqrt(normed.squares(j, w, lo, hi)))
    return out


def matrix_profile(x: np.ndarray, ell: int, side: str = "both", rows: int = 2048, kind: str = "zn") -> np.ndarray:
    """Distance of every window to its nearest one that doesn't overlap it: before it ('left') or anywhere."""
    n = len(x) - ell + 1
    if n <= 0:
        return np.zeros(0)
    ready, at = D.prepare(D.sliding(x, ell), kind), np.arange(n)
    out = np.full(n, np.inf)
    for a in range(0, n, rows):
        d = D._euclid(ready[a : a + rows], ready)
        gap = at[a : a + rows, None] - at[None, :]
        d[(gap < ell) if side == "left" else (np.abs(gap) < ell)] = np.inf
        out[a : a + rows] = d.min(1)
    return out


# -- transformer reconstruction ----------------------------------------------------------------------


PART = 16  # windows whose arrays stay near the core


class Transformer:
    """One self-attention layer with a feed-forward layer and two decoders, trained by Adam with hand-written gradients.

    The first pass reconstructs a window; the second sees the first pass's squared error beside the values, and its
    decoder is trained against it with growing weight."""

    def __init__(self, ell: int, width: int = 16, seed: int = 0, dtype: type = np.float64):
        rng = np.random.default_rng(seed)
        g = lambda *s: rng.normal(size=s) / np.sqrt(s[0])
        self.p = {"E": g(2, width), "P": rng.normal(size=(ell, width)) * 0.3, "Q": g(width, width), "K": g(width, width), "V": g(width, width), "F": g(width, 2 * width), "G": g(2 * width, width), "o1": g(width, 1), "o2": g(width, 1), "b1": np.zeros(1), "b2": np.zeros(1)}
        self.p = {k: v.astype(dtype) for k, v in self.p.items()}
        self.m = {k: np.zeros_like(v) for k, v in self.p.items()}
        self.v = {k: np.zeros_like(v) for k, v in self.p.items()}
        self.t, self.width = 0, width

    def encode(self, x: np.ndarray, focus: np.ndarray) -> tuple[np.ndarray, tuple]:
        """All windows' rows go through a weight in one product, and arrays are worked on in place: small ones stay near the core."""
        p, (b, ell), d = self.p, x.shape, self.width
        z = np.stack([x, focus], -1).reshape(-1, 2)
        h = ((z @ p["E"]).reshape(b, ell, d) + p["P"]).reshape(-1, d)
        q, k, v = (h @ p[name] for name in "QKV")
        q, k, v = (m.reshape(b, ell, d) for m in (q, k, v))
        q_ = q / float(np.sqrt(d))
        a = q_ @ k.transpose(0, 2, 1)
        if np.einsum("ijk,ijk->ij", q_, q_).max() * np.einsum("ijk,ijk->ij", k, k).max() > 60.0**2:  # else no power overflows or vanishes
            a -= a.max(-1, keepdims=True)
        np.exp(a, out=a)
        a /= a.sum(-1, keepdims=True)
        r = h + (a @ v).reshape(-1, d)
        f = r @ p["F"]
        np.maximum(f, 0, out=f)
        return (r + f @ p["G"]).reshape(b, ell, d), (z, h, q, k, v, a, r, f)

    def back(self, dy: np.ndarray, cache: tuple, grad: dict[str, np.ndarray]) -> None:
        p, (z, h, q, k, v, a, r, f), d = self.p, cache, self.width
        (b, ell), root = a.shape[:2], float(np.sqrt(d))
        dy = dy.reshape(-1, d)
        grad["G"] += f.T @ dy
        df = dy @ p["G"].T
        df *= f > 0
        grad["F"] += r.T @ df
        dr = dy + df @ p["F"].T
        cube = dr.reshape(b, ell, d)
        dv = a.transpose(0, 2, 1) @ cube
        ds = cube @ v.transpose(0, 2, 1)
        ds -= np.einsum("ijk,ijk->ij", ds, a)[..., None]
        ds *= a
        dq, dk = ds @ (k / root), ds.transpose(0, 2, 1) @ (q / root)
        dh = dr.copy()
        for name, m in (("Q", dq), ("K", dk), ("V", dv)):
            m = m.reshape(-1, d)
            grad[name] += h.T @ m
            dh += m @ p[name].T
        grad["P"] += dh.reshape(b, ell, d).sum(0)
        grad["E"] += z.T @ dh

    def passes(self, x: np.ndarray) -> tuple[np.ndarray, np.ndarray, tuple, tuple, np.ndarray, np.ndarray]:
        y1, c1 = self.encode(x, np.zeros_like(x))
        o1 = (y1.reshape(-1, self.width) @ self.p["o1"]).reshape(x.shape) + self.p["b1"]
        focus = (o1 - x) ** 2
        y2, c2 = self.encode(x, focus)
        o2 = (y2.reshape(-1, self.width) @ self.p["o2"]).reshape(x.shape) + self.p["b2"]
        return o1, o2, c1, c2, y1, y2

    def step(self, x: np.ndarray, mix: float, rate: float = 3e-3) -> None:
        grad = {k: np.zeros_like(v) for k, v in self.p.items()}
        n = x.size
        for part in (x[at : at + PART] for at in range(0, len(x), PART)):
            o1, o2, c1, c2, y1, y2 = self.passes(part)
            for o, y, c, name, bias, w in ((o1, y1, c1, "o1", "b1", 1.0), (o2, y2, c2, "o2", "b2", mix)):
                do = (2 * w * (o - part) / n)[..., None]
                grad[name] += y.reshape(-1, self.width).T @ do.reshape(-1, 1)
                grad[bias] += do.sum()
                self.back(do @ self.p[name].T, c, grad)
        self.t += 1
        for k in self.p:
            self.m[k] = 0.9 * self.m[k] + 0.1 * grad[k]
            self.v[k] = 0.999 * self.v[k] + 0.001 * grad[k] ** 2
            self.p[k] = self.p[k] - rate * (self.m[k] / (1 - 0.9**self.t)) / (np.sqrt(self.v[k] / (1 - 0.999**self.t)) + 1e-8)

    def error(self, x: np.ndarray) -> np.ndarray:
        o1, o2, *_ = self.passes(x)
        return ((o1 - x) ** 2).mean(1) / 2 + ((o2 - x) ** 2).mean(1) / 2


def transformer_fit(x: np.ndarray, ell: int, epochs: int = 3, seed: int = 0, most: int | None = None, dtype: type = np.float32) -> tuple[Transformer, float, float]:
    """Trained in single precision, as such models mostly are: less than half the time of double."""
    lo, hi = float(x.min()), float(x.max())
    ready = ((x - lo) / (hi - lo if hi > lo else 1.0)).astype(dtype)
    windows = D.sliding(ready, ell)
    rng = np.random.default_rng(seed)
    chosen = np.sort(rng.permutation(len(windows))[:most])
    rows = windows if most is None else windows[chosen]  # a view of the points where all are taken
    net = Transformer(ell, seed=seed, dtype=dtype)
    for epoch in range(epochs):
        order = rng.permutation(len(rows))
        for at in range(0, len(rows), 64):
            net.step(rows[order[at : at + 64]], mix=1.0 - 0.5 ** (epoch + 1))
    return net, lo, hi


def transformer_first(n: int, ell: int, train: float = 0.2) -> int:
    """Points that a series of n points is trained on."""
    return max(ell + 1, int(n * train))


def transformer_errors(x: np.ndarray, ell: int, net: Transformer, lo: float, hi: float, rows: np.ndarray | None = None) -> np.ndarray:
    """Reconstruction errors of the windows of x, or of some of them."""
    windows = D.sliding(((x - lo) / (hi - lo if hi > lo else 1.0)).astype(net.p["E"].dtype), ell)
    rows = np.arange(len(windows)) if rows is None else rows
    return np.concatenate([net.error(windows[rows[at : at + PART]]) for at in range(0, len(rows), PART)]).astype(float)


def transformer_score(x: np.ndarray, ell: int, train: float = 0.2, epochs: int = 3, seed: int = 0, stride: int = 1) -> np.ndarray:
    """Reconstruction errors; with a stride, windows in between take the line between their neighbours' errors."""
    n, first = len(x) - ell + 1, transformer_first(len(x), ell, train)
    if n <= 0 or len(x) < first:
        return np.zeros(max(n, 0))
    net, lo, hi = transformer_fit(x[:first], ell, epochs, seed)
    rows = np.unique(np.r_[np.arange(0, n, stride), n - 1])
    return np.interp(np.arange(n), rows, transformer_errors(x, ell, net, lo, hi, rows))


# -- adaptive window ---------------------------------------------------------------------------------


class AdaptiveWindow:
    """Counts, sums and squares of values in [0, 1] in buckets of doubling size; drops its older part when the means on both
    sides of a cut differ by more than chance allows."""

    def __init__(self, delta: float = 0.002, least: int = 5, per_size: int = 5):
        self.delta, self.least, self.per_size = delta, least, per_size
        self.rows: list[list[tuple[float, float]]] = [[]]  # per size 2^i: (sum, sum of squares), oldest first

    def push(self, v: float) -> None:
        rows, i = self.rows, 0
        rows[0].append((v, v * v))
        while len(rows[i]) > self.per_size:
            if i + 1 == len(rows):
                rows.append([])
            a, b = rows[i].pop(0), rows[i].pop(0)
            rows[i + 1].append((a[0] + b[0], a[1] + b[1]))
            i += 1

    def cut(self) -> bool:
        """Drop what lies before the clearest cut, so that a drift counts once; False if there is none."""
        buckets = [(1 << i, s, q) for i in range(len(self.rows) - 1, -1, -1) for s, q in self.rows[i]]
        n = sum(b[0] for b in buckets)
        if n < 2 * self.least:
            return False
        total, square = sum(b[1] for b in buckets), sum(b[2] for b in buckets)
        variance, confidence = max(square / n - (total / n) ** 2, 0.0), np.log(2 * np.log(max(n, 3)) / self.delta)
        n0, s0, older, clearest = 0, 0.0, 0, 1.0
        for k, (size, s, _) in enumerate(buckets[:-1], 1):
            n0, s0 = n0 + size, s0 + s
            if n0 < self.least or n - n0 < self.least:
                continue
            inverse = 1 / n0 + 1 / (n - n0)
            bound = np.sqrt(2 * inverse * variance * confidence) + 2 / 3 * inverse * confidence
            ratio = abs(s0 / n0 - (total - s0) / (n - n0)) / bound
            if ratio > clearest:
                older, clearest = k, ratio
        for size in reversed(self.rows if older else []):
            while older and size:
                size.pop(0)
                older -= 1
        return clearest > 1.0


def drift_positions(x: np.ndarray, ell: int, delta: float = 0.002) -> list[int]:
    """Positions at which an adaptive window over the level, spread or roughness of points finds a drift.

    A drift changes the shape of a period, seldom its mean, so the mean of points shows nothing.  Both parts of a cut have
    ten periods or more, so that neither a part of a period nor one anomaly makes a cut; a twentieth of the values is
    clipped at either end for the same reason.  When one window finds a drift all begin anew."""
    if len(x) < 20 * ell:
        return []
    every, out = max(1, ell // 2), []
    scaled = []
    for values in (x, np.abs(x - np.median(x)), np.abs(np.diff(x, prepend=x[0]))):
        low, high = np.quantile(values, [0.05, 0.95])
        scaled.append((np.clip(values, low, high) - low) / ((high - low) or 1.0))
    fresh = lambda: [AdaptiveWindow(delta, 10 * ell) for _ in scaled]
    windows = fresh()
    for pos, values in enumerate(zip(*scaled)):
        for w, v in zip(windows, values):
            w.push(float(v))
        if pos % every == 0 and any(w.cut() for w in windows):
            out.append(pos)
            windows = fresh()
    return out
