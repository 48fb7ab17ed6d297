"""Distances between windows, as NumPy kernels and as Column expressions.

zm: Euclidean distance of centred windows.  zn: the same after division by the population deviation (a flat window is
the zero vector).  sbd: one minus the largest normalised cross-correlation.  dtw: dynamic time warping of centred windows.
"""

from __future__ import annotations

from collections.abc import Callable

import numpy as np
from pyspark.sql import Column
from pyspark.sql import functions as F

FLAT = 1e-9


def prepare(windows: np.ndarray, kind: str) -> np.ndarray:
    """Windows (n, length) brought to the space in which `kind` is Euclidean."""
    centred = windows - windows.mean(-1, keepdims=True)
    if kind == "zm":
        return centred
    deviation = windows.std(-1, keepdims=True)
    return np.where(deviation < FLAT, 0.0, centred / np.where(deviation < FLAT, 1.0, deviation))


def sliding(x: np.ndarray, length: int) -> np.ndarray:
    return np.lib.stride_tricks.sliding_window_view(x, length)


def _euclid(a: np.ndarray, b: np.ndarray) -> np.ndarray:
    """Distances (len(a), len(b)); exact zero products are kept from going negative."""
    square = (a * a).sum(1)[:, None] + (b * b).sum(1)[None, :] - 2.0 * (a @ b.T)
    return np.sqrt(np.maximum(square, 0.0))


def zm(a: np.ndarray, b: np.ndarray) -> float:
    return float(np.linalg.norm(prepare(np.asarray(a, float), "zm") - prepare(np.asarray(b, float), "zm")))


def zn(a: np.ndarray, b: np.ndarray) -> float:
    return float(np.linalg.norm(prepare(np.asarray(a, float), "zn") - prepare(np.asarray(b, float), "zn")))


def sbd(a: np.ndarray, b: np.ndarray) -> float:
    a, b = prepare(np.asarray(a, float), "zm"), prepare(np.asarray(b, float), "zm")
    size = np.linalg.norm(a) * np.linalg.norm(b)
    if size < FLAT:
        return 0.0 if np.linalg.norm(a) + np.linalg.norm(b) < FLAT else 1.0
    n = 1 << (2 * len(a) - 1).bit_length()
    cross = np.fft.irfft(np.fft.rfft(a, n) * np.conj(np.fft.rfft(b, n)), n)
    return float(1.0 - max(cross[: len(a)].max(), cross[-(len(b) - 1) :].max() if len(b) > 1 else -np.inf) / size)


def dtw(a: np.ndarray, b: np.ndarray, band: int | None = None) -> float:
    a, b = prepare(np.asarray(a, float), "zm"), prepare(np.asarray(b, float), "zm")
    n, m = len(a), len(b)
    width = max(band if band is not None else max(n, m), abs(n - m))
    row = np.full(m + 1, np.inf)
    row[0] = 0.0
    for i in range(1, n + 1):
        new = np.full(m + 1, np.inf)
        for j in range(max(1, i - width), min(m, i + width) + 1):
            new[j] = (a[i - 1] - b[j - 1]) ** 2 + min(row[j], row[j - 1], new[j - 1])
        row = new
    return float(np.sqrt(row[m]))


def dtw_rows(a: np.ndarray, b: np.ndarray, rows: int = 1024) -> np.ndarray:
    """Warping distances of the rows of a to those of b, without a band."""
    return np.sqrt(_dtw_squares(prepare(a, "zm"), prepare(b, "zm"), rows))


def _dtw_squares(a: np.ndarray, b: np.ndarray, rows: int) -> np.ndarray:
    """Squared warping distances of rows that are ready, in their own precision; a diagonal of the table at a time for many
    pairs, which lie side by side in memory."""
    out = np.empty(len(a), a.dtype)
    n, m = a.shape[1], b.shape[1]
    for at in range(0, len(a), rows):
        x, y = np.ascontiguousarray(a[at : at + rows].T), np.ascontiguousarray(b[at : at + rows, ::-1].T)
        before, last, now = (np.full((n + 1, x.shape[1]), np.inf, a.dtype) for _ in range(3))  # by row of the table
        room = np.empty_like(x)
        before[0] = 0.0
        for s in range(2, n + m + 1):
            lo, hi = max(1, s - m), min(n, s - 1)
            gap, least = room[: hi - lo + 1], now[lo : hi + 1]
            np.subtract(x[lo - 1 : hi], y[m - s + lo : m - s + hi + 1], out=gap)
            np.multiply(gap, gap, out=gap)
            np.minimum(last[lo - 1 : hi], last[lo : hi + 1], out=least)
            np.minimum(least, before[lo - 1 : hi], out=least)
            np.add(least, gap, out=least)
            now[lo - 1], now[hi + 1 : hi + 2] = np.inf, np.inf
            before, last, now = last, now, before
        out[at : at + rows] = last[n]
    return out


def sbd_table(a: np.ndarray, b: np.ndarray, rows: int = 256) -> np.ndarray:
    """Shape-based distances (len(a), len(b)); the transforms of both sides are made once."""
    a, b = prepare(a, "zm"), prepare(b, "zm")
    m = a.shape[1]
    n = 1 << (2 * m - 1).bit_length()
    norm_a, norm_b = np.linalg.norm(a, axis=1), np.linalg.norm(b, axis=1)
    right, out = np.conj(np.fft.rfft(b, n)), np.empty((len(a), len(b)))
    for at in range(0, len(a), rows):
        cross = np.fft.irfft(np.fft.rfft(a[at : at + rows], n)[:, None, :] * right[None], n)
        best = cross[..., :m].max(-1)
        if m > 1:
            best = np.maximum(best, cross[..., -(m - 1) :].max(-1))
        size, total = norm_a[at : at + rows, None] * norm_b[None], norm_a[at : at + rows, None] + norm_b[None]
        out[at : at + rows] = np.where(size < FLAT, np.where(total < FLAT, 0.0, 1.0), 1.0 - best / np.where(size < FLAT, 1.0, size))
    return out


def dtw_table(a: np.ndarray, b: np.ndarray, pairs: int = 1 << 14) -> np.ndarray:
    """Warping distances (len(a), len(b))."""
    out, step = np.empty((len(a), len(b))), max(1, pairs // max(1, len(b)))
    for at in range(0, len(a), step):
        x = a[at : at + step]
        out[at : at + step] = dtw_rows(np.repeat(x, len(b), 0), np.tile(b, (len(x), 1))).reshape(len(x), len(b))
    return out


def _corner(x: np.ndarray, y: np.ndarray) -> np.ndarray:
    """Squared cost, at least, of a warping path's part near its first cell, of pairs in columns: every path meets one of two
    neighbouring diagonals of the table."""
    k = len(x)
    before, last = (np.full((k + 1, x.shape[1]), np.inf) for _ in range(2))  # by row of the table, after one of none
    last[1] = (x[0] - y[0]) ** 2
    for s in range(1, k):
        now = np.full_like(last, np.inf)
        now[1 : s + 2] = np.minimum(np.minimum(last[: s + 1], last[1 : s + 2]), before[: s + 1]) + (x[: s + 1] - y[s::-1]) ** 2
        before, last = last, now
    return np.minimum(before.min(0), last.min(0))


def sbd_least(windows: np.ndarray, pieces: np.ndarray) -> np.ndarray:
    """Shape-based distance of every window to its nearest piece.

    Shifts are tried from none on; a correlation is at most the product of the norms of what overlaps, which falls as the
    shift grows, so a window is done once that is no more than the best it has found."""
    a, b = prepare(np.asarray(windows, float), "zm"), prepare(np.asarray(pieces, float), "zm")
    norm_a, norm_b = np.linalg.norm(a, axis=1), np.linalg.norm(b, axis=1)
    out, fine = np.empty(len(a)), norm_a * norm_b.min() >= FLAT
    if not fine.all():
        out[~fine] = sbd_table(a[~fine], b).min(1)
    if not fine.any():
        return out
    a, b = a[fine] / norm_a[fine, None], b / norm_b[:, None]
    best, m = (a @ b.T).max(1), a.shape[1]
    for x, y in ((a, b), (a[:, ::-1], b[:, ::-1])):  # backwards, a shift to the left is one to the right
        most = np.sqrt(np.cumsum(y * y, 1)).max(0)  # of the pieces' first points
        left, rest = np.arange(len(x)), np.ascontiguousarray(x)
        square = np.cumsum(rest[:, ::-1] ** 2, 1)[:, ::-1]  # of the window's points from each on
        for s in range(1, m):
            open_ = np.sqrt(square[:, s]) * most[m - s - 1] > best[left] - 1e-12
            if not open_.all():
                left, rest, square = left[open_], rest[open_], square[open_]
            if not len(left):
                break
            best[left] = np.maximum(best[left], (rest[:, s:] @ y[:, : m - s].T).max(1))
    out[fine] = 1.0 - best
    return out


def dtw_least(windows: np.ndarray, pieces: np.ndarray, depth: int = 8, pairs: int = 1 << 14) -> np.ndarray:
    """Warping distance of every window to its nearest piece.

    The piece that is nearest without warping is tried first, then the one whose ends promise most; another is tried unless both
    ends of any path, with the points that lie outside of all pieces' range, cost more than the best already.  Trials are in
    single precision; the pieces that may be nearest within its error are worked out in double."""
    a, b = prepare(np.asarray(windows, float), "zm"), prepare(np.asarray(pieces, float), "zm")
    m = a.shape[1]
    k = min(depth, m // 2)
    if k < 1 or not len(a):
        return dtw_table(a, b).min(1, initial=np.inf)
    most = max(np.abs(a).max(), np.abs(b).max())
    if not np.isfinite(most):
        return dtw_table(a, b).min(1)
    unit = most or 1.0
    a1, b1 = (a / unit).astype(np.float32), (b / unit).astype(np.float32)

    def above(square: np.ndarray) -> np.ndarray:
        """No less than the true square of one in single precision, and the other way round."""
        return square * (1 + 2e-5) + 1e-5 * np.sqrt(square) + 1e-10

    def tried(w: np.ndarray, p: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        found = np.concatenate([_dtw_squares(a1[w[at : at + pairs]], b1[p[at : at + pairs]], 2048) for at in range(0, max(1, len(w)), pairs)]).astype(float)
        np.minimum.at(limit, w, above(found))
        return w, p, found

    every, nearest = np.arange(len(a)), _euclid(a, b).argmin(1)
    limit = np.full(len(a), np.inf)  # in units; above the square of the least distance
    seen = [tried(every, nearest)]
    outside = np.maximum(np.maximum(a1 - b1.max(), b1.min() - a1), 0.0).astype(float) ** 2
    inner, middle = outside[:, 1:-1].sum(1), outside[:, k : m - k].sum(1)
    ends = (a1[:, :1] - b1[:, 0]) ** 2 + (a1[:, -1:] - b1[:, -1]) ** 2
    i, o = np.nonzero(ends + inner[:, None] < above(limit)[:, None])
    i, o = (v[o != nearest[i]] for v in (i, o))
    head, tail = (np.ascontiguousarray(v.T) for v in (a1[:, :k], a1[:, : m - k - 1 : -1]))
    first, final = (np.ascontiguousarray(v.T) for v in (b1[:, :k], b1[:, : m - k - 1 : -1]))
    parts = []
    for at in range(0, len(i), pairs):
        w, p = i[at : at + pairs], o[at : at + pairs]
        bound = _corner(head[:, w], first[:, p]) + _corner(tail[:, w], final[:, p]) + middle[w]
        near = bound < above(limit[w])
        parts.append((w[near], p[near], bound[near]))
    if parts:
        w, p, bound = (np.concatenate(c) for c in zip(*parts))
        order = np.lexsort((bound, w))
        w, p, bound = w[order], p[order], bound[order]
        lead = np.diff(w, prepend=-1) != 0
        seen.append(tried(w[lead], p[lead]))
        left = ~lead & (bound < above(limit[w]))
        seen.append(tried(w[left], p[left]))
    w, p, found = (np.concatenate(c) for c in zip(*seen))
    best = np.full(len(a), np.inf)
    np.minimum.at(best, w, found)
    w, p = (v[found <= above(above(best[w]))] for v in (w, p))
    out = np.full(len(a), np.inf)
    for at in range(0, len(w), pairs):
        np.minimum.at(out, w[at : at + pairs], dtw_rows(a[w[at : at + pairs]], b[p[at : at + pairs]]))
    return out


def to_shape(rows: np.ndarray, shape: np.ndarray, kind: str) -> np.ndarray:
    """Distances of rows to a shape of their length."""
    if kind == "dtw":
        return dtw_rows(rows, np.broadcast_to(shape, rows.shape))
    if kind == "sbd":
        return sbd_table(rows, shape[None])[:, 0]
    return np.array([named(kind)(r, shape) for r in rows])


_NAMED: dict[str, Callable[[np.ndarray, np.ndarray], float]] = {"zm": zm, "zn": zn, "sbd": sbd, "dtw": dtw}


def register(name: str, fn: Callable[[np.ndarray, np.ndarray], float]) -> None:
    """Make a distance of two equal-length windows known under a name."""
    _NAMED[name] = fn


def named(kind: str) -> Callable[[np.ndarray, np.ndarray], float]:
    return _NAMED[kind]


def placements(windows: np.ndarray, pattern: np.ndarray, kind: str = "zm") -> np.ndarray:
    """Distances (windows, offsets) of windows to every piece of their length of a pattern."""
    pieces = sliding(np.asarray(pattern, float), windows.shape[1])
    if kind in ("zm", "zn"):
        return _euclid(prepare(windows, kind), prepare(pieces, kind))
    if kind in ("sbd", "dtw"):
        return (sbd_table if kind == "sbd" else dtw_table)(np.asarray(windows, float), pieces)
    fn = named(kind)
    return np.array([[fn(w, p) for p in pieces] for w in windows])


def least_euclid(ready: np.ndarray, pieces: np.ndarray, rows: int = 2048, squares: np.ndarray | None = None) -> np.ndarray:
    """Distance of every row to its nearest piece; the root is taken of the least square only.  squares: those of the rows."""
    out = np.einsum("ij,ij->i", ready, ready) if squares is None else squares.copy()
    turned, square = -2.0 * pieces, (pieces * pieces).sum(1)[:, None]
    for at in range(0, len(ready), rows):
        table = turned @ ready[at : at + rows].T
        table += square
        out[at : at + rows] += table.min(0)
    return np.sqrt(np.maximum(out, 0.0))


def min_place(pattern: np.ndarray, window: np.ndarray, kind: str = "zm") -> tuple[float, int]:
    """Smallest distance of a window to a piece of the pattern, and the piece's offset."""
    d = placements(np.asarray(window, float)[None, :], pattern, kind)[0]
    return float(d.min()), int(d.argmin())


def profile(x: np.ndarray, pattern: np.ndarray, ell: int, kind: str = "zm", rows: int = 8192) -> np.ndarray:
    """Distance of every window of length ell of x to its best place in a pattern."""
    if len(x) < ell:
        return np.zeros(0)
    windows = sliding(np.asarray(x, float), ell)
    if kind in ("zm", "zn"):
        pieces = prepare(sliding(np.asarray(pattern, float), ell), kind)
        return np.concatenate([least_euclid(prepare(windows[at : at + rows], kind), pieces) for at in range(0, len(windows), rows)])
    if kind in ("sbd", "dtw"):
        pieces, least = sliding(np.asarray(pattern, float), ell), sbd_least if kind == "sbd" else dtw_least
        return np.concatenate([least(windows[at : at + rows], pieces) for at in range(0, len(windows), rows)])
    return np.concatenate([placements(windows[at : at + rows], pattern, kind).min(1) for at in range(0, len(windows), rows)])


def phi(d: np.ndarray, tau: float, eta: float) -> np.ndarray:
    """Fuzzy membership: 1 within tau, falling exponentially beyond."""
    return np.where(d <= tau, 1.0, np.exp(-eta * np.maximum(d - tau, 0.0)))


# -- Column expressions ------------------------------------------------------------------------------


def mean_of(a: Column) -> Column:
    return F.aggregate(a, F.lit(0.0), lambda s, v: s + v) / F.size(a)


def centred(a: Column) -> Column:
    m = mean_of(a)
    return F.transform(a, lambda v: v - m)


def scaled(a: Column) -> Column:
    """Centred and divided by the population deviation; zeros for a flat window."""
    c = centred(a)
    sd = F.sqrt(F.aggregate(c, F.lit(0.0), lambda s, v: s + v * v) / F.size(a))
    return F.transform(c, lambda v: F.when(sd < FLAT, 0.0).otherwise(v / sd))


def euclid(a: Column, b: Column) -> Column:
    return F.sqrt(F.aggregate(F.zip_with(a, b, lambda x, y: (x - y) * (x - y)), F.lit(0.0), lambda s, v: s + v))


def zm_col(a: Column, b: Column) -> Column:
    return euclid(centred(a), centred(b))


def zn_col(a: Column, b: Column) -> Column:
    return euclid(scaled(a), scaled(b))


def min_place_col(pattern: Column, window: Column, kind: str = "zm") -> Column:
    d = zm_col if kind == "zm" else zn_col
    offsets = F.sequence(F.lit(1), F.size(pattern) - F.size(window) + 1)
    return F.array_min(F.transform(offsets, lambda o: d(F.slice(pattern, o, F.size(window)), window)))


def phi_col(d: Column, tau: Column, eta: Column) -> Column:
    return F.when(d <= tau, F.lit(1.0)).otherwise(F.exp(-eta * (d - tau)))
