"""Contiguous agglomeration of time-ordered segments, with repair of premature joins and a cut per branch."""

from __future__ import annotations

import heapq
from bisect import bisect_left
from collections.abc import Callable, Sequence
from dataclasses import dataclass, field

import numpy as np
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from seqnorm.functions import distance as D
from seqnorm.functions.linkage import Stats, link
from seqnorm.session import materialise, ship


@dataclass(slots=True)
class Node:
    id: int
    left: int = -1
    right: int = -1
    height: float = 0.0
    lo: int = 0
    hi: int = 0
    held: Sequence[int] = ()  # members in order; a range where they are contiguous, which holds no memory
    parent: int = -1
    live: bool = True
    reverted: bool = False

    @property
    def members(self) -> tuple[int, ...]:
        return tuple(self.held)


@dataclass
class Forest:
    nodes: list[Node] = field(default_factory=list)
    n_leaves: int = 0
    splits: int = 0
    order: list[int] = field(default_factory=list)  # joins as they were made

    def roots(self) -> list[Node]:
        return [x for x in self.nodes if x.live and x.parent < 0]


def joined(a: Sequence[int], b: Sequence[int]) -> Sequence[int]:
    lo, hi = min(a[0], b[0]), max(a[-1], b[-1])
    return range(lo, hi + 1) if hi - lo + 1 == len(a) + len(b) else tuple(sorted((*a, *b)))


BLOCK = 1024  # clusters whose sums lie in one array


class Agglomeration:
    """The clustering of one series' segments.

    Live clusters stand in a list in order of their first segment; a cluster may be joined with one up to k places away.
    When the closest pair is closer than the last join, the newer composite of the pair blocked a better join: it is
    opened, unless its part nearer in time is also the more similar one, and the closer part is tried, as long as the
    linkage keeps falling below the height of a composite at hand."""

    def __init__(self, rows: np.ndarray, linkage: str = "ward", k: int = 1, repair: bool = True, max_splits: int | None = None, halt_near: bool = True, stop_height: float | None = None, stop_clusters: int = 1, linker: Callable[[tuple[int, ...], tuple[int, ...]], float] | None = None):
        self.rows, self.kind, self.k, self.repair, self.halt_near = rows, linkage, k, repair, halt_near
        self.stop_height, self.stop_clusters, self.linker = stop_height, stop_clusters, linker
        n = len(rows)
        self.max_splits = 4 * n if max_splits is None else max_splits
        self.forest = Forest([Node(i, lo=i, hi=i, held=range(i, i + 1)) for i in range(n)], n)
        self.named = linkage not in ("ward", "centroid")  # a linkage over pairs of members
        self.totals: list[np.ndarray] = []  # sums of the joined clusters, in blocks
        self.live = list(range(n))
        self.heap: list[tuple[float, int, int, int, int]] = []
        self.last = 0.0
        self.undone: set[tuple[int, int]] = set()
        self.queued: set[tuple[int, int]] = set()  # pairs in the heap, which needs each once
        for at in range(n):
            self._push(at)

    def distance(self, a: int, b: int) -> float:
        if self.linker is not None:
            return self.linker(self.forest.nodes[a].members, self.forest.nodes[b].members)
        return link(self.kind, self._stats(a), self._stats(b), self.rows)

    def _total(self, node: int) -> np.ndarray:
        at = node - self.forest.n_leaves
        return self.rows[node] if at < 0 else self.totals[at // BLOCK][at % BLOCK]

    def _stats(self, node: int) -> Stats:
        held = self.forest.nodes[node].held
        return Stats(len(held), self._total(node), held if self.named else ())

    def _push(self, at: int) -> None:
        """Links of the cluster at a place of the list to those up to k places to its right."""
        a = self.live[at]
        for b in self.live[at + 1 : at + 1 + self.k]:
            if (a, b) in self.queued:
                continue
            self.queued.add((a, b))
            lo, hi = self.forest.nodes[a].lo, self.forest.nodes[b].lo
            heapq.heappush(self.heap, (self.distance(a, b), lo, hi, a, b))

    def _around(self, at: int) -> None:
        for i in range(max(0, at - self.k), min(len(self.live), at + 1)):
            self._push(i)

    def _place(self, node: int) -> int:
        return bisect_left(self.live, self.forest.nodes[node].lo, key=lambda x: self.forest.nodes[x].lo)  # live is in order of lo

    def _near(self, a: int, b: int) -> bool:
        nodes = self.forest.nodes
        return nodes[a].live and nodes[b].live and nodes[a].parent < 0 and nodes[b].parent < 0 and 0 < abs(self._place(a) - self._place(b)) <= self.k

    def _join(self, a: int, b: int, height: float) -> int:
        nodes = self.forest.nodes
        new = Node(len(nodes), a, b, height, min(nodes[a].lo, nodes[b].lo), max(nodes[a].hi, nodes[b].hi), joined(nodes[a].held, nodes[b].held))
        nodes.append(new)
        self.forest.order.append(new.id)
        nodes[a].parent = nodes[b].parent = new.id
        if self.linker is None:
            if (new.id - self.forest.n_leaves) // BLOCK == len(self.totals):
                self.totals.append(np.empty((BLOCK, *np.shape(self.rows)[1:])))
            self._total(new.id)[...] = self._total(a) + self._total(b)
        place, other = sorted((self._place(a), self._place(b)))
        del self.live[other]
        self.live[place] = new.id
        self._around(place)
        return new.id

    def _open(self, node: int) -> tuple[int, int]:
        """Undo a join; its parts go back to their places in time."""
        nodes = self.forest.nodes
        x = nodes[node]
        x.live, x.reverted = False, True
        self.forest.splits += 1
        self.undone.add((x.left, x.right))
        del self.live[self._place(node)]
        for part in (x.left, x.right):
            nodes[part].parent = -1
            self.live.insert(self._place(part), part)
        for part in (x.left, x.right):
            self._around(self._place(part))
        return x.left, x.right

    def _gap(self, a: int, b: int) -> int:
        x, y = self.forest.nodes[a], self.forest.nodes[b]
        return max(y.lo - x.hi, x.lo - y.hi, 0)

    def _repair(self, a: int, b: int, d: float) -> None:
        nodes = self.forest.nodes
        for _ in range(self.max_splits + 1):
            blocking = [x for x in (a, b) if nodes[x].left >= 0 and nodes[x].height > d]
            if not blocking or self.forest.splits >= self.max_splits:
                break
            p = max(blocking)
            q = b if p == a else a
            left, right = nodes[p].left, nodes[p].right
            near, far = (left, right) if self._gap(left, q) <= self._gap(right, q) else (right, left)
            to_near, to_far = self.distance(q, near), self.distance(q, far)
            if self.halt_near and to_near < to_far:
                break
            part, closer = (near, to_near) if to_near <= to_far else (far, to_far)
            self._open(p)
            a, b, d = (part, q, closer) if nodes[part].lo < nodes[q].lo else (q, part, closer)
        self.last = d
        self._join(a, b, d)

    def run(self) -> Forest:
        nodes = self.forest.nodes
        while len(self.live) > self.stop_clusters and self.heap:
            d, _, _, a, b = heapq.heappop(self.heap)
            self.queued.discard((a, b))
            if not self._near(a, b):
                continue
            if self.stop_height is not None and d > self.stop_height:
                break
            blocked = any(nodes[x].left >= 0 and nodes[x].height > d for x in (a, b))
            if d >= self.last or not self.repair or not blocked or self.forest.splits >= self.max_splits:
                self.last = d
                self._join(a, b, d)
            else:
                self._repair(a, b, d)
        return self.forest


def jump_limit(heights: list[float], rule: str, at: int) -> float:
    """The height difference beyond which a branch is cut at its step `at`; heights are those on the seed's way up.

    mean_jump: the mean of all the way's differences; mean_plus_std: that and their deviation; running_mean: the mean of
    the differences so far, this one included; printed: the sum of the heights so far less that mean, over their number."""
    jumps = np.diff(heights)
    if rule == "mean_jump":
        return float(jumps.mean())
    seen = jumps[: at + 1]
    if rule == "running_mean":
        return float(seen.mean())
    if rule == "mean_plus_std":
        return float(jumps.mean() + jumps.std())
    if rule == "printed":
        return float(np.sum(heights[: at + 2]) - seen.mean()) / (at + 2)
    raise ValueError(f"unknown cut rule {rule}")


def branch_cut(forest: Forest, rule: str = "mean_jump", height: float | None = None, count: int | None = None) -> list[list[int]]:
    """Clusters of segments.  rule 'height' cuts all branches at a height, 'count' leaves that many clusters."""
    nodes = forest.nodes
    if rule == "height" or rule == "count":
        # a join counts as high as the highest below it, so that what is cut stays a tree where heights fall
        high = [0.0] * len(nodes)
        for x in nodes:
            if x.left >= 0:
                high[x.id] = max(x.height, high[x.left], high[x.right])
        joins = sorted((x for x in nodes if x.live and x.left >= 0), key=lambda x: (high[x.id], x.id))
        if rule == "count":
            keep = {x.id for x in joins[: max(0, forest.n_leaves - (count or 1))]}
        else:
            keep = {x.id for x in joins if high[x.id] <= (height or 0.0)}
        top = [x for x in nodes if x.live and (x.left < 0 or x.id in keep) and (x.parent < 0 or x.parent not in keep)]
        return sorted(sorted(x.members) for x in top)
    assigned = np.zeros(forest.n_leaves, bool)
    met = [False] * len(nodes)  # nodes that hold members of a cluster made already
    seeds = sorted(range(forest.n_leaves), key=lambda i: (nodes[nodes[i].parent].height if nodes[i].parent >= 0 else np.inf, i))
    out = []
    for seed in seeds:
        if assigned[seed]:
            continue
        way = []
        up = nodes[seed].parent
        while up >= 0:
            way.append(up)
            up = nodes[up].parent
        top = seed
        heights = [nodes[i].height for i in way]
        whole = jump_limit(heights, rule, 0) if rule == "mean_jump" and len(heights) > 1 else None  # the same at each step
        for step, node in enumerate(way):
            if met[node]:
                break
            if step and heights[step] - heights[step - 1] > (jump_limit(heights, rule, step - 1) if whole is None else whole):
                break
            top = node
        members = list(nodes[top].held) or leaves(forest, top)
        assigned[members] = True
        out.append(members)
        up = top
        while up >= 0 and not met[up]:
            met[up] = True
            up = nodes[up].parent
    return sorted(out)


def cluster(rows: np.ndarray, cut_rule: str = "mean_jump", **settings) -> tuple[Forest, list[list[int]]]:
    forest = Agglomeration(rows, **settings).run()
    return forest, branch_cut(forest, cut_rule)


def free_forest(rows: np.ndarray) -> Forest:
    """Ward joins of any two clusters by chains of nearest neighbours, which make the tree that joining the closest pair
    again and again makes, without a list of all pairs: memory goes with the rows, time with their square."""
    n, (mean, size) = len(rows), (np.array(rows, float), np.ones(len(rows)))
    square, gone, names = np.einsum("ij,ij->i", mean, mean), np.zeros(n, bool), np.arange(n)
    chain, joins = [], []
    while len(joins) < n - 1:
        if 2 * gone.sum() > len(names):  # rows joined away go when they are half
            place = np.cumsum(~gone) - 1
            chain = [int(place[c]) for c in chain]
            names, size, mean, square, gone = names[~gone], size[~gone], mean[~gone], square[~gone], gone[~gone]
        chain = chain or [int(np.flatnonzero(~gone)[0])]
        while True:
            a = chain[-1]
            d = np.maximum(square + square[a] - 2.0 * (mean @ mean[a]), 0.0) * (2.0 * size[a] * size / (size[a] + size))
            d[gone] = np.inf
            d[a] = np.inf
            b = int(d.argmin())
            if len(chain) > 1 and d[chain[-2]] <= d[b] * (1 + 1e-12):
                b = chain[-2]
                gap = np.linalg.norm(mean[a] - mean[b])
                joins.append((float(np.sqrt(2.0 * size[a] * size[b] / (size[a] + size[b])) * gap), int(names[a]), int(names[b])))
                chain = chain[:-2]
                mean[b] = (size[a] * mean[a] + size[b] * mean[b]) / (size[a] + size[b])
                size[b] += size[a]
                square[b] = mean[b] @ mean[b]
                gone[a] = True
                break
            chain.append(b)
    forest, owner = Forest([Node(i, lo=i, hi=i) for i in range(n)], n), list(range(n))  # owner: next row of a row's cluster

    def find(i: int) -> int:
        while owner[i] != i:
            owner[i] = owner[owner[i]]
            i = owner[i]
        return i

    node = list(range(n))  # of the cluster whose first row this is
    for height, a, b in sorted(joins, key=lambda j: j[0]):
        a, b = sorted((find(a), find(b)))
        left, right = forest.nodes[node[a]], forest.nodes[node[b]]
        new = Node(len(forest.nodes), left.id, right.id, height, left.lo, max(left.hi, right.hi))
        forest.nodes.append(new)
        forest.order.append(new.id)
        left.parent = right.parent = new.id
        owner[b], node[a] = a, new.id
    return forest


def leaves(forest: Forest, top: int) -> list[int]:
    """Members of a node in order, found on its way down."""
    out, todo = [], [top]
    while todo:
        x = forest.nodes[todo.pop()]
        if x.left < 0:
            out.append(x.id)
        else:
            todo += [x.left, x.right]
    return sorted(out)


FOREST = "series_id string, node int, `left` int, `right` int, height double, n int, lo_seg int, hi_seg int, reverted boolean"


def agglomerate(segments: DataFrame, distance: str = "zm", **settings) -> DataFrame:
    """segments (series_id, seg, xs) to the joins of each series' forest; one task per series."""
    import pandas as pd

    ship(segments.sparkSession)

    def run(g: pd.DataFrame) -> pd.DataFrame:
        g = g.sort_values("seg")
        forest = Agglomeration(D.prepare(np.stack(g["xs"].to_numpy()).astype(float), distance), **settings).run()
        names = g["seg"].to_numpy()
        joins = [x for x in forest.nodes if x.left >= 0]
        return pd.DataFrame({"series_id": g["series_id"].iloc[0], "node": [x.id for x in joins], "left": [x.left for x in joins], "right": [x.right for x in joins], "height": [x.height for x in joins], "n": [len(x.held) for x in joins], "lo_seg": [int(names[x.lo]) for x in joins], "hi_seg": [int(names[x.hi]) for x in joins], "reverted": [x.reverted for x in joins]})

    return segments.select("series_id", "seg", "xs").groupBy("series_id").applyInPandas(run, FOREST)


def clusters(segments: DataFrame, distance: str = "zm", cut_rule: str = "mean_jump", **settings) -> DataFrame:
    """segments to (series_id, cluster_id, seg)."""
    import pandas as pd

    ship(segments.sparkSession)

    def run(g: pd.DataFrame) -> pd.DataFrame:
        g = g.sort_values("seg")
        _, found = cluster(D.prepare(np.stack(g["xs"].to_numpy()).astype(float), distance), cut_rule, **settings)
        names = g["seg"].to_numpy()
        pairs = [(k, int(names[i])) for k, members in enumerate(found) for i in members]
        return pd.DataFrame({"series_id": g["series_id"].iloc[0], "cluster_id": [p[0] for p in pairs], "seg": [p[1] for p in pairs]})

    return segments.select("series_id", "seg", "xs").groupBy("series_id").applyInPandas(run, "series_id string, cluster_id int, seg int")


def agglomerate_rounds(segments: DataFrame, stop_clusters: int = 1, stop_height: float | None = None) -> DataFrame:
    """Ward agglomeration of giant series in rounds: every pair closer than both its neighbouring pairs joins; of a run of equally
    close pairs every other one does, from the left.  Rounds go on until stop_clusters are left or no pair may join; where a round
    offers more joins than that leaves, the closest are taken.

    segments (series_id, seg, xs) to (series_id, cluster_id, seg_lo, seg_hi, n).  Blocks of neighbouring clusters are the unit of work,
    a round is one window pass over them, and its result is written to the shared folder."""
    spec = Window.partitionBy("series_id").orderBy("seg_lo")
    state = segments.select("series_id", F.col("seg").alias("seg_lo"), F.col("seg").alias("seg_hi"), F.lit(1).alias("n"), D.centred(F.col("xs")).alias("total"))
    state = materialise(state, "rounds")
    left = state.count()
    while True:
        mean = F.transform("total", lambda v: v / F.col("n"))
        s = state.withColumn("mean", mean).withColumn("next_mean", F.lead("mean").over(spec)).withColumn("next_n", F.lead("n").over(spec))
        d = F.sqrt(2.0 * F.col("n") * F.col("next_n") / (F.col("n") + F.col("next_n"))) * D.euclid(F.col("mean"), F.col("next_mean"))
        s = s.withColumn("d", F.when(F.col("next_n").isNotNull(), d))
        if stop_height is not None:
            s = s.withColumn("d", F.when(F.col("d") <= stop_height, F.col("d")))
        s = s.withColumns({"before": F.lag("d").over(spec), "after": F.lead("d").over(spec), "alive": F.count(F.lit(1)).over(Window.partitionBy("series_id"))})
        least = F.col("d").isNotNull() & (F.col("before").isNull() | (F.col("d") <= F.col("before"))) & (F.col("after").isNull() | (F.col("d") <= F.col("after")))
        s = s.withColumns({"least": F.coalesce(least, F.lit(False)), "place": F.row_number().over(spec)})
        edge = F.max(F.when(~F.col("least"), F.col("place"))).over(spec.rowsBetween(Window.unboundedPreceding, 0))
        s = s.withColumn("takes", F.col("least") & ((F.col("place") - F.coalesce(edge, F.lit(0))) % 2 == 1))
        order = F.row_number().over(Window.partitionBy("series_id", "takes").orderBy("d", "seg_lo"))
        s = s.withColumn("takes", F.col("takes") & (order <= F.col("alive") - stop_clusters))
        s = s.withColumn("taken", F.coalesce(F.lag("takes").over(spec), F.lit(False)))
        s = s.withColumns({"hi2": F.lead("seg_hi").over(spec), "n2": F.lead("n").over(spec), "total2": F.lead("total").over(spec)})
        merged = s.filter(~F.col("taken")).select(
            "series_id", "seg_lo", F.when(F.col("takes"), F.col("hi2")).otherwise(F.col("seg_hi")).alias("seg_hi"),
            F.when(F.col("takes"), F.col("n") + F.col("n2")).otherwise(F.col("n")).alias("n"),
            F.when(F.col("takes"), F.zip_with("total", "total2", lambda x, y: x + y)).otherwise(F.col("total")).alias("total"),
        )
        state, before = materialise(merged, "rounds"), left
        left = state.count()
        if left == before:
            break
    return state.select("series_id", (F.row_number().over(spec) - 1).alias("cluster_id"), "seg_lo", "seg_hi", "n")
