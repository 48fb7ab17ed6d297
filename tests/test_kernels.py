"""Worked examples and invariants of the kernels."""

from dataclasses import replace

import numpy as np
import pytest

from seqnorm.baselines import kernels
from seqnorm.functions import distance as D
from seqnorm import catalog
from seqnorm.operators import contig
from seqnorm.operators.detect import events_of
from seqnorm.operators.living import Params, activity, detect_series, fit_series, offline_series
from seqnorm.streaming.detector import LiveSeries

RNG = np.random.default_rng(0)


def carrier(n=6000, births=True):
    pos = np.arange(n)
    t = 2 * np.pi * (pos % 50) / 50
    shapes = [np.sin(t) + 0.5 * np.sin(2 * t), np.sin(t) + 0.5 * np.sin(3 * t), 0.4 * np.sin(t) + np.sin(2 * t)]
    concept = np.where(pos < n // 10, 0, np.where(pos < n // 5, 1, np.where(pos < 3 * n // 5, 0, 2 if births else 1)))
    return np.choose(concept, shapes) + 0.03 * np.random.default_rng(1).normal(size=n)


def test_distances():
    a, b, c = RNG.normal(size=(3, 24))
    assert D.zm(a, a + 5) == pytest.approx(0, abs=1e-9) and D.zn(a, 3 * a + 5) == pytest.approx(0, abs=1e-6)
    assert D.zm(a, b) == pytest.approx(D.zm(b, a)) and D.zm(a, c) <= D.zm(a, b) + D.zm(b, c) + 1e-12
    assert D.zn(a, b) <= 2 * np.sqrt(24) + 1e-9
    cross = max(np.dot(D.prepare(a, "zm")[max(0, s) : 24 + min(0, s)], D.prepare(b, "zm")[max(0, -s) : 24 + min(0, -s)]) for s in range(-23, 24))
    assert D.sbd(a, b) == pytest.approx(1 - cross / np.linalg.norm(D.prepare(a, "zm")) / np.linalg.norm(D.prepare(b, "zm")))
    assert D.dtw(a, a) == 0 and D.dtw(a, b) <= D.zm(a, b) + 1e-12 and D.dtw(a, b, 0) == pytest.approx(D.zm(a, b))
    pattern = np.r_[b, a]
    many = RNG.normal(size=(2, 300, 24))
    assert D.dtw_rows(*many) == pytest.approx([D.dtw(x, y) for x, y in zip(*many)])
    for kind, fn in (("sbd", D.sbd), ("dtw", D.dtw)):
        some = np.vstack([many[0][:5], np.zeros(24)])
        table = D.placements(some, np.r_[a, np.zeros(24), b], kind)
        assert table == pytest.approx(np.array([[fn(w, q) for q in D.sliding(np.r_[a, np.zeros(24), b], 24)] for w in some]))
    best, at = D.min_place(pattern, a)
    assert at == 24 and best == pytest.approx(0, abs=1e-6)
    assert all(best <= D.zm(pattern[o : o + 24], a) + 1e-9 for o in range(25))
    assert D.phi(np.array([0, 1, 2, 10.0]), 1.0, 0.5) == pytest.approx([1, 1, np.exp(-0.5), np.exp(-4.5)])


def test_chain_example():
    links = (0.2, 0.1, 18, 9.2, 4, 6.2, 5.3, 21.9, 14.8, 0.9, 16.9, 9.5, 2.1, 1.1)
    near = lambda a, b: links[max(a[0], b[0]) - 1] if max(a[0], b[0]) - min(a[-1], b[-1]) == 1 else 1e9
    f = contig.Agglomeration(np.zeros((15, 1)), linker=near, repair=False, stop_clusters=4).run()
    joins = [(f.nodes[i].lo, f.nodes[i].hi) for i in f.order]
    assert joins == [(1, 2), (0, 2), (9, 10), (13, 14), (12, 14), (4, 5), (6, 7), (4, 7), (3, 7), (11, 14), (8, 10)]
    assert [(x.lo, x.hi) for x in sorted(f.roots(), key=lambda x: x.lo)] == [(0, 2), (3, 7), (8, 10), (11, 14)]


def test_repair_example():
    """Four clusters with the printed linkages: the join at 62.1 is undone for the one at 22.64's closer part."""
    names = {(0,): "C1", (1,): "C8", (2,): "C10", (3,): "C9"}
    table = {("C1", "C8"): 89.8, ("C8", "C10"): 68.0, ("C10", "C9"): 62.1, ("C8", "C9"): 20.0}

    def linker(a, b):
        if names.get(a) and names.get(b):
            return table.get((names[a], names[b]), table.get((names[b], names[a]), 200.0))
        return 22.64 if {1} == set(a) or {1} == set(b) else 150.0

    f = contig.Agglomeration(np.zeros((4, 1)), linker=linker).run()
    assert f.splits >= 1
    live = [set(x.members) for x in f.nodes if x.live and x.left >= 0]
    assert {1, 3} in live and any(x.reverted and set(x.members) == {2, 3} for x in f.nodes)


def test_outlier_is_left_for_later():
    level = np.array([5, 5, 5, 5, 0, 0.6, 9, 0.3, 0.8])
    rows = level[:, None] + np.random.default_rng(0).normal(size=(9, 4)) * 0.01
    f = contig.Agglomeration(rows).run()
    with6 = min(i for i in f.order if 6 in f.nodes[i].members and f.nodes[i].live)
    assert any(i < with6 or 6 not in f.nodes[i].members for i in f.order if {5, 8} <= set(f.nodes[i].members) and f.nodes[i].live)
    assert f.splits > 0


def test_cut_example():
    # fixed values: the two branches of the worked example and the means of their jumps
    for heights, mean in (([0.13, 0.23, 0.55, 26.12, 145], 36.2175), ([1.11, 2.58, 13.72, 4.2, 145], 35.9725)):
        assert tuple(heights) in catalog.TOY_HEIGHTS.values()
        limit = contig.jump_limit(heights, "mean_jump", 0)
        assert limit == pytest.approx(mean)
        assert [j > limit for j in np.diff(heights)] == [False, False, False, True]


def test_drift_counter_finds_planted_cuts():
    """Each change of shape is found within twenty periods, a series without one has none; anomalies are no drift."""
    from seqnorm.baselines import kernels

    rng, at = np.random.default_rng(2), np.arange(10_000)
    phase = 2 * np.pi * at / 50
    shapes = np.stack([np.sin(phase), np.sin(2 * phase), 0.4 * np.sin(phase) + np.sin(3 * phase)])
    for cuts in ([], [5000], [2500, 6000]):
        which = np.searchsorted(cuts, at, "right")
        x = shapes[which, at] + 0.05 * rng.normal(size=len(at))
        hit = np.repeat(rng.random(200) < 0.03, 50)
        found = kernels.drift_positions(np.where(hit, 2.5 * x, x), 50)
        assert len(found) == len(cuts) and all(0 <= f - c <= 1000 for f, c in zip(found, cuts)), (cuts, found)


@pytest.mark.parametrize("kind", ["single", "complete", "average", "centroid", "ward"])
@pytest.mark.parametrize("k", [1, 3])
def test_forest_invariants(kind, k):
    rows = np.random.default_rng(3).normal(size=(40, 6)).cumsum(0)
    f = contig.Agglomeration(rows, kind, k).run()
    assert len(f.roots()) == 1 and len(f.roots()[0].members) == 40 and f.splits <= 160
    for cut in contig.branch_cut(f), contig.branch_cut(f, "count", count=5), contig.branch_cut(f, "height", height=2.0):
        assert sorted(i for c in cut for i in c) == list(range(40))
    assert len(contig.branch_cut(f, "count", count=5)) == 5
    plain = contig.Agglomeration(rows, kind, 1, repair=False).run()
    assert all(x.hi - x.lo + 1 == len(x.members) for x in plain.nodes)


def test_plain_agglomeration_is_the_closest_pair_each_time():
    rows = np.random.default_rng(5).normal(size=(25, 4))
    f = contig.Agglomeration(rows, repair=False).run()
    clusters = [[i] for i in range(25)]
    for j in f.order:
        d = []
        for a, b in zip(clusters, clusters[1:]):
            gap = rows[a].mean(0) - rows[b].mean(0)
            d.append(np.sqrt(2 * len(a) * len(b) / (len(a) + len(b))) * np.linalg.norm(gap))
        i = int(np.argmin(d))
        assert f.nodes[j].height == pytest.approx(d[i]) and f.nodes[j].members == tuple(clusters[i] + clusters[i + 1])
        clusters[i : i + 2] = [clusters[i] + clusters[i + 1]]


def test_birth_and_recurrence():
    x, p = carrier(), Params()
    model = fit_series(x[:1200], p)
    found = detect_series(x, model, p)
    assert found.births and found.births[0][0] >= 3600
    born = found.model.patterns[found.births[0][1]]
    assert all(D.zm(born.shape, q.shape) > q.tau for q in model.patterns)
    again = detect_series(carrier(births=False), model, p)
    assert not again.births and again.active[1200:3400].any() and again.model.win <= p.win_max * p.ell


def test_births_have_no_limit_and_refusals_are_reported():
    rng = np.random.default_rng(4)
    # 200 concepts of random shape, of which a good third are admitted
    shapes = np.cumsum(rng.normal(size=(200, 10)), 1)
    x = np.concatenate([np.tile(s - s.mean(), 30) for s in shapes]) + 0.02 * rng.normal(size=200 * 300)
    p = Params(ell=10)
    model = fit_series(x[:600], p)
    found = detect_series(x, model, p)
    assert len(found.model.patterns) > 64 and not found.refused
    few = detect_series(x, model, replace(p, max_patterns=len(model.patterns) + 2))
    assert len(few.births) == 2 and few.births == found.births[:2] and few.refused
    events = [e for e in events_of(few) if e[1] == "refused"]
    assert events == [(j, "refused", -1) for j in few.refused] and min(few.refused) > few.births[-1][0]
    live = LiveSeries(replace(p, max_patterns=len(model.patterns)), 600)
    assert any(r[4] == "refused" for i, v in enumerate(x[:3000]) for r in live.push(i, float(v)))


def test_online_sees_only_the_past():
    x, p = carrier(), Params()
    model = fit_series(x[:1200], p)
    whole, part = detect_series(x, model, p), detect_series(x[:3000], model, p)
    assert np.allclose(whole.score[: len(part.score)], part.score)


def test_stream_loop_equals_epochs():
    from seqnorm.streaming.detector import LiveSeries

    x, p = carrier(4000), Params()
    live = LiveSeries(p, 800)
    rows = [r for i, v in enumerate(x) for r in live.push(i, float(v))]
    found = detect_series(x, fit_series(x[:800], p), p)
    score = np.array([r[1] for r in rows if r[4] is None])
    assert np.allclose(score, found.score, atol=1e-6)
    assert [(r[0], r[5]) for r in rows if r[4] == "born"] == found.births
    assert list(live.push(5, 1.0)) == [] and live.late == 1


@pytest.mark.parametrize("more", [dict(delta=120), dict(scan="lazy"), dict(scan="lazy", delta=120), dict(warmup="hold"), dict(relearn_mult=2.0)])
def test_stream_with_options_equals_batch(more):
    x, p = carrier(4000), Params(**more)
    live = LiveSeries(p, 800)
    rows = [r for i, v in enumerate(x) for r in live.push(i, float(v))]
    assert sum(r[4] is None for r in rows) == len(x) - 49 - p.delta  # held back until the delay has passed
    rows += live.flush()
    found = detect_series(x, fit_series(x[:800], p), p)
    told = [r for r in rows if r[4] is None]
    assert np.allclose([r[1] for r in told], found.score, atol=1e-6)
    assert [r[3] for r in told] == found.no_active.tolist()
    assert sorted((r[0], r[4], r[5]) for r in rows if r[4]) == events_of(found)


def test_lazy_scan_against_window_by_window():
    """A literal loop over full memberships: inactive patterns count only where no active one is left."""
    x, p = carrier(8000, births=False), Params(births=False)
    model = fit_series(x[:3000], p)
    everything, lazy = detect_series(x, model, p), detect_series(x, model, Params(births=False, scan="lazy"))
    m, alive = len(model.patterns), set(range(len(model.patterns)))
    frequent = np.stack([activity(D.phi(everything.dist[:, q], model.patterns[q].tau, 1 / model.patterns[q].tau), model.patterns[q].freq, model.win, p)[1] for q in range(m)], 1)
    for j in range(len(everything.score)):
        alive = {q for q in alive if frequent[j, q]} or {q for q in range(m) if frequent[j, q]}
        assert alive == set(np.flatnonzero(lazy.active[j]))
        looked = sorted(alive) or range(m)
        q = min(looked, key=lambda q: (everything.dist[j, q], q))
        assert lazy.nearest[j] == q and lazy.score[j] == pytest.approx(everything.dist[max(0, j - 50) : j + 1, q].min(), abs=1e-6)
    assert lazy.evaluations < everything.evaluations


def test_activity_and_scores():
    phi = np.r_[np.ones(50), np.zeros(50)]
    avg, on = activity(phi, 0.5, 9, Params())
    assert avg[0] == 1 and on[:50].all() and not on[60:].any()
    x = carrier()
    off = offline_series(x, Params())
    assert off.score.min() >= 0 and len(off.score) == len(x) - 49
    copy = detect_series(np.tile(fit_series(x[:1200], Params()).patterns[0].shape, 10), fit_series(x[:1200], Params()), Params())
    assert copy.score[200:].min() < 0.5


def test_profiles_and_baselines():
    x = carrier(1500)
    ready = D.prepare(D.sliding(x, 50), "zn")
    left = kernels.matrix_profile(x, 50, "left")
    for j in (50, 333, 1200):
        assert left[j] == pytest.approx(min(np.linalg.norm(ready[j] - ready[i]) for i in range(j - 49)), abs=1e-5)
    exact, pruned = kernels.backward_discord(x, 50, prune=False), kernels.backward_discord(x, 50)
    assert np.allclose(exact[200:], left[200:], atol=1e-5) and (pruned >= exact - 1e-5).all()
    assert pruned.argmax() == exact.argmax()
    shapes, w = kernels.static_fit(x, 50)
    assert w.sum() == pytest.approx(1) and len(kernels.static_score(x, shapes, w, 50)) == 1451
    assert len(kernels.batch_shape(x, 50, batch=500)) == 1451
    assert kernels.drift_positions(np.r_[RNG.normal(size=500), RNG.normal(size=500) + 3], 20)


def test_transformer_gradients():
    net = kernels.Transformer(8, 4, 1)
    x = RNG.random((5, 8))
    _, _, c1, c2, y1, y2 = net.passes(x)
    grad = {k: np.zeros_like(v) for k, v in net.p.items()}
    o1 = (y1 @ net.p["o1"])[..., 0] + net.p["b1"]
    do = (2 * (o1 - x) / x.size)[..., None]
    net.back(do @ net.p["o1"].T, c1, grad)
    for name in ("Q", "K", "V", "F", "G", "P", "E"):
        at = (0, 1)
        loss = []
        for step in (1e-5, -2e-5):
            net.p[name][at] += step
            y, _ = net.encode(x, np.zeros_like(x))
            loss.append((((y @ net.p["o1"])[..., 0] + net.p["b1"] - x) ** 2).mean())
        net.p[name][at] += 1e-5
        assert grad[name][at] == pytest.approx((loss[0] - loss[1]) / 2e-5, rel=1e-3, abs=1e-7)


def test_experiments_take_the_grids_of_the_survey():
    from inspect import signature

    from seqnorm import workloads as w

    grid = lambda f, name="sweep": list(signature(f).parameters[name].default)
    assert grid(w.x1) == list(range(2, 12)) and grid(w.x2) == [10, 20, 30, 40, 50] and grid(w.x4) == [20, 40, 60, 80, 100]
    shares = [1, 5, 10, 15, 20, 25, 30]
    assert grid(w.x3, "shares") == grid(w.x6) == shares and grid(w.x5a, "shares") == shares[1:]
    assert grid(w.x5b) == [0.1, 0.5, 1.0, 1.5, 2.0, 2.5, 3.0] and grid(w.x7a) == [1, 2, 3, 5, 10, 15, 20]
    assert grid(w.x7b) == [10, 20, 30, 40, 50] and grid(w.x7c) == [2, 3, 4]
    assert {0.001, 0.01, 0.02, 0.04, 0.06, 0.08, 0.1} == set(grid(w.x7d))


def test_baselines_take_the_windows_that_the_series_has(monkeypatch):
    from seqnorm import workloads

    x, seen = carrier(3000), {}
    real_shape, real_step = kernels.k_shape, kernels.Transformer.step
    monkeypatch.setattr(kernels, "k_shape", lambda rows, k: seen.setdefault("batch", len(rows)) and real_shape(rows[:50], k))
    monkeypatch.setattr(kernels, "_free_clusters", lambda ready: seen.setdefault("static", len(ready)) and [[0, 1], [2]])
    monkeypatch.setattr(kernels.Transformer, "step", lambda net, rows, mix: seen.update(net=seen.get("net", 0) + len(rows)))
    kernels.batch_shape(x, 50)
    kernels.static_fit(x, 50)
    kernels.transformer_fit(x, 50, epochs=1)
    assert seen == {"batch": 2901, "static": 2901, "net": 2951}
    monkeypatch.setattr(kernels.Transformer, "step", real_step)
    score, *_ = workloads.score_of("transformer", x[:1200], Params())
    assert np.array_equal(score, kernels.transformer_score(x[:1200], 50, epochs=3, stride=1))
