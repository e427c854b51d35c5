from __future__ import annotations

import math

import numpy as np
import pandas as pd
import pytest

from vtask.kernels import baselines as bl
from vtask.kernels import detector as det
from vtask.kernels import selection as sel
from vtask.kernels.backbones import Counts, External, Kernel, make, support
from vtask.kernels.draws import normals, u01
from vtask.kernels.table import CAT, CONST, DROPPED, NUM, PROFILES, Frame, NoUsableAttributes, Schema, attribute_kind, card_threshold, dataset_profile
from vtask.kernels.tasks import Spec, Task, bins, borders, grid, instantiations


def frame(n=300, seed=0):
    g = np.random.default_rng(seed)
    a = g.normal(size=n)
    return pd.DataFrame({"a": a, "b": 2 * a + 0.1 * g.normal(size=n), "c": np.where(a > 0, "x", "y"), "d": g.integers(0, 4, n).astype(str), "e": g.normal(size=n)})


def test_type_rule():
    assert [card_threshold(n) for n in (0, 1, 4, 5, 400, 10**6)] == [2, 2, 2, 3, 20, 20]
    assert attribute_kind(0, 0, True) == CONST and attribute_kind(10, 1, True) == CONST
    assert attribute_kind(100, 9, True) == CAT and attribute_kind(100, 9, False) == CAT and attribute_kind(40, 9, False) == NUM
    assert attribute_kind(10, 6, True) == NUM  # six in ten are too many
    assert attribute_kind(1000, 25, True) == NUM and attribute_kind(1000, 20, False) == CAT
    assert attribute_kind(100, 80, False, True) == DROPPED and attribute_kind(100, 40, False, True) == NUM


def test_profiles():
    assert dataset_profile([NUM, CONST]) == PROFILES[0] and dataset_profile([CAT]) == PROFILES[1] and dataset_profile([NUM, CAT]) == PROFILES[2]
    assert dataset_profile([NUM] * 4 + [CAT]) == PROFILES[3] and dataset_profile([CAT] * 4 + [NUM]) == PROFILES[4]
    with pytest.raises(NoUsableAttributes):
        dataset_profile([CONST])
    assert len(instantiations(PROFILES[3])) == len(instantiations(PROFILES[4])) == 6 and len(instantiations(PROFILES[2])) == 5


def test_bins_by_hand():
    z = np.arange(1.0, 10)
    assert borders(z, 2).tolist() == [5.0] and bins(z, borders(z, 2)).tolist() == [0] * 5 + [1] * 4
    assert borders(np.array([1.0, 1, 1, 1, 9]), 3).tolist() == [1.0]


def test_draws():
    assert 0 <= u01(1, "p", "k") < 1 and u01(1, "p", "k") == u01(1, "p", "k") != u01(2, "p", "k")
    z = normals(0, "n", range(4000))
    assert abs(z.mean()) < 0.06 and abs(z.std() - 1) < 0.05


def test_folds_and_budget():
    assert sel.holdout_size(10**6) == 2048 and sel.holdout_size(100) == 10 and sel.holdout_size(5) == 1
    f = sel.folds(50, 3, 0.1, 0)
    assert len({x for a in f for x in a.tolist()}) == 15 and all(a.size == 5 for a in f)
    with pytest.raises(ValueError):
        sel.folds(1, 3, 0.1, 0)
    assert sel.probe_budget(8, ["a", "b", "c"]) == {"a": 3, "b": 3, "c": 2}


def test_probe_effects():
    """Shuffled columns keep their marginals and lose their dependence; jitter keeps means and adds (IQR / 2)^2; a third of the cells change."""
    s = Schema.fit(frame(6000), list("abcde"))
    f = s.frame(frame(6000))
    p, op = sel.probes(f, f, 1, 0)
    assert p.n == 6000 and {k: (op == k).sum() for k in set(op.tolist())} == {"shuffle": 2000, "replace": 2000, "jitter": 2000}
    sh, ji = p.take(op == "shuffle"), p.take(op == "jitter")
    assert abs(np.corrcoef(f.x[:, 0], f.x[:, 1])[0, 1]) > 0.99 and abs(np.corrcoef(sh.x[:, 0], sh.x[:, 1])[0, 1]) < 0.08
    assert abs(np.median(sh.x[:, 0]) - np.median(f.x[:, 0])) < 0.1
    iqr = np.quantile(f.x[:, 0], 0.75) - np.quantile(f.x[:, 0], 0.25)
    assert abs(ji.x[:, 0].var() - f.x[:, 0].var() - (iqr / 2) ** 2) < 0.12


def test_statistics_by_brute_force():
    g = np.random.default_rng(3)
    u, v = g.integers(0, 9, 40) / 9, g.integers(0, 9, 50) / 9
    assert math.isclose(sel.win_rate(u, v), np.mean([a > b for a in u for b in v]))
    assert math.isclose(sel.win_rate(u, v, "half"), np.mean([(a > b) + 0.5 * (a == b) for a in u for b in v]))
    k = sel.surprisal(u, v)
    assert np.allclose(k, [-np.log((1 + (v <= a).sum()) / (v.size + 1)) for a in u])
    assert sel.bad_rank([3, 1, 1, 9], False).tolist() == [2 / 3, 1 / 6, 1 / 6, 1.0]


def test_selection_by_hand():
    s = [sel.Stats("S", f"c{i}", m, v, r, g) for i, (m, v, r, g) in enumerate([(0.9, 0.01, 0.8, 0.2), (0.8, 0.02, 0.9, 0.1), (0.6, 0.0, 0.99, 0.9), (0.95, 0.05, 0.4, 0.3)])]
    assert sel.intra(s).name == "c0"  # c2 is not coherent; c1, c0, c3 (all of the shortlist) rank c0 best
    assert sel.intra([x for x in s if x.med < 0.7]).name == "c2"
    reps = [sel.Stats(t, t, m, 0.1, r, 0.1) for t, m, r in (("S", 0.9, 0.9), ("L", 0.8, 0.45), ("G", 0.7, 0.6), ("P", 0.75, 0.7))]
    assert [x.task for x in sel.inter(reps)] == ["S", "P", "G"] and len(sel.inter(reps, "best")) == 1 and len(sel.inter(reps, "topk")) == 2
    assert [x.task for x in sel.inter([reps[1]])] == ["L"]


def test_ensembles_by_hand():
    s = np.array([[1.0, 2, 3], [4, 1, 0], [2, 2, 2]])
    kept = [sel.Stats(t, t, m, 0.1, r, 0.1) for t, m, r in (("S", 0.9, 0.9), ("L", 0.8, 0.8), ("G", 0.7, 0.7))]
    assert sel.least(s).tolist() == [1, 0, 2] and sel.low2mean(s).tolist() == [1.5, 0.5, 2]
    b = sel.suitability(kept)
    assert b.argmin() == 0 and b.max() - b.min() >= 1 and sel.combine(s, kept, "spread-min").tolist() == [1, 4, 2]
    w = 1 / (np.array([0, 0.5, 1]) + 0.1)
    assert np.allclose(sel.combine(s, kept, "weighted"), s @ (w / w.sum()))


def test_measures():
    y, s = np.array([0, 0, 1, 1]), np.array([0.1, 0.4, 0.35, 0.8])
    assert sel.auroc(s, y) == 0.75 and math.isclose(sel.average_precision(s, y), (1 + 2 / 3) / 2)
    assert sel.auroc(s, np.zeros(4)) is None


@pytest.mark.parametrize("name", ["counts", "kernel", "gp", "kernel:softmax"])
def test_backbones(name):
    s = Schema.fit(frame(), list("abcde"))
    f = s.frame(frame())
    y = (f.x[:, 0] > 0).astype(int)
    b = make(name).fit(f, y)
    p = b.proba(f)
    assert np.allclose(p.sum(axis=1), 1) and (p >= 0).all()
    assert np.median(support(b, f, y)) > 0.6 and support(b, f, np.full(f.n, 7)).max() < 1e-6


def test_counts_closed_form():
    f = Frame(np.zeros((6, 0)), np.array([["u"], ["u"], ["v"], ["v"], ["v"], ["u"]], object), [], ["c"])
    b = Counts().fit(f, np.array([0, 0, 0, 1, 1, 1]))
    p = b.proba(f.take([0]))[0]
    a, c = 0.5 * (2 + 1) / (3 + 3), 0.5 * (1 + 1) / (3 + 3)
    assert np.allclose(p, [a / (a + c), c / (a + c)])


def test_external_needs_a_file():
    with pytest.raises(FileNotFoundError):
        External("/nowhere.onnx")
    assert Kernel().floor == "mass"


def test_tasks_are_frozen_and_targets_hidden():
    df = frame()
    s = Schema.fit(df, list("abcde"))
    f = s.frame(df)
    for specs in grid(f, s).values():
        assert 1 <= len(specs) <= 8
        for spec in specs:
            t = Task.fit(spec, f, 3)
            y = t.label(f)
            assert (t.label(f.take(slice(10, 20))) == y[10:20]).all() and y.min() >= 0
            if spec.template == "S":
                assert spec.target not in t.predictors(f).num + t.predictors(f).cat
    t = Task.fit(Spec("S", "cat", target="d"), f, 0)
    assert t.label(Frame(f.x[:1], np.array([["x", "new"]], object), f.num, f.cat)).tolist() == [-1]


def test_label_disagreement_falls_with_the_context():
    g = np.random.default_rng(5)
    q = Frame(g.normal(size=(4000, 2)), np.empty((4000, 0), object), ["a", "b"], [])
    gaps = []
    for n in (60, 20000):
        a, b = (Task.fit(Spec("D", "num", bins=3), Frame(g.normal(size=(n, 2)), np.empty((n, 0), object), ["a", "b"], []), 0) for _ in range(2))
        gaps.append((a.label(q) != b.label(q)).mean())
    assert gaps[0] > gaps[1] and gaps[1] < 0.03


@pytest.mark.parametrize("name", ["counts", "kernel", "gp"])
def test_detector(name):
    df = frame(900)
    q = df.iloc[600:].copy()
    y = np.r_[np.ones(80, int), np.zeros(220, int)]
    q.iloc[:80, 1] = np.random.default_rng(1).permutation(df["b"].to_numpy())[:80] + 3
    m = det.fit(df.iloc[:600], list("abcde"), det.Config(backbone=name))
    s = m.score(q)
    assert sel.auroc(s, y) > (0.6 if name == "counts" else 0.7) and len(m.kept) >= 1  # counts are over-confident
    assert (s == det.fit(df.iloc[:600], list("abcde"), det.Config(backbone=name)).score(q)).all()


@pytest.mark.parametrize("name", list(bl.METHODS))
def test_baselines(name):
    g = np.random.default_rng(0)
    x = g.normal(size=(500, 5))
    x[:, 1] = 2 * x[:, 0] + 0.1 * g.normal(size=500)
    q = np.concatenate([x[300:], 3 * g.normal(size=(40, 5))])
    s = bl.METHODS[name]().fit(x[:300]).score(q)
    assert np.isfinite(s).all() and (name == "goad" or sel.auroc(s, np.r_[np.zeros(200), np.ones(40)]) > 0.75)


def test_chain_density_and_adapters():
    df = frame()
    s = Schema.fit(df, list("abcde"))
    f = s.frame(df)
    m = bl.ChainDensity().fit(f)
    assert np.isfinite(m.score(f)).all() and m.calls == 4
    assert [a.shape[1] for a in bl.adapt(np.ones((3, 60)), 50, 0, 10)] == [50] * 10 and bl.adapt(np.ones((3, 7)), 50, 0)[0].shape == (3, 50)
