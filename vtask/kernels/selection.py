"""Folds, structural-violation probes, candidate statistics, selection of configurations and tasks, scores, ensembles."""

from __future__ import annotations

import math
from dataclasses import dataclass

import numpy as np

from vtask.kernels.draws import rng
from vtask.kernels.table import Frame
from vtask.kernels.tasks import TEMPLATES


def holdout_size(n: int, splits: int = 3, rho: float = 0.10, n_max: int = 2048) -> int:
    return min(n_max, math.ceil(rho * n), n // splits, n - 1)


def folds(n: int, splits: int, rho: float, seed: int, n_max: int = 2048) -> list[np.ndarray]:
    """Disjoint held-out row sets of one size, shared by all candidates."""
    if n < 2:
        raise ValueError("a context of fewer than two rows cannot be held out from")
    splits = min(splits, n)
    h = max(1, holdout_size(n, splits, rho, n_max))
    order = rng(seed, "folds").permutation(n)
    return [order[s * h : (s + 1) * h] for s in range(splits)]


def probe_budget(h: int, ops: list[str]) -> dict[str, int]:
    """h probes over the operators, the remainder to the first ones."""
    return {op: h // len(ops) + (i < h % len(ops)) for i, op in enumerate(ops)}


def probes(held: Frame, train: Frame, seed: int, fold: int, p: float = 0.3, lam: float = 0.5) -> tuple[Frame, np.ndarray]:
    """Broken copies of held-out rows and the operator of each: columns shuffled, subsets replaced, numbers jittered."""
    ops = ["shuffle", "replace", *(["jitter"] if held.x.shape[1] else [])]
    g = rng(seed, f"probes.{fold}")
    xs, cs, names = [], [], []
    for op, m in probe_budget(held.n, ops).items():
        base = held.take(g.permutation(held.n)[:m])
        x, c = base.x.copy(), base.c.copy()
        if op == "jitter":
            q = np.quantile(train.x, [0.25, 0.75], axis=0)
            x = x + lam * (q[1] - q[0]) * g.standard_normal(x.shape)
        else:
            for mat, src in ((x, train.x), (c, train.c)):
                for j in range(mat.shape[1]):
                    hit = np.ones(m, bool) if op == "shuffle" else g.random(m) < p
                    mat[hit, j] = src[g.integers(0, src.shape[0], hit.sum()), j]
        xs.append(x)
        cs.append(c)
        names += [op] * m
    return Frame(np.concatenate(xs), np.concatenate(cs), held.num, held.cat), np.array(names)


def win_rate(u: np.ndarray, v: np.ndarray, ties: str = "strict") -> float:
    """Share of pairs with u > v (ties count half on request)."""
    if not u.size or not v.size:
        return 0.0
    s = np.sort(v)
    below, upto = np.searchsorted(s, u, side="left"), np.searchsorted(s, u, side="right")
    return float((below + (0.5 * (upto - below) if ties == "half" else 0)).sum() / (u.size * v.size))


@dataclass(frozen=True)
class Stats:
    """What held-out rows and probes say about a candidate."""

    task: str
    name: str
    med: float
    var: float
    rho: float
    gap: float


def candidate_stats(task: str, name: str, nom: np.ndarray, vio: np.ndarray, ties: str = "strict") -> Stats:
    return Stats(task, name, float(np.median(nom)), float(np.var(nom)), win_rate(nom, vio, ties), float(np.quantile(nom, 0.25) - np.quantile(vio, 0.75)))


def bad_rank(values, larger_is_better: bool) -> np.ndarray:
    """Normalised badness ranks in [0, 1], ties averaged; 0 is best."""
    v = np.asarray(values, float) * (-1 if larger_is_better else 1)
    n = v.size
    return np.array([((v < x).sum() + ((v == x).sum() - 1) / 2) / max(1, n - 1) for x in v])


def intra(stats: list[Stats], coherent: float = 0.7, share: float = 0.70, least: int = 2) -> Stats:
    """The representative of one task's candidates."""
    ok = [s for s in stats if s.med >= coherent]
    if not ok:
        return min(stats, key=lambda s: (-s.rho, s.name))
    size = min(len(ok), max(least, math.ceil(share * len(ok))))
    short = sorted(ok, key=lambda s: (-s.rho, s.name))[:size]
    total = bad_rank([s.med for s in short], True) + bad_rank([s.var for s in short], False) + bad_rank([s.gap for s in short], True)
    return min(zip(total.round(9), (s.name for s in short), short, strict=True))[2]


def badness(stats: list[Stats], w_auc: float = 1.5) -> np.ndarray:
    return w_auc * bad_rank([s.rho for s in stats], True) + bad_rank([s.med for s in stats], True) + bad_rank([s.var for s in stats], False) + bad_rank([s.gap for s in stats], True)


def inter(stats: list[Stats], policy: str = "all", w_auc: float = 1.5, separate: float = 0.50) -> list[Stats]:
    """The tasks to keep: those that separate, by policy all, best or topk (half of them)."""
    ok = [s for s in stats if s.rho >= separate]
    if not ok:
        return [min(stats, key=lambda s: (-s.rho, s.task))]
    order = [s for *_, s in sorted(zip(badness(ok, w_auc).round(9), (s.task for s in ok), ok, strict=True), key=lambda t: t[:2])]
    keep = {"all": len(order), "best": 1, "topk": math.ceil(0.5 * len(order))}[policy]
    return order[:keep]


def surprisal(kappa: np.ndarray, nominal: np.ndarray) -> np.ndarray:
    """-log of the share of nominal supports at or below kappa, smoothed by one."""
    s = np.sort(nominal)
    return -np.log((1 + np.searchsorted(s, kappa, side="right")) / (s.size + 1))


# --- ensembles of task scores, a column a task


def least(s: np.ndarray) -> np.ndarray:
    return s.min(axis=1)


def low2mean(s: np.ndarray) -> np.ndarray:
    return np.sort(s, axis=1)[:, : min(2, s.shape[1])].mean(axis=1)


def suitability(kept: list[Stats], w_auc: float = 1.5) -> np.ndarray:
    """Mean ordinal badness rank of each surviving task."""

    def ordinal(values, larger):
        order = sorted(range(len(kept)), key=lambda i: (-values[i] if larger else values[i], TEMPLATES.index(kept[i].task[0]), kept[i].task))
        r = np.empty(len(kept))
        r[order] = np.arange(1, len(kept) + 1)
        return r

    total = w_auc * ordinal([s.rho for s in kept], True) + ordinal([s.med for s in kept], True) + ordinal([s.var for s in kept], False) + ordinal([s.gap for s in kept], True)
    return total / len(kept)


def combine(s: np.ndarray, kept: list[Stats], how: str = "low2mean", w_auc: float = 1.5) -> np.ndarray:
    """min, low2mean, spread-min, spread-low2mean or weighted."""
    if how in ("min", "low2mean"):
        return least(s) if how == "min" else low2mean(s)
    b = suitability(kept, w_auc)
    if how == "weighted":
        w = 1 / (bad_rank(b, False) + 0.1)
        return s @ (w / w.sum())
    if len(kept) >= 3 and b.max() - b.min() < 1.0:
        return least(s) if how == "spread-min" else low2mean(s)
    return s[:, int(b.argmin())]


# --- measures


def auroc(score: np.ndarray, anomaly: np.ndarray) -> float | None:
    a, n = score[anomaly == 1], score[anomaly == 0]
    return win_rate(a, n, "half") if a.size and n.size else None


def average_precision(score: np.ndarray, anomaly: np.ndarray) -> float | None:
    if not (anomaly == 1).any() or not (anomaly == 0).any():
        return None
    v, back = np.unique(-score, return_inverse=True)
    hit, size = np.bincount(back, anomaly == 1), np.bincount(back)
    return float(((np.cumsum(hit) / np.cumsum(size)) * hit).sum() / hit.sum())
