"""In-context classifiers: probability of each row's own label given a labelled context.

counts: Dirichlet-multinomial naive Bayes over tokens. kernel: attention-like
weights of context rows. gp: kernel least squares that falls back to the class
prior. external: a user's exported checkpoint. None is the pretrained model of
the literature; quality figures are those of these substitutes.
"""

from __future__ import annotations

import os

import numpy as np

from vtask.kernels.tasks import Tokens
from vtask.kernels.table import Frame

EPS = 1e-9


class Counts:
    """Closed-form posterior predictive over tokens; numbers in ten quantile bins."""

    def __init__(self, bins: int = 10, alpha: float = 1.0):
        self.bins, self.alpha = bins, alpha

    def fit(self, f: Frame, y: np.ndarray):
        self.classes = np.unique(y[y >= 0])
        self.tokens = Tokens.fit(f, self.bins)
        cols = self.tokens.columns(f)
        self.n = np.array([(y == k).sum() for k in self.classes], float)
        self.table = []
        for col, cnt in zip(cols, self.tokens.counts, strict=True):
            rows = [dict(zip(*(a.tolist() for a in np.unique(col[y == k], return_counts=True)), strict=True)) for k in self.classes]
            self.table.append((len(cnt), rows))
        return self

    def proba(self, f: Frame) -> np.ndarray:
        log = np.tile(np.log(self.n / self.n.sum()), (f.n, 1))
        for col, (size, rows) in zip(self.tokens.columns(f), self.table, strict=True):
            v, back = np.unique(col, return_inverse=True)
            t = np.log(np.array([[r.get(x, 0) + self.alpha for r in rows] for x in v.tolist()]) / (self.n + self.alpha * (size + 1)))
            log += t[back]
        p = np.exp(log - log.max(axis=1, keepdims=True))
        return p / p.sum(axis=1, keepdims=True)


class _Scaled:
    """Robust scale, clipped; categories as one-hot blocks."""

    def __init__(self, f: Frame, clip: float = 8.0):
        q = np.quantile(f.x, [0.25, 0.5, 0.75], axis=0) if f.x.shape[1] else np.zeros((3, 0))
        iqr, sd = q[2] - q[0], f.x.std(axis=0) if f.x.shape[1] else np.zeros(0)
        self.mid, self.width, self.clip = q[1], np.where(iqr > 0, iqr, np.where(sd > 0, sd, 1.0)), clip
        self.cats = [{v: i for i, v in enumerate(np.unique(f.c[:, j].astype(str)).tolist())} for j in range(f.c.shape[1])]

    def __call__(self, f: Frame) -> np.ndarray:
        parts = [np.clip((f.x - self.mid) / self.width, -self.clip, self.clip)]
        for j, m in enumerate(self.cats):
            z = np.zeros((f.n, len(m) + 1))  # the last place is for new categories
            z[np.arange(f.n), [m.get(v, len(m)) for v in f.c[:, j].astype(str).tolist()]] = np.sqrt(0.5)
            parts.append(z)
        return np.concatenate(parts, axis=1)


def _sq(a: np.ndarray, b: np.ndarray) -> np.ndarray:
    return np.maximum((a**2).sum(1)[:, None] + (b**2).sum(1) - 2 * a @ b.T, 0)


def bandwidth(z: np.ndarray, k: int = 10, rows: int = 500) -> float:
    """Median squared distance to the k-th neighbour, over the first rows."""
    d = np.sort(_sq(z[:rows], z), axis=1)
    h = float(np.median(d[:, min(k, d.shape[1] - 1)])) if d.size else 1.0
    return h if h > 0 else 1.0


class Kernel:
    """Class mass of context rows; the floor is added to the mass ('mass') or after normalising ('softmax')."""

    def __init__(self, floor: str = "mass", eps: float = 1e-3):
        self.floor, self.eps = floor, eps

    def fit(self, f: Frame, y: np.ndarray):
        self.scale = _Scaled(f)
        self.z = self.scale(f)
        self.h = bandwidth(self.z)
        self.classes = np.unique(y[y >= 0])
        self.hot = (y[:, None] == self.classes).astype(float)
        return self

    def mass(self, f: Frame) -> np.ndarray:
        d = _sq(self.scale(f), self.z)
        if self.floor == "softmax":
            d = d - d.min(axis=1, keepdims=True)
        return np.exp(-d / self.h) @ self.hot

    def proba(self, f: Frame) -> np.ndarray:
        m = self.mass(f)
        if self.floor == "softmax":
            m = m / np.maximum(m.sum(axis=1, keepdims=True), EPS)
        m = m + self.eps
        return m / m.sum(axis=1, keepdims=True)


class GP:
    """Posterior mean of kernel least squares on one-hot labels around the class prior."""

    def __init__(self, most: int = 1000, noise: float = 0.1):
        self.most, self.noise = most, noise

    def fit(self, f: Frame, y: np.ndarray):
        f, y = f.take(slice(0, self.most)), y[: self.most]
        self.scale = _Scaled(f)
        self.z = self.scale(f)
        self.h = bandwidth(self.z)
        self.classes = np.unique(y[y >= 0])
        hot = (y[:, None] == self.classes).astype(float)
        self.prior = hot.mean(axis=0)
        k = np.exp(-_sq(self.z, self.z) / self.h)
        self.coef = np.linalg.solve(k + self.noise * np.eye(len(k)), hot - self.prior)
        return self

    def proba(self, f: Frame) -> np.ndarray:
        p = np.maximum(self.prior + np.exp(-_sq(self.scale(f), self.z) / self.h) @ self.coef, 1e-3)
        return p / p.sum(axis=1, keepdims=True)


class External:
    """Seam for an exported checkpoint with inputs (context, labels, queries) and class probabilities out."""

    def __init__(self, path: str):
        if not os.path.exists(path):
            raise FileNotFoundError(f"no checkpoint at {path}; none is shipped")
        self.path = path

    def fit(self, f: Frame, y: np.ndarray):
        self.scale = _Scaled(f)
        self.z, self.y = self.scale(f).astype(np.float32), y
        self.classes = np.unique(y[y >= 0])
        return self

    def proba(self, f: Frame) -> np.ndarray:
        import onnxruntime

        s = onnxruntime.InferenceSession(self.path)
        names = [i.name for i in s.get_inputs()]
        code = np.searchsorted(self.classes, self.y).astype(np.int64)
        return s.run(None, dict(zip(names, (self.z, code, self.scale(f).astype(np.float32)), strict=True)))[0]


def make(name: str):
    kind, _, arg = name.partition(":")
    return {"counts": Counts, "kernel": Kernel, "gp": GP, "external": External}[kind](*([arg] if arg else []))


def support(backbone, f: Frame, y: np.ndarray, block: int = 4096) -> np.ndarray:
    """Probability of each row's own label; a tiny constant where the context lacks the label."""
    out = np.full(f.n, EPS)
    for i in range(0, f.n, block):
        p = backbone.proba(f.take(slice(i, i + block)))
        at = np.searchsorted(backbone.classes, y[i : i + block])
        ok = (at < backbone.classes.size) & (backbone.classes[np.minimum(at, backbone.classes.size - 1)] == y[i : i + block])
        rows = np.flatnonzero(ok)
        out[i + rows] = np.maximum(p[rows, at[rows]], EPS)
    return out
