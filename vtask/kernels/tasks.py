"""Virtual tasks: classification problems whose labels are functions of a row, with parameters frozen from a context.

Five templates, instantiated by the dataset's profile: single attribute (S),
localized direction (L), global direction (G), prototypes (P) and extremity (D).
"""

from __future__ import annotations

from dataclasses import dataclass, field
from itertools import zip_longest

import numpy as np

from vtask.kernels.draws import drawn_subset, normals, u01
from vtask.kernels.table import PROFILES, Frame, Schema

TEMPLATES = ("S", "L", "G", "P", "D")
ALPHA = 1.0


def borders(z: np.ndarray, k: int) -> np.ndarray:
    """Inner quantiles, equal ones merged."""
    return np.unique(np.quantile(z, np.arange(1, k) / k)) if z.size else np.zeros(0)


def bins(z: np.ndarray, b: np.ndarray) -> np.ndarray:
    """Number of borders strictly below z."""
    return (z[:, None] > b).sum(axis=1)


@dataclass
class Transform:
    """Raw, or (x - median) / IQR with the deviation where the IQR is zero."""

    kind: str
    mid: np.ndarray
    width: np.ndarray

    @classmethod
    def fit(cls, x: np.ndarray, kind: str) -> Transform:
        if kind == "raw" or not x.size:
            return cls(kind, np.zeros(x.shape[1]), np.ones(x.shape[1]))
        q = np.quantile(x, [0.25, 0.5, 0.75], axis=0)
        iqr, sd = q[2] - q[0], x.std(axis=0)
        return cls(kind, q[1], np.where(iqr > 0, iqr, np.where(sd > 0, sd, 1.0)))

    def __call__(self, x: np.ndarray) -> np.ndarray:
        return (x - self.mid) / self.width


@dataclass
class Tokens:
    """Numbers as quantile tokens, categories as they are; counts of each on the context."""

    with_num: bool
    edges: list[np.ndarray]
    counts: list[dict[str, int]]
    n: int

    @classmethod
    def fit(cls, f: Frame, k: int | None) -> Tokens:
        edges = [borders(f.x[:, j], k) for j in range(f.x.shape[1])] if k else []
        t = cls(bool(k), edges, [], f.n)
        t.counts = [dict(zip(*(a.tolist() for a in np.unique(col.astype(str), return_counts=True)), strict=True)) for col in t.columns(f)]
        return t

    def columns(self, f: Frame) -> list[np.ndarray]:
        num = [np.char.add("q", bins(f.x[:, j], e).astype(str)) for j, e in enumerate(self.edges)] if self.with_num else []
        return [*num, *(f.c[:, j].astype(str) for j in range(f.c.shape[1]))]

    def rarity(self, f: Frame) -> list[np.ndarray]:
        """-log of each token's smoothed probability, by attribute."""
        out = []
        for col, n in zip(self.columns(f), self.counts, strict=True):
            v, back = np.unique(col, return_inverse=True)
            out.append(np.log((self.n + ALPHA * (len(n) + 1)) / (np.array([n.get(x, 0) for x in v.tolist()]) + ALPHA))[back])
        return out

    def weights(self, f: Frame, seed: int, purpose: str) -> list[np.ndarray]:
        """A fixed random weight for every token, also for ones the context lacks."""
        out = []
        for j, col in enumerate(self.columns(f)):
            v, back = np.unique(col, return_inverse=True)
            out.append(normals(seed, purpose, [f"{j}|{x}" for x in v.tolist()])[back])
        return out


@dataclass(frozen=True)
class Spec:
    """One candidate configuration of one task."""

    task: str
    kind: str
    bins: int = 2
    transform: str = "robust"
    token_bins: int = 2
    clusters: int = 2
    target: str | None = None
    draw: int = 0  # which of several independent draws of subset and weights

    @property
    def drawn(self) -> str:
        """What names the task's random draws."""
        return self.task + (f"#{self.draw}" if self.draw else "")

    @property
    def template(self) -> str:
        return self.task[0]

    @property
    def name(self) -> str:
        return f"{self.task}:{self.kind}:b{self.bins}:{self.transform}:t{self.token_bins}:k{self.clusters}:{self.target or '-'}" + (f":r{self.draw}" if self.draw else "")


def instantiations(profile: str) -> list[tuple[str, str]]:
    """(task, construction) for a profile; dominant profiles have two localized tasks."""
    kind = {PROFILES[0]: "num", PROFILES[1]: "cat"}.get(profile, "mix")
    localized = {PROFILES[3]: [("L1", "num"), ("L2", "mix")], PROFILES[4]: [("L1", "cat"), ("L2", "mix")]}.get(profile, [("L", kind)])
    return [("S", kind), *localized, ("G", kind), ("P", kind), ("D", kind)]


def targets(f: Frame, schema: Schema, limit: int = 4) -> tuple[list[str], list[str]]:
    """Numerical targets by falling IQR / (p99 - p1); categorical targets that make no degenerate or sparse classes, by falling entropy."""
    num = []
    for j, a in enumerate(f.num):
        q = np.quantile(f.x[:, j], [0.01, 0.25, 0.75, 0.99])
        num.append((-(q[2] - q[1]) / (q[3] - q[0]) if q[3] > q[0] else 0.0, -np.unique(f.x[:, j]).size, a))
    cat = []
    for j, a in enumerate(f.cat):
        n = np.unique(f.c[:, j].astype(str), return_counts=True)[1]
        p = n / n.sum()
        if 2 <= n.size <= 10 and n.min() >= max(5, 0.01 * f.n) and p.max() <= 0.95:
            cat.append((float((p * np.log(p)).sum()), a))
    return [a for *_, a in sorted(num)][:limit], [a for _, a in sorted(cat)][:limit]


def axes(task: str, kind: str) -> list[dict]:
    """Candidates of a task other than S: two class or cluster numbers, times transforms or token bins; categories alone have neither, so two draws."""
    size = "clusters" if task[0] == "P" else "bins"
    rest = {"num": [{"transform": t} for t in ("raw", "robust")], "mix": [{"token_bins": q} for q in (2, 3)], "cat": [{"draw": r} for r in (0, 1)]}[kind]
    return [{size: k, **x} for k in (2, 3) for x in rest]


def grid(f: Frame, schema: Schema) -> dict[str, list[Spec]]:
    """Candidates of each task, at most eight."""
    profile = schema.profile
    num, cat = targets(f, schema)
    out: dict[str, list[Spec]] = {}
    for task, kind in instantiations(profile):
        if task == "S":
            first, second = (num, cat) if profile in (PROFILES[0], PROFILES[2], PROFILES[3]) else (cat, num)
            if profile == PROFILES[0]:
                second = []
            if profile == PROFILES[1]:
                second = []
            if profile == PROFILES[2]:
                chosen = [a for pair in zip_longest(num, cat) for a in pair if a][:4]
            else:
                chosen = first or second  # the dominant group, the other only where it has none
            specs = [Spec(task, "num", bins=b, target=a) for a in chosen if a in f.num for b in (2, 3)] + [Spec(task, "cat", target=a) for a in chosen if a in f.cat]
        else:
            specs = [Spec(task, kind, **x) for x in axes(task, kind)]
        if specs:
            out[task] = specs[:8]
    return out


@dataclass
class Task:
    """A spec with its parameters."""

    spec: Spec
    seed: int
    names: list[str] = field(default_factory=list)
    par: dict = field(default_factory=dict)

    @classmethod
    def fit(cls, spec: Spec, f: Frame, seed: int) -> Task:
        t = cls(spec, seed)
        if spec.template == "S":
            t.names = [spec.target]
            if spec.kind == "cat":
                t.par["classes"] = sorted(set(f.c[:, f.cat.index(spec.target)].astype(str).tolist()))
            else:
                t.par["borders"] = borders(f.x[:, f.num.index(spec.target)], spec.bins)
            return t
        mine = {"num": f.num, "cat": f.cat, "mix": f.num + f.cat}[spec.kind]
        t.names = list(mine)
        if spec.template == "L" or (spec.draw and spec.template in "PD"):  # drawn once and shared by the candidates of a draw
            t.names = drawn_subset(seed, spec.drawn, mine)
        v = t._view(f)
        if spec.kind == "num":
            t.par["transform"] = Transform.fit(v.x, spec.transform)
        else:
            t.par["tokens"] = Tokens.fit(v, spec.token_bins if spec.kind == "mix" else None)
        if spec.template == "P":
            t.par["prototypes"] = t._prototypes(v)
        else:
            t.par["borders"] = borders(t._scalar(v), spec.bins)
        return t

    def _view(self, f: Frame) -> Frame:
        i, j = [f.num.index(a) for a in self.names if a in f.num], [f.cat.index(a) for a in self.names if a in f.cat]
        return Frame(f.x[:, i], f.c[:, j], [f.num[k] for k in i], [f.cat[k] for k in j])

    def _scalar(self, v: Frame) -> np.ndarray:
        s = self.spec
        if s.kind == "num":
            z = self.par["transform"](v.x)
            if s.template == "D":
                return np.round(np.sqrt((z**2).sum(axis=1)), 9)
            return np.round(z @ normals(self.seed, f"weight.{s.drawn}", v.num) / np.sqrt(max(1, v.x.shape[1])), 9)
        t = self.par["tokens"]
        r = t.rarity(v)
        if s.template == "D":
            return np.round(np.mean(r, axis=0), 9)
        return np.round(sum(a * w for a, w in zip(r, t.weights(v, self.seed, f"token.{s.drawn}"), strict=True)) / np.sqrt(len(r)), 9)

    # prototypes: numbers (or bin codes) and tokens, by alternating assignment and update from a farthest-first start

    def _parts(self, v: Frame) -> tuple[np.ndarray, np.ndarray]:
        if self.spec.kind == "num":
            return self.par["transform"](v.x), np.empty((v.n, 0), object)
        if self.spec.kind == "cat":
            return np.zeros((v.n, 0)), v.c.astype(str)
        t = self.par["tokens"]
        codes = np.stack([bins(v.x[:, j], e) for j, e in enumerate(t.edges)], axis=1).astype(float) if t.edges else np.zeros((v.n, 0))
        return codes, v.c.astype(str)

    def _distance(self, x: np.ndarray, c: np.ndarray, p: tuple) -> np.ndarray:
        dx, dc = ((x - p[0]) ** 2).sum(axis=1), (c != p[1]).sum(axis=1) if c.shape[1] else 0.0
        if self.spec.kind == "mix":
            return dx / max(1, x.shape[1]) + dc / max(1, c.shape[1])
        return dx + dc

    def _prototypes(self, v: Frame, rounds: int = 20) -> list[tuple]:
        x, c = self._parts(v)
        first = int(np.argmin([u01(self.seed, "first", *np.round(a, 9), *b) for a, b in zip(x[:200], c[:200], strict=True)]))
        p = [(x[first], c[first])]
        while len(p) < self.spec.clusters:
            far = int(np.argmax(np.min([self._distance(x, c, q) for q in p], axis=0)))
            p.append((x[far], c[far]))
        old = None
        for _ in range(rounds):
            d = np.stack([self._distance(x, c, q) for q in p], axis=1)
            y = d.argmin(axis=1)
            if old is not None and (y == old).all():
                break
            old = y
            for k in range(len(p)):
                m = y == k
                if not m.any():
                    far = int(d.min(axis=1).argmax())
                    p[k] = (x[far], c[far])
                    continue
                mid = x[m].mean(axis=0) if self.spec.kind == "num" else np.sort(x[m], axis=0)[(m.sum() - 1) // 2] if x.shape[1] else x[m][0]
                mode = np.array([(lambda u, n: u[n.argmax()])(*np.unique(c[m, j], return_counts=True)) for j in range(c.shape[1])], object)
                p[k] = (mid, mode)
        return p

    def label(self, f: Frame) -> np.ndarray:
        """Class of each row; -1 where a category is new."""
        s = self.spec
        if s.template == "S":
            if s.kind == "cat":
                where = {a: i for i, a in enumerate(self.par["classes"])}
                return np.array([where.get(a, -1) for a in f.c[:, f.cat.index(s.target)].astype(str).tolist()], np.int64)
            return bins(f.x[:, f.num.index(s.target)], self.par["borders"])
        v = self._view(f)
        if s.template == "P":
            x, c = self._parts(v)
            return np.stack([self._distance(x, c, q) for q in self.par["prototypes"]], axis=1).argmin(axis=1)
        return bins(self._scalar(v), self.par["borders"])

    def predictors(self, f: Frame) -> Frame:
        """All attributes, but for a single-attribute task its target."""
        return f.without(self.spec.target) if self.spec.template == "S" else f
