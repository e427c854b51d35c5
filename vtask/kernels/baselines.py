"""Detectors to compare with, on a bounded context; larger scores are more anomalous.

fit(context matrix) then score(matrix), on z-scored numbers with categories as
one-hot columns. Exact: ecod, copod, hbos, knn, lof, dte_np, pca, loda,
kernel_density, mcd (concentration steps from one robust start), iforest.
Approximate and said so: ocsvm (random Fourier features), feature_bagging (ten
subsets), vae, deep_svdd, goad, dif, planar_flow and dagmm (small networks
trained with plain gradients). Methods that need a pretrained checkpoint are not
imitated; see PRETRAINED.
"""

from __future__ import annotations

import numpy as np

from vtask.kernels.draws import rng

PRETRAINED = {  # name: what an adapter has to obey
    "fomo_0d": {"columns": 100, "context": 5000, "transform": "quantile"},
    "outformer": {"columns": 100, "context": 5000, "transform": "quantile"},
    "tactic_clean": {"columns": 50, "subsets": 10, "transform": "minmax"},
    "tactic_cont": {"columns": 50, "subsets": 10, "transform": "minmax"},
}


def adapt(x: np.ndarray, columns: int, seed: int, subsets: int = 1) -> list[np.ndarray]:
    """Column sets for a model of fixed width: zero padding below it, random subsets beyond it."""
    if x.shape[1] <= columns:
        return [np.pad(x, ((0, 0), (0, columns - x.shape[1])))]
    return [x[:, np.sort(rng(seed, f"columns.{i}").permutation(x.shape[1])[:columns])] for i in range(subsets)]


class Base:
    def __init__(self, seed: int = 0):
        self.seed = seed

    def fit(self, x: np.ndarray):
        self.mid, self.sd = x.mean(axis=0), x.std(axis=0)
        self.sd = np.where(self.sd > 0, self.sd, 1.0)
        self._fit((x - self.mid) / self.sd)
        return self

    def score(self, x: np.ndarray) -> np.ndarray:
        return self._score((x - self.mid) / self.sd)


def _tails(s: np.ndarray, x: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Shares of sorted s at or below, and at or above, x; at least 1 / (n + 1)."""
    n = s.size
    return np.maximum(np.searchsorted(s, x, "right"), 1) / (n + 1), np.maximum(n - np.searchsorted(s, x, "left"), 1) / (n + 1)


class ECOD(Base):
    def _fit(self, x):
        self.s = np.sort(x, axis=0)
        d = x - x.mean(axis=0)
        self.skew = (d**3).mean(axis=0)

    def _parts(self, x):
        t = [_tails(self.s[:, j], x[:, j]) for j in range(x.shape[1])]
        left, right = -np.log(np.stack([a for a, _ in t], 1)), -np.log(np.stack([b for _, b in t], 1))
        return left, right, np.where(self.skew < 0, left, right)

    def _score(self, x):
        left, right, auto = self._parts(x)
        return np.maximum(np.maximum(left.sum(1), right.sum(1)), auto.sum(1))


class COPOD(ECOD):
    def _score(self, x):
        left, right, auto = self._parts(x)
        return np.maximum((left + right).sum(1) / 2, auto.sum(1))


class HBOS(Base):
    def __init__(self, seed=0, bins=10):
        super().__init__(seed)
        self.bins = bins

    def _fit(self, x):
        self.h = [np.histogram(x[:, j], self.bins) for j in range(x.shape[1])]
        self.n = x.shape[0]

    def _score(self, x):
        out = 0.0
        for j, (c, e) in enumerate(self.h):
            k = np.clip(np.searchsorted(e, x[:, j], "right") - 1, 0, self.bins - 1)
            share = np.where((x[:, j] < e[0]) | (x[:, j] > e[-1]), 0, c[k] / self.n)
            out = out - np.log(share + 0.1 / self.n)
        return out


def _distances(a, b):
    return np.sqrt(np.maximum((a**2).sum(1)[:, None] + (b**2).sum(1) - 2 * a @ b.T, 0))


def _nearest(a, b, k, own=False, block=1024):
    """Distances and positions of the k nearest rows of b; own leaves out the row itself."""
    ds, ix = [], []
    for i in range(0, len(a), block):
        d = _distances(a[i : i + block], b)
        if own:
            d[np.arange(len(d)), np.arange(i, i + len(d))] = np.inf
        p = np.argpartition(d, min(k, d.shape[1]) - 1, axis=1)[:, :k]
        v = np.take_along_axis(d, p, 1)
        o = np.argsort(v, axis=1, kind="stable")
        ds.append(np.take_along_axis(v, o, 1))
        ix.append(np.take_along_axis(p, o, 1))
    return np.concatenate(ds), np.concatenate(ix)


class KNN(Base):
    k = 5

    def _fit(self, x):
        self.z = x

    def _score(self, x):
        return _nearest(x, self.z, min(self.k, len(self.z)))[0][:, -1]


class DTENP(KNN):
    """Diffusion time by neighbours: rises with the mean squared distance to the nearest rows."""

    def _score(self, x):
        return (_nearest(x, self.z, min(self.k, len(self.z)))[0] ** 2).mean(axis=1)


class LOF(Base):
    def __init__(self, seed=0, k=20):
        super().__init__(seed)
        self.k = k

    def _fit(self, x):
        self.z = x
        k = self.kk = max(1, min(self.k, len(x) - 1))
        d, i = _nearest(x, x, k, own=True)
        self.kd = d[:, -1]
        self.lrd = 1 / np.maximum(np.maximum(d, self.kd[i]).mean(axis=1), 1e-10)

    def _score(self, x):
        d, i = _nearest(x, self.z, self.kk)
        lrd = 1 / np.maximum(np.maximum(d, self.kd[i]).mean(axis=1), 1e-10)
        return self.lrd[i].mean(axis=1) / lrd


class FeatureBagging(Base):
    def _fit(self, x):
        d, g = x.shape[1], rng(self.seed, "bagging")
        self.sets = [np.sort(g.permutation(d)[: g.integers(max(1, d // 2), max(2, d))]) for _ in range(10)]
        self.lofs = [LOF(self.seed) for _ in self.sets]
        for m, c in zip(self.lofs, self.sets, strict=True):
            m._fit(x[:, c])

    def _score(self, x):
        return np.mean([m._score(x[:, c]) for m, c in zip(self.lofs, self.sets, strict=True)], axis=0)


class PCA(Base):
    def _fit(self, x):
        self.fit_covariance(np.cov(x.T, bias=True).reshape(x.shape[1], -1))

    def fit_covariance(self, c: np.ndarray):
        w, self.v = np.linalg.eigh(c)
        self.w = np.maximum(w, 1e-8)

    def _score(self, x):
        return ((x @ self.v) ** 2 / self.w).sum(axis=1)


class MCD(Base):
    def _fit(self, x):
        h = max(x.shape[1] + 1, (len(x) + x.shape[1] + 1) // 2)
        rows = np.argsort(((x - np.median(x, axis=0)) ** 2).sum(1), kind="stable")[:h]
        for _ in range(30):
            self.mu, c = x[rows].mean(axis=0), np.cov(x[rows].T, bias=True).reshape(x.shape[1], -1)
            self.inv = np.linalg.pinv(c + 1e-9 * np.eye(len(c)))
            new = np.argsort(self._score(x), kind="stable")[:h]
            if set(new) == set(rows):
                break
            rows = new

    def _score(self, x):
        d = x - self.mu
        return np.einsum("ij,jk,ik->i", d, self.inv, d)


def _c(n):
    return 2 * (np.log(n - 1) + 0.5772156649) - 2 * (n - 1) / n if n > 2 else float(n == 2)


class IForest(Base):
    def __init__(self, seed=0, trees=100, rows=256):
        super().__init__(seed)
        self.trees, self.rows = trees, rows

    def _fit(self, x):
        g = rng(self.seed, "iforest")
        m = min(self.rows, len(x))
        self.norm, limit = _c(m), int(np.ceil(np.log2(max(2, m))))

        def grow(z, depth):
            spread = np.flatnonzero(z.max(axis=0) > z.min(axis=0)) if len(z) > 1 else []
            if depth >= limit or not len(spread):
                return depth + _c(len(z))
            j = int(g.choice(spread))
            cut = g.uniform(z[:, j].min(), z[:, j].max())
            return j, cut, grow(z[z[:, j] <= cut], depth + 1), grow(z[z[:, j] > cut], depth + 1)

        self.forest = [grow(x[g.permutation(len(x))[:m]], 0) for _ in range(self.trees)]

    def _score(self, x):
        def depth(node, rows, out):
            if not isinstance(node, tuple):
                out[rows] += node
            elif rows.size:
                go = x[rows, node[0]] <= node[1]
                depth(node[2], rows[go], out)
                depth(node[3], rows[~go], out)

        out = np.zeros(len(x))
        for t in self.forest:
            depth(t, np.arange(len(x)), out)
        return 2.0 ** (-out / len(self.forest) / max(self.norm, 1e-9))


class DIF(Base):
    """Isolation trees on the outputs of random networks."""

    def _fit(self, x):
        g = rng(self.seed, "dif")
        self.nets = [(g.normal(size=(x.shape[1], 32)) / np.sqrt(x.shape[1]), g.normal(size=(32, 8)) / np.sqrt(32)) for _ in range(6)]
        self.parts = [IForest(self.seed + i, 50) for i in range(6)]
        for f, (a, b) in zip(self.parts, self.nets, strict=True):
            f._fit(np.tanh(np.tanh(x @ a) @ b))

    def _score(self, x):
        return np.mean([f._score(np.tanh(np.tanh(x @ a) @ b)) for f, (a, b) in zip(self.parts, self.nets, strict=True)], axis=0)


class LODA(Base):
    def _fit(self, x):
        g, d = rng(self.seed, "loda"), x.shape[1]
        k = max(1, round(np.sqrt(d)))
        self.w = np.zeros((100, d))
        for r in self.w:
            r[g.permutation(d)[:k]] = g.standard_normal(k)
        z = x @ self.w.T
        self.h = [HBOS() for _ in range(100)]
        for j, h in enumerate(self.h):
            h._fit(z[:, j : j + 1])

    def _score(self, x):
        z = x @ self.w.T
        return np.mean([h._score(z[:, j : j + 1]) for j, h in enumerate(self.h)], axis=0)


class OCSVM(Base):
    """One-class boundary over random Fourier features, by stochastic subgradients."""

    def _fit(self, x):
        g, d = rng(self.seed, "ocsvm"), x.shape[1]
        self.a, self.b = g.standard_normal((d, 256)) * np.sqrt(2 / d), g.uniform(0, 2 * np.pi, 256)
        z = self._phi(x)
        w, r, nu = z.mean(axis=0), 0.0, 0.5
        for t in range(1, 301):
            m = z @ w
            r = np.quantile(m, nu)
            w = w - (1 / t) * (w - z[m < r].sum(axis=0) / (nu * len(z)))
        self.w = w

    def _phi(self, x):
        return np.sqrt(2 / 256) * np.cos(x @ self.a + self.b)

    def _score(self, x):
        return -(self._phi(x) @ self.w)


class KernelDensity(Base):
    """-log of the whole kernel mass: what the kernel backbone's floor alone can tell."""

    def _fit(self, x):
        from vtask.kernels.backbones import bandwidth

        self.z, self.h = x, bandwidth(x)

    def _score(self, x):
        out = []
        for i in range(0, len(x), 1024):
            out.append(-np.log(np.exp(-(_distances(x[i : i + 1024], self.z) ** 2) / self.h).sum(axis=1) + 1e-300))
        return np.concatenate(out) if out else np.zeros(0)


class _Net:
    """Dense tanh network with a linear end, trained by Adam."""

    def __init__(self, sizes, g, bias=True):
        self.w = [g.standard_normal((a, b)) / np.sqrt(a) for a, b in zip(sizes, sizes[1:], strict=False)]
        self.b = [np.zeros(b) for b in sizes[1:]]
        self.bias, self.t = bias, 0
        self.m = [np.zeros_like(p) for p in self.w + self.b]
        self.v = [np.zeros_like(p) for p in self.w + self.b]

    def __call__(self, x):
        self.a = [x]
        for i, (w, b) in enumerate(zip(self.w, self.b, strict=True)):
            x = x @ w + b
            if i < len(self.w) - 1:
                x = np.tanh(x)
            self.a.append(x)
        return x

    def back(self, grad, lr=3e-3):
        gw, gb = [], []
        for i in range(len(self.w) - 1, -1, -1):
            gw.insert(0, self.a[i].T @ grad)
            gb.insert(0, grad.sum(axis=0) * self.bias)
            grad = grad @ self.w[i].T
            if i:
                grad = grad * (1 - self.a[i] ** 2)
        self.t += 1
        for k, (p, g) in enumerate(zip(self.w + self.b, gw + gb, strict=True)):
            self.m[k] = 0.9 * self.m[k] + 0.1 * g
            self.v[k] = 0.999 * self.v[k] + 0.001 * g * g
            p -= lr * (self.m[k] / (1 - 0.9**self.t)) / (np.sqrt(self.v[k] / (1 - 0.999**self.t)) + 1e-8)
        return grad


def _batches(g, n, epochs, size=128):
    for _ in range(epochs):
        order = g.permutation(n)
        for i in range(0, n, size):
            yield order[i : i + size]


class VAE(Base):
    """Reconstruction error of a small variational autoencoder."""

    epochs = 60

    def _fit(self, x):
        g, d = rng(self.seed, "vae"), x.shape[1]
        k = self.k = max(2, d // 2)
        self.enc, self.dec = _Net([d, 32, 2 * k], g), _Net([k, 32, d], g)
        for rows in _batches(g, len(x), self.epochs):
            z = x[rows]
            h = self.enc(z)
            mu, ls = h[:, :k], np.clip(h[:, k:], -6, 3)
            e = g.standard_normal(mu.shape)
            out = self.dec(mu + np.exp(ls / 2) * e)
            gz = self.dec.back(2 * (out - z) / len(z))
            self.enc.back(np.concatenate([gz + 0.1 * mu / len(z), gz * e * np.exp(ls / 2) / 2 + 0.05 * (np.exp(ls) - 1) / len(z)], axis=1))

    def _score(self, x):
        return ((self.dec(self.enc(x)[:, : self.k]) - x) ** 2).sum(axis=1)


class DeepSVDD(Base):
    """Distance to the centre of a bias-free network's outputs."""

    def _fit(self, x):
        g = rng(self.seed, "svdd")
        self.net = _Net([x.shape[1], 32, 16], g, bias=False)
        self.centre = self.net(x).mean(axis=0)
        self.centre = np.where(np.abs(self.centre) < 0.1, 0.1, self.centre)
        for rows in _batches(g, len(x), 40):
            self.net.back(2 * (self.net(x[rows]) - self.centre) / len(rows), 1e-3)

    def _score(self, x):
        return ((self.net(x) - self.centre) ** 2).sum(axis=1)


class GOAD(Base):
    """How far each random affine view lies from its own class's centre among all classes' centres."""

    views = 16

    def _fit(self, x):
        g, d = rng(self.seed, "goad"), x.shape[1]
        self.a = g.standard_normal((self.views, d + 1, 16)) / np.sqrt(d + 1)
        x = np.pad(x, ((0, 0), (0, 1)), constant_values=1.0)  # the views are affine
        self.net = _Net([16, 32, 8], g)
        y = np.eye(self.views)
        for rows in _batches(g, len(x), 25, 64):
            z = np.concatenate([x[rows] @ a for a in self.a])
            own = np.repeat(np.arange(self.views), len(rows))
            h = self.net(z)
            c = np.stack([h[own == k].mean(axis=0) for k in range(self.views)])
            dist = ((h[:, None] - c) ** 2).sum(axis=2)
            p = np.exp(-(dist - dist.min(axis=1, keepdims=True)))
            p /= p.sum(axis=1, keepdims=True)
            self.net.back(2 * ((y[own] - p)[:, :, None] * (h[:, None] - c)).sum(axis=1) / len(z), 1e-3)
        self.c = np.stack([self.net(x @ a).mean(axis=0) for a in self.a])

    def _score(self, x):
        out, x = 0.0, np.pad(x, ((0, 0), (0, 1)), constant_values=1.0)
        for k, a in enumerate(self.a):
            d = ((self.net(x @ a)[:, None] - self.c) ** 2).sum(axis=2)
            out = out + d[:, k] + np.log(np.exp(-(d - d.min(axis=1, keepdims=True))).sum(axis=1)) - d.min(axis=1)
        return out


class PlanarFlow(Base):
    """-log likelihood under planar layers, trained by gradients of the exact change of variables."""

    layers = 4

    def _fit(self, x):
        g, d = rng(self.seed, "flow"), x.shape[1]
        self.p = [[g.standard_normal(d) * 0.1, g.standard_normal(d) * 0.1, 0.0] for _ in range(self.layers)]
        m = [[np.zeros(d), np.zeros(d), 0.0] for _ in self.p]
        for rows in _batches(g, len(x), 30, 256):
            z, keep = x[rows], []
            for w, u, b in self.p:
                t = np.tanh(z @ w + b)
                keep.append((z, t, np.maximum(1 + (1 - t**2) * (w @ u), 1e-3)))
                z = z + t[:, None] * u
            gz = z / len(rows)
            for i in range(self.layers - 1, -1, -1):
                w, u, b = self.p[i]
                zi, t, det = keep[i]
                s, wu, n = 1 - t**2, w @ u, len(rows)
                gt = gz @ u + (2 * t * wu / det) / n  # from the image, and from -log det
                gpre = gt * s
                gw = zi.T @ gpre - (s / det).mean() * u
                gu = gz.T @ t - (s / det).mean() * w
                gz = gz + gpre[:, None] * w
                for k, gr in enumerate((gw, gu, gpre.sum())):
                    m[i][k] = 0.9 * m[i][k] + gr
                    self.p[i][k] = self.p[i][k] - 0.003 * m[i][k]

    def _score(self, x):
        z, log = x, np.zeros(len(x))
        for w, u, b in self.p:
            t = np.tanh(z @ w + b)
            log += np.log(np.maximum(1 + (1 - t**2) * (w @ u), 1e-3))
            z = z + t[:, None] * u
        return (z**2).sum(axis=1) / 2 - log


class DAGMM(Base):
    """Energy of a Gaussian mixture over an autoencoder's code and its reconstruction error (fitted one after the other)."""

    def _fit(self, x):
        g, d = rng(self.seed, "dagmm"), x.shape[1]
        self.net = [_Net([d, 16, 2], g), _Net([2, 16, d], g)]
        for rows in _batches(g, len(x), 60):
            out = self.net[1](self.net[0](x[rows]))
            self.net[0].back(self.net[1].back(2 * (out - x[rows]) / len(rows)))
        z = self._code(x)
        r = g.dirichlet(np.ones(3), len(z))
        for _ in range(40):
            n = r.sum(axis=0) + 1e-6
            self.pi, self.mu = n / n.sum(), (r.T @ z) / n[:, None]
            self.cov = [((z - m).T * r[:, k]) @ (z - m) / n[k] + 1e-3 * np.eye(z.shape[1]) for k, m in enumerate(self.mu)]
            p = self._log(z)
            r = np.exp(p - p.max(axis=1, keepdims=True))
            r /= r.sum(axis=1, keepdims=True)

    def _code(self, x):
        h = self.net[0](x)
        e = ((self.net[1](h) - x) ** 2).sum(axis=1)
        return np.column_stack([h, np.log1p(e)])

    def _log(self, z):
        return np.stack([np.log(p) - 0.5 * (np.linalg.slogdet(c)[1] + np.einsum("ij,jk,ik->i", z - m, np.linalg.inv(c), z - m)) for p, m, c in zip(self.pi, self.mu, self.cov, strict=True)], axis=1)

    def _score(self, x):
        p = self._log(self._code(x))
        return -(p.max(axis=1) + np.log(np.exp(p - p.max(axis=1, keepdims=True)).sum(axis=1)))


METHODS = {
    "ecod": ECOD, "copod": COPOD, "hbos": HBOS, "knn": KNN, "lof": LOF, "feature_bagging": FeatureBagging, "dte_np": DTENP, "pca": PCA, "mcd": MCD, "iforest": IForest, "dif": DIF,
    "loda": LODA, "ocsvm": OCSVM, "kernel_density": KernelDensity, "vae": VAE, "deep_svdd": DeepSVDD, "goad": GOAD, "planar_flow": PlanarFlow, "dagmm": DAGMM,
}


def matrix(frame, fitted: list[np.ndarray] | None = None) -> tuple[np.ndarray, list[np.ndarray]]:
    """Numbers and one-hot categories of a kernels.table.Frame; the categories are those of the first call."""
    cats = fitted if fitted is not None else [np.unique(frame.c[:, j].astype(str)) for j in range(frame.c.shape[1])]
    hot = [(frame.c[:, j].astype(str)[:, None] == v).astype(float) for j, v in enumerate(cats)]
    return np.concatenate([frame.x, *hot], axis=1), cats


class ChainDensity:
    """Joint density by attribute-wise conditionals of the in-context backbone: -sum of log p(attribute | earlier ones)."""

    def __init__(self, backbone: str = "counts", bins: int = 10, seed: int = 0):
        self.backbone, self.bins, self.seed, self.calls = backbone, bins, seed, 0

    def _labels(self, f):
        from vtask.kernels.tasks import bins as bin_of

        num = [bin_of(f.x[:, j], e) for j, e in enumerate(self.edges)]
        cat = [np.array([m.get(v, -1) for v in f.c[:, j].astype(str).tolist()]) for j, m in enumerate(self.cats)]
        return [*num, *cat]

    def _before(self, f, j):
        from vtask.kernels.table import Frame

        a, b = min(j, f.x.shape[1]), max(0, j - f.x.shape[1])
        return Frame(f.x[:, :a], f.c[:, :b], f.num[:a], f.cat[:b])

    def fit(self, f):
        from vtask.kernels.backbones import make
        from vtask.kernels.tasks import borders

        self.edges = [borders(f.x[:, j], self.bins) for j in range(f.x.shape[1])]
        self.cats = [{v: i for i, v in enumerate(np.unique(f.c[:, j].astype(str)).tolist())} for j in range(f.c.shape[1])]
        y = self._labels(f)
        # the first attribute has nothing before it: its own frequencies
        self.models = [None] + [make(self.backbone).fit(self._before(f, j), y[j]) for j in range(1, len(y))]
        v, n = np.unique(y[0], return_counts=True)
        self.first = dict(zip(v.tolist(), ((n + 1) / (n.sum() + v.size + 1)).tolist(), strict=True)), 1 / (n.sum() + v.size + 1)
        return self

    def score(self, f):
        from vtask.kernels.backbones import support

        y = self._labels(f)
        out = -np.log([self.first[0].get(k, self.first[1]) for k in y[0].tolist()])
        for j in range(1, len(y)):
            out = out - np.log(support(self.models[j], self._before(f, j), y[j]))
            self.calls += 1
        return out
