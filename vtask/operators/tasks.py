"""Virtual-task labels as map-only Spark expressions.

Fitting is a few aggregations whose results are as small as the schema (borders,
medians, counts of at most a few dozen tokens an attribute); labelling is a
projection with these as literals, so it never shuffles, whatever the table.
With approx=True quantiles come from Spark's mergeable sketch instead of
sorting.
"""

from __future__ import annotations

import math
from dataclasses import dataclass

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from vtask.kernels.draws import normals

ALPHA = 1.0
#: A categorical attribute has few values by the type rule; more than this is not one.
MAX_TOKENS = 10_000


#: A sketch of this accuracy errs by one in so many ranks; brackets reach twice as far on either side.
_ACCURACY = 10_000


def _quantiles(df: DataFrame, exprs: dict[str, Column], ps: list[float], approx: bool) -> dict[str, list[float]]:
    if not exprs:
        return {}
    if not approx:
        return _exact_quantiles(df, exprs, ps)
    row = df.agg(*(F.percentile_approx(c, ps, _ACCURACY).alias(a) for a, c in exprs.items())).first()
    return {a: list(row[a] or []) for a in exprs}


def _exact_quantiles(df: DataFrame, exprs: dict[str, Column], ps: list[float]) -> dict[str, list[float]]:
    """What Spark's percentile gives, bit for bit, in two passes of bounded memory whatever the number of distinct values.

    A sketch brackets each quantile; the second pass counts the values between
    brackets and keeps those within, by value. A rank that a bracket misses shows
    in these counts and is searched again among all values.
    """
    names = list(exprs)
    x = [exprs[a].cast("double") for a in names]
    near = sorted({min(1.0, max(0.0, p + s * 2 / _ACCURACY)) for p in ps for s in (-1, 1)})
    row = df.agg(*(F.struct(F.count(c).alias("n"), F.percentile_approx(c, near, _ACCURACY).alias("q")).alias(f"s{i}") for i, c in enumerate(x))).first()
    n = [row[i].n for i in range(len(names))]
    at = [[p * (k - 1) for p in ps] if k else [] for k in n]
    ranks = [sorted({r for v in pos for r in (math.floor(v), math.ceil(v))}) for pos in at]
    brackets: list[list[tuple]] = []
    for i in range(len(names)):
        cut = dict(zip(near, row[i].q or [], strict=bool(n[i])))
        ends: list[tuple] = []
        for p in sorted(ps) if n[i] else []:
            lo, hi = (cut[min(1.0, max(0.0, p + s * 2 / _ACCURACY))] for s in (-1, 1))
            if ends and not lo > ends[-1][1]:  # brackets that touch are one
                lo, hi = ends.pop()[0], hi
            ends.append((lo, hi))
        brackets.append(ends)
    got: list[dict[int, float]] = [{} for _ in names]
    while todo := [i for i in range(len(names)) if len(got[i]) < len(ranks[i])]:
        for i, r, v in _values_at(df, [(i, x[i], brackets[i], ranks[i]) for i in todo]):
            got[i][r] = v
        for i in todo:
            brackets[i] = [(None, None)]
    out = {}
    for a, pos, v in zip(names, at, got, strict=True):
        out[a] = []
        for p in pos:
            lo, hi = math.floor(p), math.ceil(p)
            out[a].append(v[lo] if v[lo] == v[hi] else (hi - p) * v[lo] + (p - lo) * v[hi])
    return out


def _values_at(df: DataFrame, wanted: list[tuple]) -> list[tuple[int, int, float]]:
    """(i, rank, value) for each (i, column, brackets, ranks from 0), without ranks outside the brackets; an unbounded bracket has them all."""

    def place(c, ends):
        """Cells in order: an odd one is a bracket, an even one lies before it."""
        steps = [(F.lit(True) if lo is None else c >= F.lit(lo)).cast("int") for lo, _ in ends] + [(c > F.lit(hi)).cast("int") for _, hi in ends if hi is not None]
        cell = total(steps)
        return cell, F.when(cell % 2 == 1, c)

    cells = []
    for i, c, ends, _ in wanted:
        cell, v = place(c, ends)
        cells.append(F.when(c.isNotNull(), F.struct(F.lit(i).alias("i"), cell.alias("cell"), v.alias("v"))))
    few = df.select(F.explode(F.array(*cells)).alias("t")).filter("t IS NOT NULL").groupBy("t.i", "t.cell", "t.v").agg(F.count("*").alias("n"))
    upto = few.withColumn("upto", F.sum("n").over(Window.partitionBy("i").orderBy("cell", "v").rowsBetween(Window.unboundedPreceding, 0)))
    first = F.col("upto") - F.col("n")
    asked = F.element_at(F.create_map(*(y for i, _, _, ranks in wanted for y in (F.lit(i), F.array(*(F.lit(r).cast("long") for r in ranks))))), F.col("i"))
    rows = upto.filter("cell % 2 = 1").select("i", "v", F.filter(asked, lambda r: (r >= first) & (r < F.col("upto"))).alias("r")).filter(F.size("r") > 0)
    return [(t.i, r, t.v) for t in rows.collect() for r in t.r]


def fit_borders(df: DataFrame, exprs: dict[str, Column], k: int, approx: bool = False) -> dict[str, list[float]]:
    """Inner quantiles of each expression, equal ones merged; one aggregation for all."""
    return {a: sorted(set(q)) for a, q in _quantiles(df, exprs, [i / k for i in range(1, k)], approx).items()}


def qbin(z: Column, borders: list[float]) -> Column:
    """Number of borders strictly below z."""
    out = F.lit(0)
    for b in borders:
        out = out + (z > F.lit(float(b))).cast("int")
    return out


@dataclass(frozen=True)
class Robust:
    mid: dict[str, float]
    width: dict[str, float]

    def __call__(self, a: str) -> Column:
        return (F.col(a) - F.lit(self.mid[a])) / F.lit(self.width[a])


def fit_robust(df: DataFrame, attrs: list[str], approx: bool = False) -> Robust:
    q = _quantiles(df, {a: F.col(a) for a in attrs}, [0.25, 0.5, 0.75], approx)
    flat = [a for a in attrs if q[a][2] == q[a][0]]  # only these need a pass for their deviation
    sd = df.agg(*(F.stddev_pop(a).alias(a) for a in flat)).first() if flat else {}
    return Robust({a: q[a][1] for a in attrs}, {a: (q[a][2] - q[a][0]) or sd[a] or 1.0 for a in attrs})


def raw(attrs: list[str]) -> Robust:
    return Robust(dict.fromkeys(attrs, 0.0), dict.fromkeys(attrs, 1.0))


def total(terms: list[Column]) -> Column:
    out = terms[0]
    for t in terms[1:]:
        out = out + t
    return out


def projection(t: Robust, attrs: list[str], weights: list[float]) -> Column:
    return F.round(total([t(a) * F.lit(float(w)) for a, w in zip(attrs, weights, strict=True)]), 6)


def radius(t: Robust, attrs: list[str]) -> Column:
    return F.round(F.sqrt(total([t(a) * t(a) for a in attrs])), 6)


def numeric_tokens(edges: dict[str, list[float]]) -> dict[str, Column]:
    return {a: F.concat(F.lit("q"), qbin(F.col(a), b).cast("string")) for a, b in edges.items()}


def token_view(num_edges: dict[str, list[float]], cat: list[str]) -> dict[str, Column]:
    """Quantile tokens of numbers and categories as they are, a null being a token of its own."""
    return {**numeric_tokens(num_edges), **{a: F.coalesce(F.col(a), F.lit("\x00null")) for a in cat}}


def token_counts(df: DataFrame, view: dict[str, Column]) -> DataFrame:
    """(attr, tok, n): one explode and one partial aggregation."""
    toks = F.array(*(F.struct(F.lit(a).alias("attr"), c.alias("tok")) for a, c in view.items()))
    return df.select(F.explode(toks).alias("t")).groupBy("t.attr", "t.tok").agg(F.count("*").alias("n"))


@dataclass(frozen=True)
class TokenModel:
    n: int
    counts: dict[str, dict[str, int]]

    @classmethod
    def fit(cls, df: DataFrame, view: dict[str, Column]) -> TokenModel:
        rows = token_counts(df, view).limit(MAX_TOKENS + 1).collect()
        if len(rows) > MAX_TOKENS:
            raise ValueError(f"more than {MAX_TOKENS} tokens: not categorical by the type rule")
        counts: dict[str, dict[str, int]] = {a: {} for a in view}
        for r in rows:
            counts[r.attr][r.tok] = r.n
        return cls(sum(next(iter(counts.values())).values()) if counts else 0, counts)

    def _lookup(self, a: str, tok: Column, values: dict[str, float], other: float) -> Column:
        if not values:
            return F.lit(other)
        m = F.create_map(*(F.lit(x) for kv in sorted(values.items()) for x in kv))
        return F.coalesce(F.element_at(m, tok), F.lit(other))

    def prob(self, a: str, tok: Column) -> Column:
        """Smoothed probability; also of a token that the context lacks."""
        return (self._lookup(a, tok, {v: float(c) for v, c in self.counts[a].items()}, 0.0) + ALPHA) / F.lit(self.n + ALPHA * (len(self.counts[a]) + 1))

    def rarity(self, a: str, tok: Column) -> Column:
        return -F.log(self.prob(a, tok))

    def _sum(self, view: dict[str, Column], weight=lambda key: 1.0, weight_of=lambda key: F.lit(1.0)) -> Column:
        """Sum over a row's tokens of rarity times weight, in one small expression: known tokens by a literal map, new ones by weight_of their key."""
        # a token is named by its attribute's place in the view, as in kernels.tasks
        known = {f"{j}|{v}": math.log((self.n + ALPHA * (len(self.counts[a]) + 1)) / (k + ALPHA)) for j, a in enumerate(view) for v, k in self.counts[a].items()}
        values = F.create_map(*(F.lit(x) for k, r in sorted(known.items()) for x in (k, r * weight(k)))) if known else None
        new = {a: math.log((self.n + ALPHA * (len(self.counts[a]) + 1)) / ALPHA) for a in view}
        each = F.array(*(F.struct(F.concat(F.lit(f"{j}|"), c).alias("key"), F.lit(new[a]).alias("new")) for j, (a, c) in enumerate(view.items())))

        def term(x):
            other = x["new"] * weight_of(x["key"])
            return F.coalesce(F.element_at(values, x["key"]), other) if known else other

        return F.aggregate(each, F.lit(0.0), lambda s, x: s + term(x))

    def projected(self, seed: int, purpose: str, view: dict[str, Column]) -> Column:
        """Sum of rarities times the tokens' fixed random weights, by Box-Muller on two hashed uniforms each."""

        def weight_of(key):
            u = [u01(seed, f"{purpose}.{k}", key) for k in "ab"]
            return F.sqrt(F.lit(-2.0) * F.log(F.lit(1.0) - u[0])) * F.cos(F.lit(6.283185307179586) * u[1])

        return F.round(self._sum(view, lambda k: float(normals(seed, purpose, [k])[0]), weight_of) / F.lit(float(len(view)) ** 0.5), 6)

    def mean_rarity(self, view: dict[str, Column]) -> Column:
        return F.round(self._sum(view) / F.lit(float(len(view))), 6)


def u01(seed: int, purpose: str, key: Column) -> Column:
    """Stateless uniform of kernels.draws as an expression."""
    digest = F.md5(F.concat_ws("|", F.lit(str(seed)), F.lit(purpose), key).cast("binary"))
    return F.conv(F.substring(digest, 1, 13), 16, 10).cast("double") / F.lit(float(16**13))


def weights(seed: int, task: str, attrs: list[str]) -> list[float]:
    """Fixed projection weights, rounded so that every engine reads the same numbers."""
    return [round(float(w), 6) for w in normals(seed, f"weight.{task}", attrs)]


# --- prototypes


def nearest(distances: list[Column]) -> Column:
    """Index of the smallest distance, the lowest of equal ones."""
    d = F.array(*distances)
    return (F.array_position(d, F.array_min(d)) - 1).cast("int")


def assign_kmeans(t: Robust, attrs: list[str], centres: list[list[float]]) -> Column:
    """Index of the smallest distance rounded to six places; only distances that rounding can make equal are rounded, as it is slow."""
    d = [total([(t(a) - F.lit(float(m))) * (t(a) - F.lit(float(m))) for a, m in zip(attrs, c, strict=True)]) for c in centres]
    rounded = nearest([F.round(x, 6) for x in d])
    if len(d) == 1:
        return rounded
    close = [x <= F.least(*d) + F.lit(2e-6) for x in d]
    alone = total([x.cast("int") for x in close]) == 1
    return F.when(alone, total([x.cast("int") * i for i, x in enumerate(close)])).otherwise(rounded)


def assign_kmodes(attrs: list[str], modes: list[list[str]]) -> Column:
    return nearest([total([(F.coalesce(F.col(a), F.lit("\x00null")) != F.lit(v)).cast("double") for a, v in zip(attrs, m, strict=True)]) for m in modes])


def assign_kproto(codes: dict[str, Column], cat: list[str], protos: list[tuple[list[float], list[str]]]) -> Column:
    """Mean squared code gap plus mean mismatch."""
    out = []
    for c, m in protos:
        gap = total([(x - F.lit(float(v))) * (x - F.lit(float(v))) for x, v in zip(codes.values(), c, strict=True)]) / F.lit(float(len(codes)))
        miss = total([(F.coalesce(F.col(a), F.lit("\x00null")) != F.lit(v)).cast("double") for a, v in zip(cat, m, strict=True)]) / F.lit(float(len(cat)))
        out.append(F.round(gap + miss, 6))
    return nearest(out)


def update_modes(df: DataFrame, cluster: Column, attrs: list[str]) -> DataFrame:
    """(cluster, attr, mode): most frequent value, the smallest of equal ones; partial counts before the shuffle."""
    toks = F.array(*(F.struct(F.lit(a).alias("attr"), F.coalesce(F.col(a), F.lit("\x00null")).alias("tok")) for a in attrs))
    n = df.select(cluster.alias("cluster"), F.explode(toks).alias("t")).groupBy("cluster", "t.attr", "t.tok").agg(F.count("*").alias("n"))
    # the largest count, then the smallest token: the least pair of (-count, token)
    return n.groupBy("cluster", "attr").agg(F.min(F.struct((-F.col("n")).alias("k"), "tok")).alias("m")).select("cluster", "attr", F.col("m.tok").alias("mode"))


def fit_kmeans(df: DataFrame, t: Robust, attrs: list[str], k: int, rounds: int = 20) -> list[list[float]]:
    """Lloyd rounds from a deterministic farthest-first start; each is one aggregation of k * d sums."""
    key = F.md5(F.concat_ws("|", *(F.round(t(a), 6).cast("string") for a in attrs)).cast("binary"))
    z = [F.round(t(a), 6).alias(a) for a in attrs]
    first = df.select(*z, key.alias("key")).orderBy("key", *attrs).limit(1).first()
    centres = [[first[a] for a in attrs]] if first else []
    while first and len(centres) < k:
        d = F.least(*(total([(t(a) - F.lit(m)) * (t(a) - F.lit(m)) for a, m in zip(attrs, c, strict=True)]) for c in centres + centres[:1]))
        top = df.agg(F.max(d)).first()[0]  # names and sorts only the farthest rows
        far = df.filter(d.eqNullSafe(F.lit(top).cast("double"))).select(*z, key.alias("key")).orderBy("key").limit(1).first()
        centres.append([far[a] for a in attrs])
    for _ in range(rounds if first else 0):
        y = assign_kmeans(t, attrs, centres)
        rows = df.groupBy(y.alias("k")).agg(*(F.avg(t(a)).alias(a) for a in attrs)).collect()
        new = [list(c) for c in centres]
        for r in rows:
            new[r.k] = [round(r[a], 6) for a in attrs]
        if new == centres:
            break
        centres = new
    return centres


def fit_kmodes(df: DataFrame, attrs: list[str], k: int, rounds: int = 20) -> list[list[str]]:
    """Alternating assignment and modal update, from the rows of smallest hash that differ."""
    key = F.md5(F.concat_ws("|", *attrs).cast("binary"))
    rows = df.select(*(F.coalesce(F.col(a), F.lit("\x00null")).alias(a) for a in attrs)).distinct().orderBy(key).limit(k).collect()
    modes = [[r[a] for a in attrs] for r in rows]
    for _ in range(rounds if modes else 0):
        got = update_modes(df, assign_kmodes(attrs, modes), attrs).collect()
        new = [list(m) for m in modes]
        for r in got:
            new[r.cluster][attrs.index(r.attr)] = r.mode
        if new == modes:
            break
        modes = new
    return modes
