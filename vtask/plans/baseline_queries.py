"""Baselines as Spark plans, with SQL twins."""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from vtask.operators import tasks as tk
from vtask.plans.queries import context, ctx, fx, query
from vtask.sources.fixtures import FIXTURES, fixture

_LN = list(FIXTURES["line_num"].num)
_PN = list(FIXTURES["part_dep"].num)
#: Context rows that a neighbour search holds, by the order of a draw: the published cap of a context.
NEIGHBOUR_CONTEXT = 100_000
#: Of the baselines fitted in one task, those whose fit is linear hold as many; the others, quadratic or trained, fewer.
CONTEXT = {"loda": 100_000, "mcd": 100_000, "iforest": 100_000}
DENSE_CONTEXT = 2000


def _tails(s, d) -> DataFrame:
    """(rid, attr, left, right): tail shares of each query value in the context, by one sort of distinct levels an attribute."""
    df = fixture(s, d, "line_num")
    long = df.select("rid", F.col("split"), F.explode(F.array(*(F.struct(F.lit(a).alias("attr"), F.round(a, 4).alias("v")) for a in _LN))).alias("x")).select("rid", "split", "x.*")
    lv = long.groupBy("attr", "v").agg(F.sum((F.col("split") == "context").cast("long")).alias("n"))
    upto = Window.partitionBy("attr").orderBy("v").rowsBetween(Window.unboundedPreceding, Window.currentRow)
    total = Window.partitionBy("attr")
    lv = lv.withColumns({"le": F.sum("n").over(upto), "t": F.sum("n").over(total)})
    lv = lv.select("attr", "v", (F.greatest(F.lit(1), F.col("le")) / (F.col("t") + 1)).alias("left"), (F.greatest(F.lit(1), F.col("t") - F.col("le") + F.col("n")) / (F.col("t") + 1)).alias("right"))
    return long.filter("split = 'query'").join(lv, ["attr", "v"]).select("rid", "attr", "left", "right")


_TAILS = f"""WITH a AS {fx('line_num')}, l AS ({' UNION ALL '.join(f"SELECT rid, split, '{a}' AS attr, round({a}, 4) AS v FROM a" for a in _LN)}),
    lv AS (SELECT attr, v, sum((split = 'context')::INT) AS n FROM l GROUP BY ALL), t AS (SELECT *, sum(n) OVER (PARTITION BY attr ORDER BY v) AS le, sum(n) OVER (PARTITION BY attr) AS t FROM lv),
    sk AS ({' UNION ALL '.join(f"SELECT '{a}' AS attr, sum(pow({a} - m, 3)) AS skew FROM a, (SELECT avg({a}) AS m FROM a WHERE split = 'context') WHERE split = 'context'" for a in _LN)}),
    p AS (SELECT rid, l.attr, -ln(greatest(1, le) / (t + 1.0)) AS lt, -ln(greatest(1, t - le + n) / (t + 1.0)) AS rt, skew FROM l JOIN t USING (attr, v) JOIN sk ON sk.attr = l.attr WHERE split = 'query')"""


def _tail_scores(s, d) -> DataFrame:
    c = context(s, d, "line_num")
    m = c.agg(*(F.avg(a).alias(a) for a in _LN)).first()
    skew = c.agg(*(F.sum(F.pow(F.col(a) - F.lit(m[a]), 3)).alias(a) for a in _LN)).first()
    left = F.create_map(*(F.lit(x) for a in _LN for x in (a, skew[a] < 0)))
    p = _tails(s, d).select("rid", (-F.log("left")).alias("lt"), (-F.log("right")).alias("rt"), F.element_at(left, F.col("attr")).alias("is_left"))
    auto = F.sum(F.when(F.col("is_left"), F.col("lt")).otherwise(F.col("rt")))
    return p.groupBy("rid").agg(F.sum("lt").alias("l"), F.sum("rt").alias("r"), auto.alias("a"))


query("ecod_line_num", f"{_TAILS} SELECT rid, round(greatest(sum(lt), sum(rt), sum(CASE WHEN skew < 0 THEN lt ELSE rt END)), 6) AS score FROM p GROUP BY rid")(lambda s, d: _tail_scores(s, d).select("rid", F.round(F.greatest("l", "r", "a"), 6).alias("score")))
query("copod_line_num", f"{_TAILS} SELECT rid, round(greatest((sum(lt) + sum(rt)) / 2, sum(CASE WHEN skew < 0 THEN lt ELSE rt END)), 6) AS score FROM p GROUP BY rid")(
    lambda s, d: _tail_scores(s, d).select("rid", F.round(F.greatest((F.col("l") + F.col("r")) / 2, F.col("a")), 6).alias("score"))
)


def _bin(v: str, lo: str, hi: str) -> str:
    return f"CASE WHEN {v} < {lo} OR {v} > {hi} THEN -1 ELSE least(9, floor(({v} - {lo}) / ({hi} - {lo}) * 10)) END"


@query(
    "hbos_line_num",
    f"WITH a AS {fx('line_num')}, r AS (SELECT count(*) AS n, {', '.join(f'min({a}) AS lo_{a}, max({a}) AS hi_{a}' for a in _LN)} FROM a WHERE split = 'context'), "
    + ", ".join(f"h_{a} AS (SELECT {_bin(a, f'lo_{a}', f'hi_{a}')} AS b, count(*) AS k FROM a, r WHERE split = 'context' GROUP BY 1)" for a in _LN)
    + " SELECT a.rid, round(" + " + ".join(f"-ln(coalesce(h_{a}.k, 0) / r.n + 0.1 / r.n)" for a in _LN) + ", 6) AS score FROM a CROSS JOIN r "
    + " ".join(f"LEFT JOIN h_{a} ON h_{a}.b = {_bin('a.' + a, f'r.lo_{a}', f'r.hi_{a}')}" for a in _LN) + " WHERE a.split = 'query'",
)
def hbos(s, d):
    """Ten bins an attribute: forty counts come to the driver and go back as literals."""
    df = fixture(s, d, "line_num")
    c = df.filter("split = 'context'")
    r = c.agg(F.count("*").alias("n"), *(f(a).alias(f"{k}_{a}") for a in _LN for k, f in (("lo", F.min), ("hi", F.max)))).first()

    def b(a):
        v, lo, hi = F.col(a), F.lit(r[f"lo_{a}"]), F.lit(r[f"hi_{a}"])
        return F.when((v < lo) | (v > hi), F.lit(-1)).otherwise(F.least(F.lit(9), F.floor((v - lo) / (hi - lo) * 10))).cast("int")

    n = {(x.attr, x.b): x.k for x in c.select(F.explode(F.array(*(F.struct(F.lit(a).alias("attr"), b(a).alias("b")) for a in _LN))).alias("x")).groupBy("x.attr", "x.b").agg(F.count("*").alias("k")).collect()}
    out = None
    for a in _LN:
        m = F.create_map(*(F.lit(x) for (at, k), v in sorted(n.items()) if at == a for x in (k, float(v))))
        t = -F.log(F.coalesce(F.element_at(m, b(a)), F.lit(0.0)) / F.lit(float(r.n)) + F.lit(0.1) / F.lit(float(r.n)))
        out = t if out is None else out + t
    return df.filter("split = 'query'").select("rid", F.round(out, 6).alias("score"))


_Z = f"""WITH a AS {fx('part_dep')}, m AS (SELECT {', '.join(f'avg({a}) AS m_{a}, stddev_pop({a}) AS s_{a}' for a in _PN)} FROM a WHERE split = 'context'),
    z AS (SELECT rid, split, {', '.join(f'({a} - m_{a}) / s_{a} AS {a}' for a in _PN)} FROM a, m), c AS (SELECT * FROM z WHERE split = 'context' ORDER BY U['0';'ctx';rid], rid LIMIT {NEIGHBOUR_CONTEXT})"""
_D2 = " + ".join(f"pow(q.{a} - c.{a}, 2)" for a in _PN)
_NN = f"{_Z}, dd AS (SELECT q.rid, {_D2} AS d2, row_number() OVER (PARTITION BY q.rid ORDER BY {_D2}, c.rid) AS k FROM z AS q, c WHERE q.split = 'query')"


def _neighbours(s, d, score, name: str = "part_dep") -> DataFrame:
    """Arrow map over the queries against a bounded context that goes out with the function."""
    df = fixture(s, d, name)
    c = df.filter("split = 'context'")
    st = c.agg(*(f(a).alias(f"{k}_{a}") for a in _PN for k, f in (("m", F.avg), ("s", F.stddev_pop)))).first()
    z = [((F.col(a) - F.lit(st[f"m_{a}"])) / F.lit(st[f"s_{a}"])).alias(a) for a in _PN]
    ctx_rows = c.orderBy(tk.u01(0, "ctx", F.col("rid")), "rid").limit(NEIGHBOUR_CONTEXT).select(*z).toPandas().to_numpy(float)

    block = max(1, (1 << 22) // max(1, len(ctx_rows)))  # queries at a time

    def run(batches):
        for b in batches:
            q, out = b[_PN].to_numpy(float), []
            for i in range(0, len(q), block):
                d2 = sum((q[i : i + block, None, j] - ctx_rows[None, :, j]) ** 2 for j in range(len(_PN)))
                out.append(score(d2))
            yield pd.DataFrame({"rid": b["rid"], "score": np.round(np.concatenate(out), 6)})

    return df.filter("split = 'query'").select("rid", *z).mapInPandas(run, "rid string, score double")


query("knn_part", f"{_NN} SELECT rid, round(sqrt(d2), 6) AS score FROM dd WHERE k = 5")(lambda s, d: _neighbours(s, d, lambda d2: np.sqrt(np.partition(d2, 4, axis=1)[:, 4])))
query("dte_np_part", f"{_NN} SELECT rid, round(avg(d2), 6) AS score FROM dd WHERE k <= 5 GROUP BY rid")(lambda s, d: _neighbours(s, d, lambda d2: np.partition(d2, 4, axis=1)[:, :5].mean(axis=1)))


@query(
    "kernel_density_part",
    f"{_Z} SELECT q.rid, round(-ln(sum(exp(-({_D2}))) + 1e-300), 6) AS score FROM z AS q, c WHERE q.split = 'query' GROUP BY q.rid",
)
def kernel_density(s, d):
    return _neighbours(s, d, lambda d2: -np.log(np.exp(-d2).sum(axis=1) + 1e-300))


def _dense(name: str, fixture_name: str):
    """A kernels.baselines method: fitted on the bounded context in one task, scored as an Arrow map."""

    def run(s, d):
        from vtask.kernels.baselines import METHODS

        f = FIXTURES[fixture_name]
        df = fixture(s, d, fixture_name)
        cols = list(f.num)
        x = df.filter("split = 'context'").orderBy(tk.u01(0, "ctx", F.col("rid")), "rid").limit(CONTEXT.get(name, DENSE_CONTEXT)).select(*cols).toPandas().to_numpy(float)
        m = METHODS[name]().fit(x)

        def score(batches):
            for b in batches:
                yield pd.DataFrame({"rid": b["rid"], "score": np.round(m.score(b[cols].to_numpy(float)), 4)})

        return df.filter("split = 'query'").select("rid", *cols).mapInPandas(score, "rid string, score double")

    return run


for _m, _f in (
    ("lof", "part_dep"), ("loda", "line_num"), ("mcd", "line_num"), ("iforest", "line_num"), ("feature_bagging", "part_dep"), ("ocsvm", "part_dep"),
    ("dif", "part_dep"), ("vae", "part_dep"), ("deep_svdd", "part_dep"), ("goad", "part_dep"), ("planar_flow", "part_dep"), ("dagmm", "part_dep"),
):
    query(f"{_m}_{_f}")(_dense(_m, _f))


@query("pca_line_num")
def pca(s, d):
    """kernels.baselines.PCA on the whole context: moments and covariances of all its rows by two aggregations."""
    from vtask.kernels.baselines import PCA

    df = fixture(s, d, "line_num")
    c = df.filter("split = 'context'")
    st = c.agg(*(f(a).alias(f"{k}_{a}") for a in _LN for k, f in (("m", F.avg), ("s", F.stddev_pop)))).first()
    m = PCA()
    m.mid, sd = (np.array([st[f"{k}_{a}"] for a in _LN], float) for k in "ms")
    m.sd = np.where(sd > 0, sd, 1.0)
    z = {a: (F.col(a) - F.lit(float(mid))) / F.lit(float(w)) for a, mid, w in zip(_LN, m.mid, m.sd, strict=True)}
    cov = c.agg(*(F.avg(z[a] * z[b]).alias(f"{a}_{b}") for a in _LN for b in _LN)).first()
    m.fit_covariance(np.array(cov, float).reshape(len(_LN), -1))

    def score(batches):
        for b in batches:
            yield pd.DataFrame({"rid": b["rid"], "score": np.round(m.score(b[_LN].to_numpy(float)), 4)})

    return df.filter("split = 'query'").select("rid", *_LN).mapInPandas(score, "rid string, score double")


@query("chain_density_line_cat")
def chain_density(s, d):
    """Attribute-wise conditionals by the count backbone: d supports a row against the method's one a kept task."""
    from vtask.operators import scoring as sc

    df = fixture(s, d, "line_cat")
    c = df.filter("split = 'context'")
    cat = list(FIXTURES["line_cat"].cat)
    out = F.lit(0.0)
    for j, a in enumerate(cat):
        view = tk.token_view({}, cat[:j])
        out = out - F.log(sc.counts_support(sc.fit_counts(c, F.col(a), view), F.col(a), view))
    return df.filter("split = 'query'").select("rid", F.round(out, 4).alias("score"))
