"""The experiments on the given tables: suites, planting, contamination, budgets, ablations, calibration.

Many small datasets run as one grouped map, a dataset and seed a task; one large
dataset runs as a map over its rows against a fitted detector whose size is
bounded by its context. Both use the same kernels, so they agree.
"""

from __future__ import annotations

import itertools
import json

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from vtask.kernels import baselines as bl
from vtask.kernels import detector as det
from vtask.kernels import selection as sel
from vtask.kernels.draws import rng, uniforms
from vtask.operators import tasks as tk
from vtask.plans.queries import fx, query
from vtask.sources.fixtures import FIXTURES, fixture

#: Rows of a dataset in the suite, in the ratio of its two sides; the published experiments cap at 100,000.
SUITE_CAP = 1500
DEV = [n for n, f in FIXTURES.items() if f.side == "dev" and n not in ("supp_small", "event_err", "user_profile")]
EVAL = [n for n, f in FIXTURES.items() if f.side == "eval"]
OVERALL_SEEDS = (0, 1, 2, 3, 4)
MECHANISMS = ("law_break", "scale_out", "tight_blob", "rare_combo", "all_shuffle")


def plant(pdf: pd.DataFrame, num: list[str], cat: list[str], mechanism: str, seed: int) -> pd.DataFrame:
    """Query rows marked as anomalies, changed by one mechanism; the pool they draw from is the context."""
    out, c = pdf.copy(), pdf[pdf["split"] == "context"]
    rows = np.flatnonzero(((pdf["split"] == "query") & (pdf["is_anom"] == 1)).to_numpy())
    g = rng(seed, f"plant.{mechanism}")
    if not len(rows) or not len(c):
        return out
    if mechanism == "law_break" and num:
        a = num[-1]
        out[a] = out[a].astype(float)
        edges = np.quantile(c[a].astype(float), np.arange(1, 10) / 10)
        bin_c, pool = np.searchsorted(edges, c[a].astype(float)), c[a].astype(float).to_numpy()
        for r in rows:
            own = pool[bin_c == np.searchsorted(edges, float(pdf[a].iloc[r]))]
            out.iloc[r, out.columns.get_loc(a)] = g.choice(own if own.size else pool)
    elif mechanism in ("scale_out", "tight_blob") and num:
        q = {a: np.quantile(c[a].astype(float), [0.25, 0.75, 1.0]) for a in num}
        for a in num:
            out[a] = out[a].astype(float)
        for r in rows:
            some = g.permutation(num)[: g.integers(1, min(3, len(num)) + 1)] if mechanism == "scale_out" else num
            for a in some:
                iqr = q[a][1] - q[a][0]
                v = float(pdf[a].iloc[r]) + g.choice([-1, 1]) * g.uniform(2, 4) * iqr if mechanism == "scale_out" else q[a][2] + iqr + 0.01 * iqr * g.standard_normal()
                out.iloc[r, out.columns.get_loc(a)] = v
    elif mechanism == "rare_combo" and cat:
        for a in cat[:2]:
            out.iloc[rows, out.columns.get_loc(a)] = "never seen"
    else:
        for a in [*num, *cat]:
            out.iloc[rows, out.columns.get_loc(a)] = c[a].to_numpy()[g.integers(0, len(c), len(rows))]
    return out


def _frame(s, d, name: str, cap: int = SUITE_CAP) -> DataFrame:
    """A fixture as (dataset, rid, split, is_anom, row as JSON), the `cap` rows of smallest draw in each side's ratio."""
    f = FIXTURES[name]
    df = fixture(s, d, name).withColumn("u", tk.u01(0, "cap", F.col("rid")))
    n = df.count()
    if n > cap:
        df = df.filter(F.col("u") < cap / n)  # a threshold on the draw: stratified in expectation, no sort
    return df.select(F.lit(name).alias("dataset"), "rid", "split", "is_anom", F.to_json(F.struct(*f.attrs)).alias("row"))


def _rows(pdf: pd.DataFrame, name: str) -> pd.DataFrame:
    f = FIXTURES[name]
    x = pd.DataFrame([json.loads(r) for r in pdf["row"]], columns=f.attrs)
    out = pd.concat([pdf[["rid", "split", "is_anom"]].reset_index(drop=True), x], axis=1)
    # in the order of a draw, so that the first rows of a context are a random sample of it
    return out.iloc[np.lexsort((out["rid"], uniforms(0, "ctx", out["rid"])))].reset_index(drop=True)


def _measure(score: np.ndarray, y: np.ndarray) -> tuple[float | None, float | None]:
    return sel.auroc(score, y), sel.average_precision(score, y)


_RESULT = "dataset string, method string, seed int, auroc double, ap double, n_context long, kept string"


def run_suite(s, d, names: list[str], configs: dict[str, det.Config], methods: list[str], mechanisms: dict[str, str] | None = None, change=None, seeds: tuple[int, ...] = (0,), cap: int = SUITE_CAP) -> DataFrame:
    """(dataset, method, seed, auroc, ap, n_context, kept): every configuration and baseline on every dataset, a dataset and seed a task."""
    data = None
    for n in names:
        x = _frame(s, d, n, cap)
        data = x if data is None else data.unionAll(x)
    data = data.crossJoin(s.createDataFrame([(i,) for i in seeds], "seed int"))  # a few seeds
    # the groups are small and their work is not: a stated number of partitions, as coalescing by bytes would put all into one task
    data = data.repartition(2 * len(names) * len(seeds), "dataset", "seed")
    mech = mechanisms or {}

    def one(key, pdf):
        name, seed = key
        f = FIXTURES[name]
        rows = _rows(pdf, name)
        if not f.given:
            rows = plant(rows, list(f.num), list(f.cat), mech.get(name, "law_break" if f.num else "rare_combo"), int(seed))
        if change is not None:
            rows = change(rows, int(seed))
        c, q = rows[rows["split"] == "context"], rows[rows["split"] == "query"]
        if not len(c) or not len(q):
            return pd.DataFrame([], columns=[x.split()[0] for x in _RESULT.split(", ")])
        y, out, cache = q["is_anom"].to_numpy(), [], {}
        for m, cfg in configs.items():
            cfg = det.replace_seed(cfg, int(seed))
            part = c.iloc[: cfg.context]  # by draw: see _rows
            k = (cfg.backbone, cfg.splits, cfg.rho_h, cfg.intra, cfg.context, cfg.ties)
            if k not in cache:  # supports are shared by all ablations that only choose among them
                cache[k] = det.evaluate(part, f.attrs, det.full(cfg))
            fit = det.finish(cache[k], cfg, f.attrs)
            sc_ = fit.score(q) if fit.tasks else np.zeros(len(q))
            out.append((name, m, int(seed), *_measure(sc_, y), len(part), ",".join(t.task for t in fit.kept)))
        if methods:
            c = c.iloc[: max((x.context for x in configs.values()), default=len(c))]  # baselines see the same rows
            schema = det.Schema.fit(c, f.attrs)
            x, cats = bl.matrix(schema.frame(c))
            z, _ = bl.matrix(schema.frame(q), cats)
            for m in methods:
                sc_ = bl.ChainDensity().fit(schema.frame(c)).score(schema.frame(q)) if m == "chain_density" else bl.METHODS[m](int(seed)).fit(x).score(z)
                out.append((name, m, int(seed), *_measure(sc_, y), len(c), ""))
        return pd.DataFrame(out, columns=[x.split()[0] for x in _RESULT.split(", ")])

    res = data.groupBy("dataset", "seed").applyInPandas(one, _RESULT)
    return res.withColumns({"auroc": F.round("auroc", 4), "ap": F.round("ap", 4)})


BASE = det.Config(backbone="kernel", context=600)


def overall(s, d):
    """All methods and backbones on all evaluation fixtures at five seeds; the control of the kernel's own floor beside them."""
    configs = {f"virtual_tasks_{b}": det.with_(BASE, backbone=b) for b in ("counts", "kernel", "gp", "kernel:softmax")}
    return run_suite(s, d, EVAL, configs, [*bl.METHODS, "chain_density"], seeds=OVERALL_SEEDS)


@query("workload_template_removal")
def template_removal(s, d):
    """Each template removed, each pair, each triple, each alone: re-selected from the same supports."""
    sets = [c for k in range(1, 6) for c in itertools.combinations("SLGPD", k)]
    return run_suite(s, d, ["line_num", "part_dep"], {"".join(c): det.with_(BASE, backbone="counts", templates="".join(c)) for c in sets}, [])


@query("workload_selection_ablation")
def selection_ablation(s, d):
    c = {
        "full": BASE, "one_fold": det.with_(BASE, splits=1), "default_configuration": det.with_(BASE, intra="default"),
        **{f"random_{k}": det.with_(BASE, inter=f"random{k}") for k in (1, 2, 3, 4)}, "best_task": det.with_(BASE, retention="best"), "half": det.with_(BASE, retention="topk"),
        **{e: det.with_(BASE, ensemble=e) for e in ("min", "spread-min", "spread-low2mean", "weighted")},
    }
    return run_suite(s, d, ["line_num", "part_dep"], c, [])


@query("workload_calibration")
def calibration(s, d):
    """Grid over fold share, shortlist share, rank weight, retention and ensemble on the development suite alone."""
    grid = {
        f"h{h}:g{g}:w{w}:{r}:{e}": det.with_(BASE, backbone="counts", rho_h=h, gamma=g, w_auc=w, retention=r, ensemble=e, context=400)
        for h in (0.10, 0.15, 0.20) for g in (0.5, 0.6, 0.7) for w in (1.5, 2.0) for r in ("all", "best", "topk") for e in ("min", "low2mean", "weighted")
    }
    res = run_suite(s, d, DEV, grid, [])
    return res.groupBy("method").agg(F.round(F.avg("auroc"), 4).alias("mean_auroc"), F.round(F.avg("ap"), 4).alias("mean_ap"))


@query("detect_line_mixed_kernel")
def detect_large(s, d):
    """The large mode: one detector from a bounded context, a map over all query rows; no shuffle after the context's top-n."""
    f = FIXTURES["line_mixed"]
    df = fixture(s, d, "line_mixed")
    c = df.filter("split = 'context'").orderBy(tk.u01(0, "ctx", F.col("rid")), "rid").limit(BASE.context).toPandas()
    return score_rows(df.filter("split = 'query'"), det.fit(c, f.attrs, BASE))


def score_rows(df: DataFrame, model: det.Fitted) -> DataFrame:
    """(rid, is_anom, score, by_task): scores of each row by a fitted detector, as a map."""
    names = [t.task for t in model.kept]

    def run(batches):
        for b in batches:
            k, sp = model.score_tasks(b)
            yield pd.DataFrame({"rid": b["rid"], "is_anom": b["is_anom"], "score": np.round(sel.combine(sp, model.kept, model.cfg.ensemble, model.cfg.w_auc), 6), "by_task": [dict(zip(names, r, strict=True)) for r in sp.round(6).tolist()]})

    return df.mapInPandas(run, "rid string, is_anom int, score double, by_task map<string,double>")


# --- plans that both engines can state

_OW = FIXTURES["order_wide"]
query("cap_order_wide", f"WITH a AS {fx('order_wide')}, r AS (SELECT rid, split, row_number() OVER (PARTITION BY split ORDER BY U['0';'cap';rid], rid) AS k, count(*) OVER (PARTITION BY split) AS ns, count(*) OVER () AS n FROM a) SELECT rid, split FROM r WHERE k <= round(1000.0 * ns / n)")(
    lambda s, d: cap_exact(fixture(s, d, "order_wide"), 1000)
)


def cap_exact(df: DataFrame, cap: int) -> DataFrame:
    """Exactly `cap` rows (to rounding) in the ratio of the sides: a top-n by draw on each."""
    n = {r.split: r.n for r in df.groupBy("split").agg(F.count("*").alias("n")).collect()}
    total, out = sum(n.values()), None
    for side, k in sorted(n.items()):
        size = int(np.floor(cap * k / total + 0.5)) if total > cap else k
        x = df.filter(F.col("split") == side).orderBy(tk.u01(0, "cap", F.col("rid")), "rid").limit(size).select("rid", "split")
        out = x if out is None else out.unionAll(x)
    return out


_SHARES = (0.0, 0.03, 0.05, 0.07)
query("contaminate_plan", f"""WITH a AS {fx('doc_quality')}, n AS (SELECT sum(is_anom) AS bad, sum((split = 'context')::INT) AS n_context FROM a), p AS (SELECT *, ceil(0.1::DOUBLE * n_context) AS pool FROM n)
    SELECT share, floor(share * n_context + 0.5::DOUBLE)::BIGINT AS replaced, pool::BIGINT AS pool, n_context::BIGINT AS n_context, pool <= 0.5 * bad AS eligible FROM p, (VALUES (0.0::DOUBLE), (0.03), (0.05), (0.07)) AS v(share)""")(
    lambda s, d: fixture(s, d, "doc_quality").agg(F.sum("is_anom").alias("bad"), F.sum((F.col("split") == "context").cast("long")).alias("n_context")).withColumn("pool", F.ceil(F.lit(0.1) * F.col("n_context")))
    .select(F.explode(F.array(*(F.lit(x) for x in _SHARES))).alias("share"), "*").select("share", F.floor(F.col("share") * F.col("n_context") + 0.5).alias("replaced"), "pool", "n_context", (F.col("pool") <= 0.5 * F.col("bad")).alias("eligible"))
)
query("context_budget_plan", f"WITH c AS (SELECT count(*) AS n FROM {fx('line_num')} AS a WHERE split = 'context') SELECT budget, least(budget, n)::BIGINT AS used FROM c, (VALUES (10000), (5000), (2000), (1000)) AS v(budget)")(
    lambda s, d: fixture(s, d, "line_num").filter("split = 'context'").agg(F.count("*").alias("n")).select(F.explode(F.array(*(F.lit(x) for x in (10000, 5000, 2000, 1000)))).alias("budget"), "n").select("budget", F.least("budget", "n").alias("used"))
)


@query("template_removal_plan", "WITH t(x) AS (VALUES ('S'), ('L'), ('G'), ('P'), ('D')) SELECT DISTINCT array_to_string(list_sort(list_distinct([a.x, b.x, c.x, d.x, e.x])), '') AS kept FROM t a, t b, t c, t d, t e")
def template_removal_plan(s, d):
    return s.createDataFrame([("".join(sorted(c)),) for k in range(1, 6) for c in itertools.combinations("SLGPD", k)], "kept string")


@query("plant_scale_out", f"WITH a AS {fx('part_dep')}, r AS (SELECT Q[retail;0.75] - Q[retail;0.25] AS w FROM a WHERE split = 'context') SELECT rid, is_anom, round(CASE WHEN is_anom = 1 THEN retail + CASE WHEN U['0';'sign';rid] < 0.5 THEN -1 ELSE 1 END * (2 + 2 * U['0';'size';rid]) * w ELSE retail END, 6) AS retail FROM a, r WHERE split = 'query'")
def plant_scale_out(s, d):
    df = fixture(s, d, "part_dep")
    q = df.filter("split = 'context'").agg(F.percentile("retail", F.array(F.lit(0.25), F.lit(0.75)))).first()[0]
    sign = F.when(tk.u01(0, "sign", F.col("rid")) < 0.5, -1).otherwise(1)
    moved = F.col("retail") + sign * (2 + 2 * tk.u01(0, "size", F.col("rid"))) * F.lit(q[1] - q[0])
    return df.filter("split = 'query'").select("rid", "is_anom", F.round(F.when(F.col("is_anom") == 1, moved).otherwise(F.col("retail")), 6).alias("retail"))

