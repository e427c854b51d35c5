"""The measures over results that the suite really gave, and the efficiency, contamination and budget experiments.

The suite runs once a session and folder: its rows are datasets x methods x
seeds, few by nature, so they are kept on the driver and every measure reads
them. A dataset whose query side has one class has no value and is left out.
"""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from vtask.kernels import baselines as bl
from vtask.kernels import detector as det
from vtask.kernels.draws import rng
from vtask.operators import compare as cmp
from vtask.operators import tasks as tk
from vtask.plans.cost import timed
from vtask.plans.queries import query
from vtask.plans.workloads import BASE, EVAL, overall, run_suite
from vtask.sources.fixtures import FIXTURES, fixture

#: Rows a result table may have on the driver; more is no table of methods and datasets.
MOST = 200_000
_SEEN: dict[tuple, list] = {}


def kept(s, d, name: str, run) -> DataFrame:
    """Rows of run(s, d), computed once a session and folder."""
    key = (s.sparkContext.applicationId, d, name)
    if key not in _SEEN:
        df = run(s, d)
        rows = df.limit(MOST + 1).collect()
        if len(rows) > MOST:
            raise ValueError(f"more than {MOST} results")
        _SEEN[key] = (rows, df.schema)
    rows, schema = _SEEN[key]
    return s.createDataFrame(rows, schema)


@query("workload_overall")
def results(s, d) -> DataFrame:
    """All methods and backbones on all evaluation fixtures at five seeds."""
    return kept(s, d, "overall", overall)


def values(res: DataFrame, measure: str) -> DataFrame:
    """(dataset, method, value, n_rows): mean over seeds; only datasets with a value by some method."""
    return res.filter(F.col(measure).isNotNull()).groupBy("dataset", "method").agg(F.round(F.avg(measure), 6).alias("value"), F.max("n_context").alias("n_rows"))


def imputed(v: DataFrame) -> DataFrame:
    """A method without a value gets the mean of the others on that dataset."""
    return cmp.impute(v.select("dataset", "method", "value"), v.select("dataset").distinct(), v.select("method").distinct()).drop("imputed")


def complete(v: DataFrame) -> DataFrame:
    return cmp.complete_only(v.select("dataset", "method", "value"), v.select("method").distinct().count())


def table(v: DataFrame) -> DataFrame:
    """(method, mean_value, avg_rank, elo, top_ratio) of values(dataset, method, value)."""
    mean = v.groupBy("method").agg(F.round(F.avg("value"), 6).alias("mean_value"))
    return mean.join(cmp.avg_rank(v), "method").join(cmp.elo(v), "method").join(cmp.topk_ratio(v), "method")


def both(res: DataFrame, f) -> DataFrame:
    """f of the values by each measure, one under the other."""
    a, b = (f(values(res, m)).select(F.lit(m).alias("measure"), "*") for m in ("auroc", "ap"))
    return a.unionByName(b)


def total(res: DataFrame, policy=imputed) -> DataFrame:
    """(method, total_rank): mean of the ranks by eight measures: mean, average rank, Elo and Top-3, by each of both qualities."""
    a, b = (policy(values(res, m)) for m in ("auroc", "ap"))
    x, y = (table(v).select("method", *(F.col(c).alias(f"{c}_{i}") for c in ("mean_value", "avg_rank", "elo", "top_ratio"))) for i, v in enumerate((a, b)))
    return cmp.total_rank(x.join(y, "method"), [f"{c}_{i}" for i in (0, 1) for c in ("mean_value", "elo", "top_ratio")], ["avg_rank_0", "avg_rank_1"])


@query("overall_summary")
def overall_summary(s, d):
    """Mean over datasets and its deviation over the five seeds."""
    out = [cmp.summary(results(s, d).filter(F.col(m).isNotNull()).withColumnRenamed(m, "value")).select(F.lit(m).alias("measure"), "*") for m in ("auroc", "ap")]
    return out[0].unionAll(out[1])


query("overall_measures")(lambda s, d: both(results(s, d), lambda v: table(imputed(v))))
query("overall_complete")(lambda s, d: both(results(s, d), lambda v: table(complete(v))))
query("overall_total_rank")(lambda s, d: total(results(s, d)))
query("overall_total_rank_complete")(lambda s, d: total(results(s, d), complete))
query("overall_rank_box")(lambda s, d: both(results(s, d), lambda v: cmp.rank_box(imputed(v))))


def elo_by_size(v: DataFrame) -> DataFrame:
    """(size_group, method, elo): the ratings within each group of context sizes; three groups at most."""
    g = v.withColumn("size_group", cmp.size_group(F.max("n_rows").over(_by_dataset())))
    out = None
    for name in sorted(r.size_group for r in g.select("size_group").distinct().collect()):
        x = cmp.elo(imputed(g.filter(F.col("size_group") == name))).select(F.lit(name).alias("size_group"), "method", "elo")
        out = x if out is None else out.unionAll(x)
    return out if out is not None else g.select("size_group", "method", F.col("value").alias("elo"))


def _by_dataset():
    from pyspark.sql import Window

    return Window.partitionBy("dataset")


query("overall_elo_by_size")(lambda s, d: both(results(s, d), elo_by_size))

# ------------------------------------------------------------------ efficiency

#: Context rows and attributes of the grid, and the query rows that a time is measured on.
SIZES, WIDTHS, TIMED_ROWS = (1_000, 10_000, 100_000), (4, 16, 64), 2_000


def efficiency(context: pd.DataFrame, rows: pd.DataFrame, attrs: list[str], cfg: det.Config) -> list[dict]:
    """Times of selection and scoring at three folds and at one, and their ratio to the attribute chain with the same backbone."""
    schema = det.Schema.fit(context, attrs)
    c, q = schema.frame(context), schema.frame(rows)
    t_fit, chain = timed(lambda: bl.ChainDensity(cfg.backbone).fit(c))
    t_chain = timed(chain.score, q)[0]
    out = []
    for splits in (3, 1):
        t_sel, fit = timed(det.fit, context, attrs, det.with_(cfg, splits=splits, context=max(len(context), 1)))
        t_score = timed(fit.score, rows)[0]
        out.append({"n": len(context), "d": len(attrs), "splits": splits, "selection_s": t_sel, "ms_a_row": 1000 * t_score / len(rows), "chain_ms_a_row": 1000 * t_chain / len(rows),
                    "ratio_scoring": t_chain / t_score, "ratio_with_selection": (t_fit + t_chain) / (t_sel + t_score), "kept": len(fit.kept), "fit_calls": fit.counters["fit_calls"], "chain_calls": chain.calls})
    return out


def _drawn(df: DataFrame, n: int) -> pd.DataFrame:
    """The n rows of smallest draw; n is bounded by the largest context."""
    return df.orderBy(tk.u01(0, "ctx", F.col("rid")), "rid").limit(n).toPandas()


@query("workload_efficiency")
def workload_efficiency(s, d):
    """Over context sizes on lineitem and over attributes on embeddings; a size that the table lacks is reported as what there is.

    One process measures, as times of tasks that share cores mean little.
    """
    cfg, out = det.with_(BASE, backbone="counts"), []
    df = fixture(s, d, "line_mixed")
    c, q = _drawn(df.filter("split = 'context'"), max(SIZES)), _drawn(df.filter("split = 'query'"), TIMED_ROWS)
    for n in sorted({min(n, len(c)) for n in SIZES}):
        out += [{"axis": "rows", **x} for x in efficiency(c.iloc[:n], q, FIXTURES["line_mixed"].attrs, cfg)] if n > 3 and len(q) else []
    e = s.read.parquet(f"{d}/embeddings.parquet").select(F.col("vec_id").cast("string").alias("rid"), "embedding")
    pdf = _drawn(e, min(SIZES) + TIMED_ROWS)
    x = pd.DataFrame(np.stack(pdf["embedding"]).astype(float), columns=[f"e{i}" for i in range(len(pdf["embedding"].iloc[0]))]) if len(pdf) else pd.DataFrame()
    cut = min(min(SIZES), len(x) * 6 // 10)
    for w in sorted({min(w, x.shape[1]) for w in WIDTHS}) if cut > 3 else ():
        out += [{"axis": "attributes", **r} for r in efficiency(x.iloc[:cut], x.iloc[cut:], list(x.columns[:w]), cfg)]
    fields = "axis string, n long, d int, splits int, selection_s double, ms_a_row double, chain_ms_a_row double, ratio_scoring double, ratio_with_selection double, kept int, fit_calls int, chain_calls int"
    return s.createDataFrame([tuple(r[f.split()[0]] for f in fields.split(", ")) for r in out], fields)


# ------------------------------------------------------------------ contamination

SHARES, WORST, MAY_LOSE = (0.0, 0.03, 0.05, 0.07), 0.10, 0.5


def contaminate(share: float):
    """Swap a share of the context for anomalies of a pool that no query set holds.

    The pool is as large as the worst setting needs and the same at every share;
    a dataset that would lose more than half of its anomalies to it gives no
    rows. Normal query rows are thinned so that the share of anomalies among
    the queries stays what it was.
    """

    def change(rows: pd.DataFrame, seed: int) -> pd.DataFrame:
        g = rng(seed, "pool")
        c = np.flatnonzero((rows["split"] == "context").to_numpy())
        query_side = (rows["split"] == "query").to_numpy()
        bad, good = (np.flatnonzero(query_side & (rows["is_anom"] == v).to_numpy()) for v in (1, 0))
        size = int(np.ceil(WORST * len(c)))
        if not len(c) or size > MAY_LOSE * len(bad):
            return rows.iloc[:0]
        pool = g.permutation(bad)[:size]
        away = g.permutation(good)[: int(np.floor(len(good) * size / len(bad) + 0.5))]
        n = int(np.floor(share * len(c) + 0.5))
        swapped, out = g.permutation(c)[:n], rows.copy()
        # a swapped-in row takes the place of the row it replaces, so its rank in the draw does not move
        for a in out.columns:
            if a != "split":
                out.iloc[swapped, out.columns.get_loc(a)] = rows[a].to_numpy()[pool[:n]]
        return out.drop(index=out.index[np.concatenate([pool, away])])

    return change


GIVEN = [n for n in EVAL if FIXTURES[n].given]


def _contaminated(s, d) -> DataFrame:
    out = None
    for p in SHARES:
        r = run_suite(s, d, GIVEN, {"virtual_tasks": BASE}, ["knn", "lof", "iforest", "ecod"], change=contaminate(p)).withColumn("share", F.lit(p))
        out = r if out is None else out.unionAll(r)
    return out


@query("workload_contamination")
def contamination(s, d):
    """Labelled datasets at each share; the query set is the same at all of them."""
    return kept(s, d, "contamination", _contaminated)


@query("contamination_relative")
def contamination_relative(s, d):
    """(share, method, measure, value, relative): means over datasets, and against the method itself at 1 at each share."""
    v = contamination(s, d).select("share", "method", "dataset", F.explode(F.create_map(F.lit("auroc"), F.col("auroc"), F.lit("ap"), F.col("ap"))).alias("measure", "x"))
    v = v.filter("x IS NOT NULL").groupBy("share", "measure", "method").agg(F.avg("x").alias("value"))
    own = v.filter("method = 'virtual_tasks'").select("share", "measure", F.col("value").alias("own"))
    return v.join(F.broadcast(own), ["share", "measure"]).select("share", "measure", "method", F.round("value", 6).alias("value"), F.round(F.col("value") / F.col("own"), 6).alias("relative"))


# ------------------------------------------------------------------ context budgets

BUDGETS = (10_000, 5_000, 2_000, 1_000)
LARGE = ["line_num", "line_cat", "line_mixed"]


@query("workload_context_budget")
def context_budget(s, d):
    """Whole pipeline on 10K, 5K, 2K and 1K rows by draw and on the whole context up to the published cap; the count backbone, as the kernel is quadratic."""
    c = {f"context_{n}": det.with_(BASE, backbone="counts", context=n) for n in BUDGETS} | {"context_full": det.with_(BASE, backbone="counts", context=100_000)}
    return kept(s, d, "budget", lambda s, d: run_suite(s, d, LARGE, c, [], cap=100_000))


query("context_budget_elo")(lambda s, d: both(context_budget(s, d), cmp.elo))
