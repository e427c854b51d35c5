"""Split, cap, planting and probe diagnostics as plans that both engines state; the mixed prototype fit and the classifiers of Spark's own library."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from vtask.operators import tasks as tk
from vtask.plans.queries import _LC_REST, _MIX, _mix_view, _probe, _probe_sql, context, ctx, fx, query
from vtask.plans.workloads import cap_exact
from vtask.sources.fixtures import FIXTURES, fixture

# ------------------------------------------------------------------ split and cap

#: Normal rows that are context, where anomalies are at most 30 % of all rows and where they are more.
FEW, MANY, BORDER = 0.6, 0.5, 0.3


def split_by_ratio(df: DataFrame) -> DataFrame:
    """(rid, is_anom, split): a share of the normal rows is context, less of them where anomalies are many; the ratio is one aggregation."""
    share = df.agg(F.avg(F.col("is_anom").cast("double")).alias("r")).select(F.when(F.col("r") > BORDER, MANY).otherwise(FEW).alias("share"))
    side = F.when((F.col("is_anom") == 0) & (tk.u01(0, "split", F.col("rid")) < F.col("share")), "context").otherwise("query")
    return df.crossJoin(F.broadcast(share)).select("rid", "is_anom", side.alias("split"))  # one row


query("split_60_50", " UNION ALL ".join(f"SELECT '{n}' AS dataset, rid, is_anom, CASE WHEN is_anom = 0 AND U['0';'split';rid] < CASE WHEN (SELECT avg(is_anom) FROM {fx(n)} AS r{i}) > 0.3 THEN 0.5 ELSE 0.6 END THEN 'context' ELSE 'query' END AS split FROM {fx(n)} AS a{i}"
      for i, n in enumerate(("doc_quality", "doc_toxic", "conv_role"))))(
    lambda s, d: _union(split_by_ratio(fixture(s, d, n)).select(F.lit(n).alias("dataset"), "rid", "is_anom", "split") for n in ("doc_quality", "doc_toxic", "conv_role"))
)


def _union(frames) -> DataFrame:
    first, *rest = frames
    for f in rest:
        first = first.unionAll(f)
    return first


query("cap_100k", f"WITH a AS {fx('order_cat')}, r AS (SELECT rid, split, row_number() OVER (PARTITION BY split ORDER BY U['0';'cap';rid], rid) AS k, count(*) OVER (PARTITION BY split) AS ns, count(*) OVER () AS n FROM a) SELECT rid, split FROM r WHERE n <= 100000 OR k <= floor(100000.0 * ns / n + 0.5)")(
    lambda s, d: cap_exact(fixture(s, d, "order_cat"), 100_000)
)

# ------------------------------------------------------------------ planting

_TENTHS = ", ".join(f"Q[per_size;{i / 10}] AS b{i}" for i in range(1, 10))
_TENTH = " + ".join(f"(per_size > b{i})::INT" for i in range(1, 10))


@query(
    "plant_law_break",
    f"""WITH a AS {fx('part_dep')}, b AS (SELECT {_TENTHS} FROM a WHERE split = 'context'),
    t AS (SELECT rid, split, is_anom, per_size, {_TENTH} AS tenth FROM a, b),
    c AS (SELECT tenth, per_size AS other, row_number() OVER (PARTITION BY tenth ORDER BY rid) - 1 AS place, count(*) OVER (PARTITION BY tenth) AS n FROM t WHERE split = 'context'),
    z AS (SELECT tenth, max(n) AS n FROM c GROUP BY tenth)
    SELECT t.rid, t.is_anom, round(CASE WHEN t.is_anom = 1 THEN c.other ELSE t.per_size END, 6) AS per_size FROM t LEFT JOIN z ON t.tenth = z.tenth LEFT JOIN c ON c.tenth = t.tenth AND t.is_anom = 1 AND c.place = floor(U['0';'donor';t.rid] * z.n) WHERE t.split = 'query'""",
)
def plant_law_break(s, d):
    """A dependent attribute takes a context value of its own tenth: its marginal holds, the law that ties it to the others does not."""
    df = fixture(s, d, "part_dep")
    edges = tk.fit_borders(df.filter("split = 'context'"), {"per_size": F.col("per_size")}, 10)["per_size"]
    t = df.select("rid", "split", "is_anom", "per_size", tk.qbin(F.col("per_size"), edges).alias("tenth"))
    c = t.filter("split = 'context'").select("tenth", F.col("per_size").alias("other"), (F.row_number().over(Window.partitionBy("tenth").orderBy("rid")) - 1).alias("place"))
    q = t.filter("split = 'query'")
    bad = q.filter("is_anom = 1").join(F.broadcast(c.groupBy("tenth").agg(F.count("*").alias("n"))), "tenth")  # ten rows
    bad = bad.withColumn("place", F.floor(tk.u01(0, "donor", F.col("rid")) * F.col("n"))).join(c, ["tenth", "place"])
    keep = q.filter("is_anom = 0").select("rid", "is_anom", F.round("per_size", 6).alias("per_size"))
    return keep.unionAll(bad.select("rid", "is_anom", F.round("other", 6).alias("per_size")))


# ------------------------------------------------------------------ probes

_CAT = FIXTURES["order_wide"].cat
_PAIRS = [(a, b) for i, a in enumerate(_CAT) for b in _CAT[i + 1 :]]


def mutual_information(df: DataFrame, pairs: list[tuple[str, str]], *by: str) -> DataFrame:
    """(by, a, b, mi): one grouped count for all pairs, whose rows are bounded by the categories."""
    one = F.array(*(F.struct(F.lit(a).alias("a"), F.lit(b).alias("b"), F.col(a).alias("va"), F.col(b).alias("vb")) for a, b in pairs))
    k = df.select(*by, F.explode(one).alias("p")).groupBy(*by, "p.a", "p.b", "p.va", "p.vb").agg(F.count("*").cast("double").alias("k"))
    w = Window.partitionBy(*by, "a", "b")
    k = k.withColumns({"n": F.sum("k").over(w), "ka": F.sum("k").over(Window.partitionBy(*by, "a", "b", "va")), "kb": F.sum("k").over(Window.partitionBy(*by, "a", "b", "vb"))})
    return k.groupBy(*by, "a", "b").agg(F.sum(F.col("k") / F.col("n") * F.log(F.col("k") * F.col("n") / (F.col("ka") * F.col("kb")))).alias("mi"))


def _mi_sql(a: str, b: str) -> str:
    w = "OVER (PARTITION BY side"
    return f"""SELECT side, '{a}' AS a, '{b}' AS b, sum(k / n * ln(k * n / (ka * kb))) AS mi FROM (SELECT side, k, sum(k) {w}) AS n, sum(k) {w}, {a}) AS ka, sum(k) {w}, {b}) AS kb
    FROM (SELECT side, {a}, {b}, count(*)::DOUBLE AS k FROM x GROUP BY side, {a}, {b}) AS g) AS h GROUP BY side"""


@query(
    "probe_dependence_gap",
    f"WITH p AS ({_probe_sql(FIXTURES['order_wide'].attrs, 'true')}), c0 AS {ctx('order_wide')}, x AS (SELECT 'real' AS side, {', '.join(_CAT)} FROM c0 UNION ALL SELECT 'probe', {', '.join(_CAT)} FROM p), m AS ({' UNION ALL '.join(_mi_sql(a, b) for a, b in _PAIRS)}) "
    "SELECT a, b, round(max(mi) FILTER (WHERE side = 'real'), 6) AS mi_real, round(max(mi) FILTER (WHERE side = 'probe'), 6) AS mi_probe FROM m GROUP BY a, b",
)
def dependence_gap(s, d):
    """Mutual information of each pair of categories in the context and in its shuffled probes, whose cells come from independent donors."""
    real, probe = context(s, d, "order_wide").select(F.lit("real").alias("side"), *_CAT), _probe(s, d, None).select(F.lit("probe").alias("side"), *_CAT)
    m = mutual_information(real.unionAll(probe), _PAIRS, "side")
    return m.groupBy("a", "b").agg(*(F.round(F.max(F.when(F.col("side") == x, F.col("mi"))), 6).alias(f"mi_{x}") for x in ("real", "probe")))


_NUM = FIXTURES["order_wide"].num
_JIT = ", ".join(f"{a} + 0.5 * w_{a} * (sqrt(-2.0 * ln(1.0 - U['0';'jit.{a}.a';rid])) * cos(6.283185307179586 * U['0';'jit.{a}.b';rid])) AS j_{a}" for a in _NUM)


@query(
    "probe_jitter_moments",
    f"WITH c AS {ctx('order_wide')}, r AS (SELECT " + ", ".join(f"Q[{a};0.75] - Q[{a};0.25] AS w_{a}" for a in _NUM) + f" FROM c), j AS (SELECT c.*, {_JIT} FROM c, r) "
    + " UNION ALL ".join(f"SELECT '{a}' AS attr, round((avg(j_{a}) - avg({a})) / any_value(w_{a}), 6) AS mean_shift, round((var_pop(j_{a}) - var_pop({a})) / pow(0.5 * any_value(w_{a}), 2), 6) AS variance_gain FROM j, r" for a in _NUM),
)
def jitter_moments(s, d):
    """What jitter leaves and adds: the mean's move in interquartile widths (near 0) and the variance's growth in squared noise widths (near 1)."""
    c = context(s, d, "order_wide")
    q = c.agg(*(F.percentile(a, F.array(F.lit(0.25), F.lit(0.75))).alias(a) for a in _NUM)).first()
    out = []
    for a in _NUM:
        u, v, w = tk.u01(0, f"jit.{a}.a", F.col("rid")), tk.u01(0, f"jit.{a}.b", F.col("rid")), q[a][1] - q[a][0]
        j = F.col(a) + F.lit(0.5 * w) * (F.sqrt(F.lit(-2.0) * F.log(F.lit(1.0) - u)) * F.cos(F.lit(6.283185307179586) * v))
        out.append(F.struct(F.lit(a).alias("attr"), F.round((F.avg(j) - F.avg(a)) / F.lit(w), 6).alias("mean_shift"), F.round((F.var_pop(j) - F.var_pop(a)) / F.lit((0.5 * w) ** 2), 6).alias("variance_gain")))
    return c.agg(F.array(*out).alias("x")).select(F.explode("x").alias("x")).select("x.*")


# ------------------------------------------------------------------ prototypes of mixed rows


def fit_kproto(df: DataFrame, codes: dict, cat: list[str], k: int, rounds: int = 20) -> list[tuple[list[float], list[str]]]:
    """Alternating assignment and update (mean codes, modal categories); a round is two aggregations of k rows and k x categories rows.

    The start is the k rows of smallest hash that differ; a prototype that loses
    all rows stays where it was. An empty table gives no prototype.
    """
    names = list(codes)
    key = F.md5(F.concat_ws("|", *names, *cat).cast("binary"))
    rows = df.select(*(c.alias(a) for a, c in codes.items()), *(F.coalesce(F.col(a), F.lit("\x00null")).alias(a) for a in cat)).distinct().orderBy(key, *names, *cat).limit(k).collect()
    protos = [([float(r[a]) for a in names], [r[a] for a in cat]) for r in rows]
    for _ in range(rounds if protos else 0):
        y = tk.assign_kproto(codes, cat, protos)
        means = {r.cluster: [round(r[a], 6) for a in names] for r in df.groupBy(y.alias("cluster")).agg(*(F.avg(c).alias(a) for a, c in codes.items())).collect()}
        modes = {(r.cluster, r.attr): r["mode"] for r in tk.update_modes(df, y, cat).collect()}
        new = [(means.get(i, c), [modes.get((i, a), v) for a, v in zip(cat, m, strict=True)]) for i, (c, m) in enumerate(protos)]
        if new == protos:
            break
        protos = new
    return protos


@query("kproto_fit")
def kproto_fit(s, d):
    c = context(s, d, "line_mixed")
    edges, _ = _mix_view(c)
    codes = {a: tk.qbin(F.col(a), b).cast("double") for a, b in edges.items()}
    return fixture(s, d, "line_mixed").select("rid", tk.assign_kproto(codes, list(_MIX.cat), fit_kproto(c, codes, list(_MIX.cat), 3)).alias("label"))


# ------------------------------------------------------------------ trained classifiers as backbones


def trained_support(df: DataFrame, label: str, cat: list[str], kind: str, seed: int = 0) -> DataFrame:
    """(rid, is_anom, kappa): probability of each row's own label by a classifier trained on the context's labels, distributed; a label or token that the context lacks gets the least support."""
    from pyspark.ml import Pipeline
    from pyspark.ml.classification import LogisticRegression, RandomForestClassifier
    from pyspark.ml.feature import OneHotEncoder, StringIndexer, VectorAssembler
    from pyspark.ml.functions import vector_to_array

    df = df.select("rid", "split", "is_anom", *(F.coalesce(F.col(a), F.lit("\x00null")).alias(a) for a in [label, *cat]))
    steps = [StringIndexer(inputCols=[label, *cat], outputCols=[f"i_{a}" for a in [label, *cat]], handleInvalid="keep"), OneHotEncoder(inputCols=[f"i_{a}" for a in cat], outputCols=[f"v_{a}" for a in cat], handleInvalid="keep"), VectorAssembler(inputCols=[f"v_{a}" for a in cat], outputCol="x")]
    how = {"featuresCol": "x", "labelCol": f"i_{label}", "probabilityCol": "p"}
    model = {"forest": lambda: RandomForestClassifier(numTrees=20, maxDepth=8, seed=seed, **how), "logit": lambda: LogisticRegression(maxIter=50, regParam=1e-4, **how)}[kind]()
    fit = Pipeline(stages=[*steps, model]).fit(df.filter("split = 'context'"))
    p = F.try_element_at(vector_to_array("p"), (F.col(f"i_{label}") + 1).cast("int"))
    return fit.transform(df).select("rid", "is_anom", F.round(F.greatest(F.coalesce(p, F.lit(0.0)), F.lit(1e-9)), 6).alias("kappa"))


for _kind in ("forest", "logit"):
    query(f"{_kind}_support_line_cat")(lambda s, d, k=_kind: trained_support(fixture(s, d, "line_cat"), "return_flag", _LC_REST, k).select("rid", "kappa"))
