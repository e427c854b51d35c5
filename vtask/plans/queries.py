"""The registered queries of the method, each with SQL of its own where SQL can say it."""

from __future__ import annotations

from collections.abc import Callable, Iterator
from contextlib import contextmanager

from pyspark import StorageLevel
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from vtask.kernels import selection as sel
from vtask.kernels.draws import drawn_subset
from vtask.kernels.table import CAT, NUM, PROFILES
from vtask.kernels.tasks import axes, instantiations
from vtask.operators import compare as cmp
from vtask.operators import profile as prof
from vtask.operators import scoring as sc
from vtask.operators import tasks as tk
from vtask.sources.dialect import duck, spark_sql
from vtask.sources.fixtures import FIXTURES, fixture

QUERIES: dict[str, Callable] = {}
ORACLES: dict[str, str] = {}


def query(name: str, sql: str | None = None):
    def add(f):
        QUERIES[name] = f
        if sql is not None:
            ORACLES[name] = duck(sql)
        return f

    return add


def fx(name: str) -> str:
    return f"({FIXTURES[name].sql})"


def ctx(name: str) -> str:
    return f"(SELECT * FROM {fx(name)} AS f0 WHERE split = 'context')"


def context(s, d, name) -> DataFrame:
    return fixture(s, d, name).filter("split = 'context'")


@contextmanager
def held(df: DataFrame) -> Iterator[DataFrame]:
    """df, worked out once and kept on disk while it is fitted, as naming and splitting rows costs more than any pass over their numbers."""
    df.persist(StorageLevel.DISK_ONLY)
    try:
        yield df
    finally:
        df.unpersist()


# ------------------------------------------------------------------ profiling

_STATS = "SELECT '{a}' AS name, count({a}) AS n_valid, count(DISTINCT {a}) AS n_distinct, {whole} AS int_like FROM {src} AS s"


def _stats_sql(name: str) -> str:
    f = FIXTURES[name]
    return " UNION ALL ".join(_STATS.format(a=a, src="c", whole=f"coalesce(min((({a}) = floor({a}))::INT) = 1, false)" if a in f.num else "false") for a in f.attrs)


def _types_sql(name: str) -> str:
    f = FIXTURES[name]
    text = ", ".join(f"'{a}'" for a in f.cat) or "''"
    return f"""WITH c AS {ctx(name)}, st AS ({_stats_sql(name)}), t AS (SELECT *, least(20, greatest(2, ceil(sqrt(n_valid))))::BIGINT AS threshold FROM st)
    SELECT name, n_valid, n_distinct, int_like, threshold, CASE WHEN n_valid = 0 OR n_distinct <= 1 THEN 'constant'
        WHEN name IN ({text}) THEN CASE WHEN n_distinct * 1.0 / n_valid > 0.5 THEN 'identifier' WHEN n_distinct <= threshold THEN 'categorical' ELSE 'numerical' END
        WHEN (n_distinct < 10 OR n_distinct <= threshold) AND (int_like OR n_distinct <= threshold) AND n_distinct * 1.0 / n_valid <= 0.5 THEN 'categorical' ELSE 'numerical' END AS kind FROM t"""


for _n, _x in (("lineitem", "line_mixed"), ("orders", "order_wide")):
    query(f"attr_stats_{_n}", f"WITH c AS {ctx(_x)} {_stats_sql(_x)}")(lambda s, d, x=_x: prof.attr_stats(context(s, d, x), FIXTURES[x].attrs))
for _x in ("line_mixed", "event_mix", "part_dep", "doc_quality"):
    query(f"attr_types_{_x}", _types_sql(_x))(lambda s, d, x=_x: prof.infer_types(context(s, d, x), FIXTURES[x].attrs))

_PROFILED = ("line_mixed", "line_num", "line_cat", "line_catdom", "order_wide", "part_dep", "event_mix", "user_profile", "supp_small")


@query(
    "profile_all_fixtures",
    " UNION ALL ".join(
        f"""SELECT '{x}' AS fixture, sum((kind = 'numerical')::INT)::BIGINT AS d_num, sum((kind = 'categorical')::INT)::BIGINT AS d_cat,
        CASE WHEN sum((kind = 'categorical')::INT) = 0 THEN 'numerical-only' WHEN sum((kind = 'numerical')::INT) = 0 THEN 'categorical-only'
        WHEN sum((kind = 'categorical')::INT) * 1.0 / sum((kind IN ('numerical', 'categorical'))::INT) >= 0.8 THEN 'mixed-categorical-dominant'
        WHEN sum((kind = 'numerical')::INT) * 1.0 / sum((kind IN ('numerical', 'categorical'))::INT) >= 0.8 THEN 'mixed-numerical-dominant' ELSE 'mixed' END AS profile FROM ({_types_sql(x)})"""
        for x in _PROFILED
    ),
)
def profile_all(s, d):
    out = None
    for x in _PROFILED:
        t = prof.infer_types(context(s, d, x), FIXTURES[x].attrs).select(F.lit(x).alias("fixture"), "kind")
        out = t if out is None else out.unionAll(t)
    return _profiles(out, "fixture")


def _profiles(kinds: DataFrame, name: str) -> DataFrame:
    """(name, d_num, d_cat, profile) from a row (name, kind) an attribute."""
    num, cat = F.sum((F.col("kind") == NUM).cast("long")), F.sum((F.col("kind") == CAT).cast("long"))
    g = kinds.groupBy(name).agg(num.alias("d_num"), cat.alias("d_cat"))
    share = F.col("d_cat") / (F.col("d_num") + F.col("d_cat"))
    p = F.when(F.col("d_cat") == 0, "numerical-only").when(F.col("d_num") == 0, "categorical-only").when(share >= 0.8, "mixed-categorical-dominant").when(F.lit(1) - share >= 0.8, "mixed-numerical-dominant").otherwise("mixed")
    return g.withColumn("profile", p)


#: Data sets of many sizes: the orders of each buyer, none included; the events of each user; the lines of each seller and of each status.
_LINE_SETS = """SELECT 'seller' AS source, cast(l_suppkey AS TEXT) AS id, count(*) AS n FROM lineitem GROUP BY l_suppkey
    UNION ALL SELECT 'status' AS source, l_linestatus AS id, count(*) AS n FROM lineitem GROUP BY l_linestatus"""
_SETS = f"""SELECT 'buyer' AS source, cast(c_custkey AS TEXT) AS id, count(o_orderkey) AS n FROM customer LEFT JOIN orders ON c_custkey = o_custkey GROUP BY c_custkey
    UNION ALL SELECT 'user' AS source, cast(user_id AS TEXT) AS id, count(*) AS n FROM events GROUP BY user_id UNION ALL {_LINE_SETS}"""


@query("card_threshold_grid", f"SELECT source, id, n, least(20, greatest(2, ceil(sqrt(n))))::BIGINT AS threshold FROM ({_SETS}) AS r")
def card_grid(s, d):
    return spark_sql(s, d, _SETS).withColumn("threshold", prof.card_threshold(F.col("n")))


# ------------------------------------------------------------------ transforms

_LN = FIXTURES["line_num"].num
_ROBUST = ", ".join(f"Q[{a};0.25] AS q1_{a}, Q[{a};0.5] AS m_{a}, CASE WHEN Q[{a};0.75] - Q[{a};0.25] = 0 THEN stddev_pop({a}) ELSE Q[{a};0.75] - Q[{a};0.25] END AS w_{a}" for a in _LN)


@query("robust_params_line_num", f"WITH c AS {ctx('line_num')}, r AS (SELECT {_ROBUST} FROM c) " + " UNION ALL ".join(f"SELECT '{a}' AS name, round(m_{a}, 6) AS mid, round(w_{a}, 6) AS width FROM r" for a in _LN))
def robust_params(s, d):
    with held(context(s, d, "line_num").select(*_LN)) as c:
        t = tk.fit_robust(c, list(_LN))
    return s.createDataFrame([(a, round(t.mid[a], 6), round(t.width[a], 6)) for a in _LN], "name string, mid double, width double")


def _qbin_sql(expr: str, k: int) -> str:
    return " + ".join(f"CASE WHEN {expr} > b.b{i} THEN 1 ELSE 0 END" for i in range(1, k))


def _borders_sql(expr: str, k: int, src: str) -> str:
    """Borders as columns; equal ones give a step of two, which merged borders count once, so later ones must differ from earlier."""
    cols = [f"Q[{expr};{i / k!r}] AS b{i}" for i in range(1, k)]
    return f"(SELECT {', '.join(cols)} FROM {src} AS s)"


def _steps(expr: str, k: int) -> str:
    return " + ".join(f"CASE WHEN {expr} > b{i}" + (f" AND b{i} > b{i - 1}" if i > 1 else "") + " THEN 1 ELSE 0 END" for i in range(1, k))


for _k in (2, 3):
    query(f"qbin{_k}_price", f"WITH a AS {fx('line_num')}, b AS {_borders_sql('price', _k, '(SELECT * FROM a WHERE split = ' + chr(39) + 'context' + chr(39) + ')')} SELECT rid, ({_steps('price', _k)})::INT AS label FROM a, b")(
        lambda s, d, k=_k: fixture(s, d, "line_num").select("rid", tk.qbin(F.col("price"), tk.fit_borders(context(s, d, "line_num"), {"price": F.col("price")}, k)["price"]).alias("label"))
    )

_MIX = FIXTURES["line_mixed"]


def _mix_view(df: DataFrame, k: int = 2, name: str = "line_mixed"):
    f = FIXTURES[name]
    edges = tk.fit_borders(df, {a: F.col(a) for a in f.num}, k)
    return edges, tk.token_view(edges, list(f.cat))


def _mix_sql(k: int = 2, name: str = "line_mixed") -> str:
    """CTEs a (all rows), b (borders), m (tokens of all rows, one column an attribute)."""
    f = FIXTURES[name]
    cols = [f"Q[{a};{i / k!r}] AS b_{a}{i}" for a in f.num for i in range(1, k)]
    toks = [f"concat('q', cast({' + '.join(f'CASE WHEN {a} > b_{a}{i} THEN 1 ELSE 0 END' for i in range(1, k))} AS TEXT)) AS t_{a}" for a in f.num] + [f"{c} AS t_{c}" for c in f.cat]
    head = f"a AS {fx(name)}"
    if cols:
        head += f", bq AS (SELECT {', '.join(cols)} FROM a WHERE split = 'context')"
    return f"{head}, m AS (SELECT a.rid, a.split, a.is_anom, {', '.join(toks)} FROM a{', bq' if cols else ''})"


@query("quantile_tokens_line_mixed", f"WITH {_mix_sql(3)} SELECT rid, t_quantity, t_price FROM m")
def quantile_tokens(s, d):
    _, view = _mix_view(context(s, d, "line_mixed"), 3)
    return fixture(s, d, "line_mixed").select("rid", view["quantity"].alias("t_quantity"), view["price"].alias("t_price"))


_LC = FIXTURES["line_cat"].cat
_CAT_COUNTS = "SELECT attr, tok, count(*) AS n FROM (" + " UNION ALL ".join(f"SELECT '{a}' AS attr, {a} AS tok FROM c" for a in _LC) + ") AS u GROUP BY attr, tok"


def _cat_model(s, d, name="line_cat"):
    view = tk.token_view({}, list(FIXTURES[name].cat))
    return view, tk.TokenModel.fit(context(s, d, name), view)


@query("token_counts_line_cat", f"WITH c AS {ctx('line_cat')} {_CAT_COUNTS}")
def token_counts(s, d):
    return tk.token_counts(context(s, d, "line_cat"), tk.token_view({}, list(_LC)))


_PROB = f"WITH c AS {ctx('line_cat')}, k AS ({_CAT_COUNTS}), p AS (SELECT attr, tok, (n + 1.0) / ((SELECT count(*) FROM c) + count(*) OVER (PARTITION BY attr) + 1.0) AS p FROM k)"


def _prob_rows(s, d, f):
    counts = tk.token_counts(context(s, d, "line_cat"), tk.token_view({}, list(_LC)))
    n = context(s, d, "line_cat").count()
    p = (F.col("n") + tk.ALPHA) / (F.lit(n) + tk.ALPHA * (F.count("*").over(Window.partitionBy("attr")) + 1))
    return counts.select("attr", "tok", f(p))


query("smoothed_prob_line_cat", f"{_PROB} SELECT attr, tok, round(p, 6) AS prob FROM p")(lambda s, d: _prob_rows(s, d, lambda p: F.round(p, 6).alias("prob")))
query("token_rarity_line_cat", f"{_PROB} SELECT attr, tok, round(-ln(p), 6) AS rarity FROM p")(lambda s, d: _prob_rows(s, d, lambda p: F.round(-F.log(p), 6).alias("rarity")))

# ------------------------------------------------------------------ tasks

_HALF = drawn_subset(0, "L", list(_LN))
_W = {"L": tk.weights(0, "L", _HALF), "G": tk.weights(0, "G", list(_LN))}


def _rob(a: str) -> str:
    return f"({a} - m_{a}) / w_{a}"


def _labelled_sql(z: str, k: int, extra: str = "") -> str:
    return f"""WITH a AS {fx('line_num')}, r AS (SELECT {_ROBUST} FROM a WHERE split = 'context'), z AS (SELECT rid, split, {z} AS z FROM a, r),
    b AS {_borders_sql('z', k, "(SELECT * FROM z WHERE split = 'context')")} SELECT rid, z, ({_steps('z', k)})::INT AS label FROM z, b"""


def _scalar_label(df: DataFrame, z, k: int) -> DataFrame:
    zs = df.withColumn("z", z)
    b = tk.fit_borders(zs.filter("split = 'context'"), {"z": F.col("z")}, k)["z"]
    return zs.select("rid", "z", tk.qbin(F.col("z"), b).alias("label"))


def _numeric_label(s, d, z, k: int) -> DataFrame:
    """z: the scalar of a row as an expression of the fitted scales."""
    with held(context(s, d, "line_num").select(*_LN)) as c:
        e = z(tk.fit_robust(c, list(_LN)))
        b = tk.fit_borders(c, {"z": e}, k)["z"]
    return fixture(s, d, "line_num").select("rid", e.alias("z")).select("rid", "z", tk.qbin(F.col("z"), b).alias("label"))


query("single_numeric_label", f"WITH a AS {fx('line_num')}, b AS {_borders_sql('net', 3, '(SELECT * FROM a WHERE split = ' + chr(39) + 'context' + chr(39) + ')')} SELECT rid, ({_steps('net', 3)})::INT AS label FROM a, b")(
    lambda s, d: fixture(s, d, "line_num").select("rid", tk.qbin(F.col("net"), tk.fit_borders(context(s, d, "line_num"), {"net": F.col("net")}, 3)["net"]).alias("label"))
)


@query("single_category_label", f"WITH a AS {fx('line_cat')}, k AS (SELECT return_flag AS v, (row_number() OVER (ORDER BY return_flag) - 1)::INT AS label FROM (SELECT DISTINCT return_flag FROM a WHERE split = 'context') AS u) SELECT rid, coalesce(label, -1)::INT AS label FROM a LEFT JOIN k ON return_flag = v")
def single_category(s, d):
    view, m = _cat_model(s, d)
    classes = sorted(m.counts["return_flag"])
    return fixture(s, d, "line_cat").select("rid", F.coalesce(F.element_at(F.create_map(*(F.lit(x) for i, c in enumerate(classes) for x in (c, i))), view["return_flag"]), F.lit(-1)).alias("label"))


query("masked_numeric_label", _labelled_sql("round(" + " + ".join(f"{_rob(a)} * cast({w!r} AS double)" for a, w in zip(_HALF, _W["L"], strict=True)) + ", 6)", 2))(lambda s, d: _numeric_label(s, d, lambda t: tk.projection(t, _HALF, _W["L"]), 2))
query("global_numeric_label", _labelled_sql("round(" + " + ".join(f"{_rob(a)} * cast({w!r} AS double)" for a, w in zip(_LN, _W["G"], strict=True)) + ", 6)", 3))(lambda s, d: _numeric_label(s, d, lambda t: tk.projection(t, list(_LN), _W["G"]), 3))
query("radial_label", _labelled_sql("round(sqrt(" + " + ".join(f"{_rob(a)} * {_rob(a)}" for a in _LN) + "), 6)", 3))(lambda s, d: _numeric_label(s, d, lambda t: tk.radius(t, list(_LN)), 3))


def _token_sql(name: str, attrs: list[str], value: str, k: int, tok_bins: int = 2) -> str:
    """value: expression over {n} (context rows), {kj}, {nj} and {a}, {t} summed over attrs."""
    parts = []
    for j, a in enumerate(attrs):
        nj = f"coalesce((SELECT n FROM k_{a} WHERE tok = t_{a}), 0)"
        parts.append(value.format(n="(SELECT count(*) FROM m WHERE split = 'context')", kj=f"(SELECT count(*) FROM k_{a})", nj=nj, j=j, t=f"t_{a}"))
    counts = ", ".join(f"k_{a} AS (SELECT t_{a} AS tok, count(*) AS n FROM m WHERE split = 'context' GROUP BY t_{a})" for a in attrs)
    return f"""WITH {_mix_sql(tok_bins, name)}, {counts}, z AS (SELECT rid, split, round(({' + '.join(parts)}) / cast(DIV AS double), 6) AS z FROM m),
    b AS {_borders_sql('z', k, "(SELECT * FROM z WHERE split = 'context')")} SELECT rid, z, ({_steps('z', k)})::INT AS label FROM z, b"""


_RAR = "ln(({n} + {kj} + 1.0) / ({nj} + 1.0))"


def rarity_sql(**names: str) -> str:
    return _RAR.format(**names)


def _weighted(purpose: str) -> str:
    return _RAR + " * (sqrt(-2.0 * ln(1.0 - U['0';'" + purpose + ".a';concat('{j}|', {t})])) * cos(6.283185307179586 * U['0';'" + purpose + ".b';concat('{j}|', {t})]))"


def _token_query(name: str, attrs: list[str], rarity_only: bool, purpose: str, k: int):
    def run(s, d):
        df = fixture(s, d, name)
        c = df.filter("split = 'context'")
        _, view = _mix_view(c, 2, name)
        view = {a: view[a] for a in attrs}
        m = tk.TokenModel.fit(c, view)
        return _scalar_label(df, m.mean_rarity(view) if rarity_only else m.projected(0, purpose, view), k)

    return run


for _q, _fx, _attrs, _rare, _p, _k in (
    ("masked_category_label", "line_cat", drawn_subset(0, "L", list(_LC)), False, "token.L", 2),
    ("global_category_label", "line_cat", list(_LC), False, "token.G", 2),
    ("masked_mixed_label", "line_mixed", drawn_subset(0, "L", list(_MIX.attrs)), False, "token.L", 2),
    ("global_mixed_label", "line_mixed", list(_MIX.attrs), False, "token.G", 3),
    ("rarity_cat_label", "line_cat", list(_LC), True, "", 3),
    ("rarity_mixed_label", "line_mixed", list(_MIX.attrs), True, "", 2),
):
    query(_q, _token_sql(_fx, _attrs, _RAR if _rare else _weighted(_p), _k).replace("DIV", repr(float(len(_attrs)) if _rare else float(len(_attrs)) ** 0.5)))(_token_query(_fx, _attrs, _rare, _p, _k))


def _assigned(s, d, centres) -> DataFrame:
    """The nearest of the centres that centres(context, scales) gives."""
    with held(context(s, d, "line_num").select(*_LN)) as c:
        t = tk.fit_robust(c, list(_LN))
        m = centres(c, t)
    return fixture(s, d, "line_num").select("rid", tk.assign_kmeans(t, list(_LN), m).alias("label"))


_CENTRES = [[-0.5, -0.4, -0.3, -0.2], [0.6, 0.5, 0.4, 0.3], [0.1, 0.9, 0.8, 0.7]]
_MODES = [["5", "2", "1", "A", "O"], ["0", "7", "3", "N", "F"], ["10", "4", "5", "R", "O"]]


def _argmin(ds: list[str]) -> str:
    return "CASE " + " ".join(f"WHEN d{i} = least({', '.join(f'd{j}' for j in range(len(ds)))}) THEN {i}" for i in range(len(ds))) + " END::INT AS label"


query(
    "kmeans_assign_fixed",
    f"WITH a AS {fx('line_num')}, r AS (SELECT {_ROBUST} FROM a WHERE split = 'context'), dd AS (SELECT rid, "
    + ", ".join("round(" + " + ".join(f"({_rob(a)} - cast({m!r} AS double)) * ({_rob(a)} - cast({m!r} AS double))" for a, m in zip(_LN, c, strict=True)) + f", 6) AS d{i}" for i, c in enumerate(_CENTRES))
    + f" FROM a, r) SELECT rid, {_argmin(_CENTRES)} FROM dd",
)(lambda s, d: _assigned(s, d, lambda c, t: _CENTRES))

_KM = f"a AS {fx('line_cat')}, dd AS (SELECT *, " + ", ".join(" + ".join(f"({a} <> '{v}')::INT" for a, v in zip(_LC, m, strict=True)) + f" AS d{i}" for i, m in enumerate(_MODES)) + " FROM a)"
query("kmodes_assign_fixed", f"WITH {_KM} SELECT rid, {_argmin(_MODES)} FROM dd")(lambda s, d: fixture(s, d, "line_cat").select("rid", tk.assign_kmodes(list(_LC), _MODES).alias("label")))
query(
    "kmodes_one_step",
    f"WITH {_KM}, l AS (SELECT *, {_argmin(_MODES)} FROM dd WHERE split = 'context'), u AS (" + " UNION ALL ".join(f"SELECT label AS cluster, '{a}' AS attr, {a} AS tok FROM l" for a in _LC)
    + "), n AS (SELECT cluster, attr, tok, count(*) AS n FROM u GROUP BY ALL) SELECT cluster, attr, tok AS mode FROM (SELECT *, row_number() OVER (PARTITION BY cluster, attr ORDER BY n DESC, tok) AS r FROM n) WHERE r = 1",
)(lambda s, d: tk.update_modes(context(s, d, "line_cat"), tk.assign_kmodes(list(_LC), _MODES), list(_LC)))
_PROTOS = [([0.0, 0.0], _MODES[0]), ([1.0, 1.0], _MODES[1])]


@query(
    "kproto_assign_fixed",
    f"WITH {_mix_sql(2)}, dd AS (SELECT rid, "
    + ", ".join(
        "round((" + " + ".join(f"pow(cast(substr(t_{a}, 2) AS double) - {v}, 2)" for a, v in zip(_MIX.num, p, strict=True)) + ") / 2.0 + (" + " + ".join(f"(t_{a} <> '{v}')::INT" for a, v in zip(_MIX.cat, m, strict=True)) + f") / 5.0, 6) AS d{i}"
        for i, (p, m) in enumerate(_PROTOS)
    )
    + f" FROM m) SELECT rid, {_argmin(_PROTOS)} FROM dd",
)
def kproto_fixed(s, d):
    edges, _ = _mix_view(context(s, d, "line_mixed"))
    codes = {a: tk.qbin(F.col(a), b).cast("double") for a, b in edges.items()}
    return fixture(s, d, "line_mixed").select("rid", tk.assign_kproto(codes, list(_MIX.cat), _PROTOS).alias("label"))


@query("kmeans_fit")
def kmeans_fit(s, d):
    return _assigned(s, d, lambda c, t: tk.fit_kmeans(c, t, list(_LN), 3))


@query("kmodes_fit")
def kmodes_fit(s, d):
    m = tk.fit_kmodes(context(s, d, "line_cat"), list(_LC), 2)
    return fixture(s, d, "line_cat").select("rid", tk.assign_kmodes(list(_LC), m).alias("label"))


_OW_VIEWS = {"orders_num": FIXTURES["order_wide"].num, "orders_cat": FIXTURES["order_wide"].cat, "orders_wide": tuple(FIXTURES["order_wide"].attrs), "orders_total": ("total", *FIXTURES["order_wide"].cat)}


@query(
    "candidate_grid",
    f"""WITH k AS (SELECT dataset, kind FROM ({_types_sql("order_wide")}) AS ow JOIN (VALUES {", ".join(f"('{v}', '{a}')" for v, attrs in _OW_VIEWS.items() for a in attrs)}) AS vw(dataset, attr) ON name = attr
      UNION ALL SELECT 'parts', kind FROM ({_types_sql("part_dep")}) AS pd),
    q AS (SELECT dataset, sum((kind = 'numerical')::INT) AS nn, sum((kind = 'categorical')::INT) AS nc FROM k GROUP BY dataset),
    pr AS (SELECT dataset, CASE WHEN nc = 0 THEN 'numerical-only' WHEN nn = 0 THEN 'categorical-only' WHEN nc * 1.0 / (nn + nc) >= 0.8 THEN 'mixed-categorical-dominant' WHEN nn * 1.0 / (nn + nc) >= 0.8 THEN 'mixed-numerical-dominant' ELSE 'mixed' END AS profile FROM q WHERE nn + nc > 0),"""
    """p(profile, kind) AS (VALUES ('numerical-only', 'num'), ('categorical-only', 'cat'), ('mixed', 'mix'), ('mixed-numerical-dominant', 'mix'), ('mixed-categorical-dominant', 'mix')),
    t AS (SELECT profile, unnest(['G', 'P', 'D']) AS task, kind FROM p UNION ALL SELECT profile, 'L', kind FROM p WHERE profile NOT LIKE '%dominant'
      UNION ALL SELECT 'mixed-numerical-dominant', unnest(['L1', 'L2']), unnest(['num', 'mix']) UNION ALL SELECT 'mixed-categorical-dominant', unnest(['L1', 'L2']), unnest(['cat', 'mix']))
    SELECT dataset, profile, task, kind, CASE WHEN task = 'P' THEN k END AS clusters, CASE WHEN task <> 'P' THEN k END AS bins, CASE WHEN kind = 'num' THEN CASE WHEN i = 0 THEN 'raw' ELSE 'robust' END END AS transform,
      CASE WHEN kind = 'mix' THEN i + 2 END AS token_bins, CASE WHEN kind = 'cat' THEN i END AS draw FROM pr JOIN t USING (profile), (VALUES (2), (3)) AS a(k), (VALUES (0), (1)) AS b(i)""",
)
def candidate_grid(s, d):
    """Every axis of the tasks whose candidates do not depend on the data, for the profile that each data set turns out to have; a target's candidates are its bins."""
    ow = prof.infer_types(context(s, d, "order_wide"), FIXTURES["order_wide"].attrs).select("name", "kind")
    views = s.createDataFrame([(v, a) for v, attrs in _OW_VIEWS.items() for a in attrs], "dataset string, name string")
    kinds = views.join(ow, "name").select("dataset", "kind").unionAll(prof.infer_types(context(s, d, "part_dep"), FIXTURES["part_dep"].attrs).select(F.lit("parts"), "kind"))
    rows = [(p, t, k, *(x.get(c) for c in ("clusters", "bins", "transform", "token_bins", "draw"))) for p in PROFILES for t, k in instantiations(p) if t != "S" for x in axes(t, k)]
    grid = s.createDataFrame(rows, "profile string, task string, kind string, clusters int, bins int, transform string, token_bins int, draw int")
    return _profiles(kinds, "dataset").filter("d_num + d_cat > 0").select("dataset", "profile").join(F.broadcast(grid), "profile").select("dataset", *grid.columns)


# ------------------------------------------------------------------ held-out rows and probes


def _held_sql(sets: str, splits: str) -> str:
    return f"SELECT source, id, n, s AS splits, least(2048, ceil(cast(0.1 AS double) * n), floor(n / s), n - 1)::BIGINT AS h FROM ({sets}) AS r, (VALUES {splits}) AS v(s) WHERE n >= 2"


def _held_out(sets: DataFrame, splits: tuple[int, ...]) -> DataFrame:
    """sets with splits and h, the size of a fold as in kernels.selection; data sets of one row have none."""
    n, k = F.col("n"), F.col("splits")
    h = F.least(F.lit(2048), F.ceil(F.lit(0.1) * n), F.floor(n / k), n - 1).cast("long")
    return sets.filter("n >= 2").withColumn("splits", F.explode(F.array(*map(F.lit, splits)))).withColumn("h", h)


query("holdout_size_grid", _held_sql(_SETS, "(1), (3)"))(lambda s, d: _held_out(spark_sql(s, d, _SETS), (1, 3)))


@query("holdout_registry", f"WITH c AS {ctx('order_wide')}, n AS (SELECT count(*) AS n, least(2048, ceil(0.1 * count(*)), floor(count(*) / 3), count(*) - 1)::BIGINT AS h FROM c), r AS (SELECT rid, row_number() OVER (ORDER BY U['0';'fold';rid], rid) - 1 AS k FROM c) SELECT rid, (k // h)::INT AS fold FROM r, n WHERE k < 3 * h")
def holdout_registry(s, d):
    """Disjoint folds of one size by the order of a draw; only (draw, rid) pairs are sorted, and a top-n suffices."""
    c = context(s, d, "order_wide").select("rid", tk.u01(0, "fold", F.col("rid")).alias("u"))
    n = c.count()
    h = sel.holdout_size(n, 3)
    top = c.orderBy("u", "rid").limit(3 * h)  # bounded: three folds of at most 2048 rows
    return top.withColumn("k", F.row_number().over(Window.orderBy("u", "rid")) - 1).select("rid", F.floor(F.col("k") / h).cast("int").alias("fold"))


_DONOR = "(SELECT *, row_number() OVER (ORDER BY rid) - 1 AS row_no FROM c)"


def _numbered(df: DataFrame) -> DataFrame:
    """Consecutive numbers by rid; contexts are capped, so one sorted task holds them."""
    return df.withColumn("row_no", F.row_number().over(Window.orderBy("rid")) - 1)


def _probe_sql(attrs, hit: str) -> str:
    joins = " ".join(f"JOIN t AS d_{a} ON d_{a}.row_no = floor(U['0';'donor.{a}';c.rid] * n.n)" for a in attrs)
    cols = ", ".join(f"CASE WHEN {hit.format(a=a)} THEN d_{a}.{a} ELSE c.{a} END AS {a}" for a in attrs)
    return f"WITH c AS {ctx('order_wide')}, t AS {_DONOR}, n AS (SELECT count(*) AS n FROM c) SELECT c.rid, {cols} FROM c CROSS JOIN n {joins}"


def _probe(s, d, p: float | None):
    f = FIXTURES["order_wide"]
    c = context(s, d, "order_wide")
    t, n = _numbered(c), c.count()
    out = c
    for a in f.attrs:  # an independent donor for each cell: a join on the donor's number
        donor = t.select(F.col("row_no").alias(f"r_{a}"), F.col(a).alias(f"d_{a}"))
        out = out.join(donor, F.floor(tk.u01(0, f"donor.{a}", F.col("rid")) * n) == F.col(f"r_{a}"))
    cell = [F.when(F.lit(True) if p is None else tk.u01(0, f"hit.{a}", F.col("rid")) < p, F.col(f"d_{a}")).otherwise(F.col(a)).alias(a) for a in f.attrs]
    return out.select("rid", *cell)


_OW = FIXTURES["order_wide"].attrs
query("probe_shuffle", _probe_sql(_OW, "true"))(lambda s, d: _probe(s, d, None))
query("probe_replace", _probe_sql(_OW, "U['0';'hit.{a}';c.rid] < 0.3"))(lambda s, d: _probe(s, d, 0.3))


@query(
    "probe_jitter",
    f"WITH c AS {ctx('order_wide')}, r AS (SELECT " + ", ".join(f"Q[{a};0.75] - Q[{a};0.25] AS w_{a}" for a in FIXTURES["order_wide"].num) + " FROM c) SELECT rid, "
    + ", ".join(f"round({a} + 0.5 * w_{a} * (sqrt(-2.0 * ln(1.0 - U['0';'jit.{a}.a';rid])) * cos(6.283185307179586 * U['0';'jit.{a}.b';rid])), 4) AS {a}" for a in FIXTURES["order_wide"].num) + " FROM c, r",
)
def probe_jitter(s, d):
    c = context(s, d, "order_wide")
    num = list(FIXTURES["order_wide"].num)
    q = c.agg(*(F.percentile(a, F.array(F.lit(0.25), F.lit(0.75))).alias(a) for a in num)).first()

    def z(a):
        u, v = tk.u01(0, f"jit.{a}.a", F.col("rid")), tk.u01(0, f"jit.{a}.b", F.col("rid"))
        return F.sqrt(F.lit(-2.0) * F.log(F.lit(1.0) - u)) * F.cos(F.lit(6.283185307179586) * v)

    return c.select("rid", *(F.round(F.col(a) + F.lit(0.5) * F.lit(q[a][1] - q[a][0]) * z(a), 4).alias(a) for a in num))


@query("probe_budget", f"SELECT source, id, h, op, (h // 3 + CASE WHEN i < h % 3 THEN 1 ELSE 0 END)::BIGINT AS probes FROM ({_held_sql(_SETS, '(3)')}) AS hs, (VALUES ('shuffle', 0), ('replace', 1), ('jitter', 2)) AS v(op, i)")
def probe_budget(s, d):
    """The held-out rows of each data set dealt to the operators, the remainder to the first ones."""
    ops = ("shuffle", "replace", "jitter")
    each = _held_out(spark_sql(s, d, _SETS), (3,)).select("source", "id", "h", F.posexplode(F.array(*map(F.lit, ops))).alias("i", "op"))
    return each.select("source", "id", "h", "op", (F.floor(F.col("h") / len(ops)) + (F.col("i") < F.col("h") % len(ops)).cast("long")).alias("probes"))


@query("probe_marginals_kept", f"WITH p AS ({_probe_sql(_OW, 'true')}), c0 AS {ctx('order_wide')}, x AS (SELECT 'real' AS side, status, priority, segment, region_key FROM c0 UNION ALL SELECT 'probe', status, priority, segment, region_key FROM p) "
       + " UNION ALL ".join(f"SELECT side, '{a}' AS attr, {a} AS tok, count(*) AS n FROM x GROUP BY side, {a}" for a in FIXTURES["order_wide"].cat))
def probe_marginals(s, d):
    cat = list(FIXTURES["order_wide"].cat)
    both = context(s, d, "order_wide").select(F.lit("real").alias("side"), *cat).unionAll(_probe(s, d, None).select(F.lit("probe").alias("side"), *cat))
    return both.select("side", F.explode(F.array(*(F.struct(F.lit(a).alias("attr"), F.col(a).alias("tok")) for a in cat))).alias("t")).groupBy("side", "t.attr", "t.tok").agg(F.count("*").alias("n"))


@query(
    "total_correlation_pairs",
    f"WITH c AS {ctx('line_cat')}, n AS (SELECT count(*) * 1.0 AS n FROM c), "
    + ", ".join(f"j_{a}_{b} AS (SELECT round(sum(k / n * ln(k * n / (ka * kb))), 6) AS mi FROM (SELECT count(*) * 1.0 AS k, {a}, {b} FROM c GROUP BY {a}, {b}) JOIN (SELECT {a} AS va, count(*) AS ka FROM c GROUP BY 1) ON {a} = va JOIN (SELECT {b} AS vb, count(*) AS kb FROM c GROUP BY 1) ON {b} = vb, n)" for i, a in enumerate(_LC) for b in _LC[i + 1 :])
    + " " + " UNION ALL ".join(f"SELECT '{a}' AS a, '{b}' AS b, mi FROM j_{a}_{b}" for i, a in enumerate(_LC) for b in _LC[i + 1 :]),
)
def total_correlation(s, d):
    """Mutual information of each pair of categorical attributes, from one grouped count."""
    c = context(s, d, "line_cat")
    pairs = [(a, b) for i, a in enumerate(_LC) for b in _LC[i + 1 :]]
    rows = c.select(F.explode(F.array(*(F.struct(F.lit(a).alias("a"), F.lit(b).alias("b"), F.col(a).alias("va"), F.col(b).alias("vb")) for a, b in pairs))).alias("p")).groupBy("p.a", "p.b", "p.va", "p.vb").agg(F.count("*").cast("double").alias("k"))
    w = Window.partitionBy("a", "b")
    k = rows.withColumns({"n": F.sum("k").over(w), "ka": F.sum("k").over(Window.partitionBy("a", "b", "va")), "kb": F.sum("k").over(Window.partitionBy("a", "b", "vb"))})
    return k.groupBy("a", "b").agg(F.round(F.sum(F.col("k") / F.col("n") * F.log(F.col("k") * F.col("n") / (F.col("ka") * F.col("kb")))), 6).alias("mi"))


@query("label_agreement", f"""WITH a AS {fx('line_num')}, h AS (SELECT *, U['1';'half';rid] < 0.5 AS one FROM a WHERE split = 'context'),
    b AS (SELECT quantile_cont(price, 1.0 / 3) FILTER (WHERE one) AS x1, quantile_cont(price, 2.0 / 3) FILTER (WHERE one) AS x2, quantile_cont(price, 1.0 / 3) FILTER (WHERE NOT one) AS y1, quantile_cont(price, 2.0 / 3) FILTER (WHERE NOT one) AS y2 FROM h)
    SELECT round(avg(((price > x1)::INT + (price > x2)::INT = (price > y1)::INT + (price > y2)::INT)::INT), 6) AS agreement FROM a, b WHERE split = 'query'""")
def label_agreement(s, d):
    """Share of query rows whose label does not change when the parameters come from the other half of the context."""
    df = fixture(s, d, "line_num")
    c = df.filter("split = 'context'").withColumn("one", tk.u01(1, "half", F.col("rid")) < 0.5)
    x, y = (tk.fit_borders(c.filter(F.col("one") == v), {"price": F.col("price")}, 3)["price"] for v in (True, False))
    return df.filter("split = 'query'").agg(F.round(F.avg((tk.qbin(F.col("price"), x) == tk.qbin(F.col("price"), y)).cast("double")), 6).alias("agreement"))


# ------------------------------------------------------------------ backbone, calibration, detection


def _counts_sql(view: dict[str, str], label: str, tail: str) -> str:
    """view: attribute -> token column of m; label: its class column in m."""
    k = ", ".join(f"n_{a} AS (SELECT {label} AS y, {t} AS tok, count(*) AS n FROM m WHERE split = 'context' GROUP BY 1, 2), v_{a} AS (SELECT count(DISTINCT tok) AS kj FROM n_{a})" for a, t in view.items())
    logs = " + ".join(f"ln((coalesce(n_{a}.n, 0) + 1.0) / (z.ny + v_{a}.kj + 1.0))" for a in view)
    joins = " ".join(f"CROSS JOIN v_{a} LEFT JOIN n_{a} ON n_{a}.y = z.y AND n_{a}.tok = m.{t}" for a, t in view.items())
    return f"""{k}, z AS (SELECT {label} AS y, count(*) AS ny FROM m WHERE split = 'context' GROUP BY 1), tot AS (SELECT sum(ny) AS n FROM z),
    lp AS (SELECT m.rid, m.split, m.is_anom, m.{label} AS own, z.y, ln(z.ny / tot.n) + {logs} AS lp FROM m CROSS JOIN z CROSS JOIN tot {joins}),
    mx AS (SELECT rid, max(lp) AS top FROM lp GROUP BY rid),
    sup AS (SELECT lp.rid, any_value(split) AS split, any_value(is_anom) AS is_anom, round(coalesce(max(CASE WHEN y = own THEN exp(lp - top) END) / sum(exp(lp - top)), 1e-9), 6) AS kappa FROM lp JOIN mx USING (rid) GROUP BY lp.rid) {tail}"""


_LC_REST = [a for a in _LC if a != "return_flag"]


def _line_cat_support(s, d):
    df = fixture(s, d, "line_cat")
    view = tk.token_view({}, _LC_REST)
    y = F.col("return_flag")
    m = sc.fit_counts(df.filter("split = 'context'"), y, view)
    return df.select("rid", "split", "is_anom", sc.counts_support(m, y, view).alias("kappa"))


_LC_SQL = f"WITH m AS {fx('line_cat')}, " + _counts_sql({a: a for a in _LC_REST}, "return_flag", "{tail}")
query("counts_support_line_cat", _LC_SQL.replace("{tail}", "SELECT rid, kappa FROM sup"))(lambda s, d: _line_cat_support(s, d).select("rid", "kappa"))


@query("counts_support_line_mixed", f"WITH {_mix_sql(3)}, " + _counts_sql({a: f"t_{a}" for a in _MIX.attrs if a != "line_status"}, "t_line_status", "SELECT rid, kappa FROM sup"))
def counts_support_mixed(s, d):
    df = fixture(s, d, "line_mixed")
    _, view = _mix_view(df.filter("split = 'context'"), 3)
    y = view.pop("line_status")
    m = sc.fit_counts(df.filter("split = 'context'"), y, view)
    return df.select("rid", sc.counts_support(m, y, view).alias("kappa"))


@query("kernel_support_small", f"""WITH a AS {fx('supp_small')}, c AS (SELECT *, CASE WHEN balance > 4000 THEN 1 ELSE 0 END AS y FROM a WHERE split = 'context'), q AS (SELECT *, CASE WHEN balance > 4000 THEN 1 ELSE 0 END AS y FROM a WHERE split = 'query'),
    w AS (SELECT q.rid, q.y, c.y AS yc, exp(-pow((q.balance - c.balance) / 1000.0, 2)) AS w FROM q, c)
    SELECT rid, round((sum(CASE WHEN y = yc THEN w ELSE 0 END) + 0.001) / (sum(w) + 0.002), 6) AS kappa FROM w GROUP BY rid""")
def kernel_support_small(s, d):
    """Kernel mass of the whole context, added floor: every query against the distinct levels of the context."""
    df = fixture(s, d, "supp_small").withColumn("y", (F.col("balance") > 4000).cast("int"))
    c = df.filter("split = 'context'").groupBy(F.col("balance").alias("cx"), F.col("y").alias("cy")).agg(F.count("*").alias("n"))
    w = F.col("n") * F.exp(-F.pow((F.col("balance") - F.col("cx")) / 1000.0, F.lit(2.0)))
    pairs = df.filter("split = 'query'").select("rid", "balance", "y").crossJoin(c).select("rid", w.alias("w"), F.when(F.col("y") == F.col("cy"), w).otherwise(0.0).alias("own"))
    kappa = (F.sum("own") + 0.001) / (F.sum("w") + 0.002)
    return pairs.groupBy("rid").agg(F.round(kappa, 6).alias("kappa"))


# ------------------------------------------------------------------ selection, on a stated table of supports

_SUPPORT = """
SELECT task, cand, kind, round(CASE WHEN kind = 'nom' THEN pow(u, 0.25 + 0.1 * cand * t) ELSE pow(u, 0.9 + 0.05 * t) END, 4) AS kappa
FROM (SELECT task, t, cand, kind, U['7';'support';concat_ws('.', task, cand, kind, c_custkey)] AS u FROM customer
  CROSS JOIN (SELECT 'S' AS task, 1 AS t UNION ALL SELECT 'L', 2 UNION ALL SELECT 'G', 3 UNION ALL SELECT 'P', 20 UNION ALL SELECT 'D', 5) AS a
  CROSS JOIN (SELECT 1 AS cand UNION ALL SELECT 2 UNION ALL SELECT 3 UNION ALL SELECT 4) AS b CROSS JOIN (SELECT 'nom' AS kind UNION ALL SELECT 'vio') AS k) AS x
"""


def _support(s, d):
    return spark_sql(s, d, _SUPPORT)


_AUC = """lq AS (SELECT task, cand, kappa, sum((kind = 'nom')::INT) AS u, sum((kind = 'vio')::INT) AS v FROM sp GROUP BY task, cand, kappa),
    au AS (SELECT task, cand, round(sum(u * below) * 1.0 / (sum(u) * sum(v)), 6) AS rho FROM (SELECT *, coalesce(sum(v) OVER (PARTITION BY task, cand ORDER BY kappa ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0) AS below FROM lq) AS lb GROUP BY task, cand)"""
_CS = f"""WITH sp AS ({_SUPPORT}), {_AUC}, st AS (SELECT task, cand, round(quantile_cont(kappa, 0.5) FILTER (WHERE kind = 'nom'), 6) AS med, round(var_pop(kappa) FILTER (WHERE kind = 'nom'), 6) AS var, rho,
    round(quantile_cont(kappa, 0.25) FILTER (WHERE kind = 'nom') - quantile_cont(kappa, 0.75) FILTER (WHERE kind = 'vio'), 6) AS gap FROM sp JOIN au USING (task, cand) GROUP BY task, cand, rho)"""
query("separation_auc", f"WITH sp AS ({_SUPPORT}), {_AUC} SELECT task, cand, rho FROM au")(lambda s, d: sc.separation_auc(_support(s, d)))
query("cand_stats", f"{_CS} SELECT task, cand, med, var, rho, gap FROM st")(lambda s, d: sc.cand_stats(_support(s, d)))
_FI = f"{_CS}, fi AS (SELECT task, cand, med, var, rho, gap FROM (SELECT *, max((med >= 0.7)::INT) OVER (PARTITION BY task) AS ok, row_number() OVER (PARTITION BY task ORDER BY rho DESC, cand) AS r FROM st) WHERE (ok = 1 AND med >= 0.7) OR (ok = 0 AND r = 1))"
query("intra_filter", f"{_FI} SELECT * FROM fi")(lambda s, d: sc.intra_filter(sc.cand_stats(_support(s, d))))
_SH = f"{_FI}, sh AS (SELECT task, cand, med, var, rho, gap FROM (SELECT *, count(*) OVER (PARTITION BY task) AS n, row_number() OVER (PARTITION BY task ORDER BY rho DESC, cand) AS r FROM fi) WHERE r <= least(n, greatest(2, ceil(0.7 * n))))"
query("intra_shortlist", f"{_SH} SELECT * FROM sh")(lambda s, d: sc.intra_shortlist(sc.cand_stats(_support(s, d))))


def _rank_sql(col: str, part: str) -> str:
    w = f"PARTITION BY {part} " if part else ""
    return f"((rank() OVER ({w}ORDER BY {col}) + (count(*) OVER ({f'PARTITION BY {part}, {col}' if part else f'PARTITION BY {col}'}) - 1) / 2.0 - 1) / greatest(1, count(*) OVER ({w.strip()}) - 1))"


_PK = f"{_SH}, bd AS (SELECT *, round({_rank_sql('-med', 'task')} + {_rank_sql('var', 'task')} + {_rank_sql('-gap', 'task')}, 6) AS badness FROM sh), pk AS (SELECT task, cand, med, var, rho, gap, badness FROM (SELECT *, row_number() OVER (PARTITION BY task ORDER BY badness, cand) AS r FROM bd) WHERE r = 1)"
query("intra_pick", f"{_PK} SELECT * FROM pk")(lambda s, d: sc.intra_pick(sc.cand_stats(_support(s, d))))


def _reps(s, d):
    return sc.intra_pick(sc.cand_stats(_support(s, d))).drop("badness")


_PF = f"{_PK}, pf AS (SELECT task, cand, med, var, rho, gap FROM (SELECT *, max((rho >= 0.5)::INT) OVER () AS ok, row_number() OVER (ORDER BY rho DESC, task) AS r FROM pk) WHERE (ok = 1 AND rho >= 0.5) OR (ok = 0 AND r = 1))"
query("inter_prefilter", f"{_PF} SELECT * FROM pf")(lambda s, d: sc.inter_prefilter(_reps(s, d)))
_RK = f"{_PF}, ib AS (SELECT task, cand, round(1.5 * {_rank_sql('-rho', '')} + {_rank_sql('-med', '')} + {_rank_sql('var', '')} + {_rank_sql('-gap', '')}, 6) AS badness FROM pf), rk AS (SELECT *, row_number() OVER (ORDER BY badness, task)::INT AS place, count(*) OVER () AS n FROM ib)"
query("inter_rank", f"{_RK} SELECT task, cand, badness, place, n FROM rk")(lambda s, d: sc.inter_rank(_reps(s, d)))
for _p, _c in (("all", "true"), ("best", "place = 1"), ("topk", "place <= ceil(n * 0.5)")):
    query(f"retain_{_p}", f"{_RK} SELECT task, cand, badness, place FROM rk WHERE {_c}")(lambda s, d, p=_p: sc.retain(sc.inter_rank(_reps(s, d)), p))

# ------------------------------------------------------------------ ensembles, on a stated table of task scores

_SCORES = "SELECT c_custkey AS id, " + ", ".join(f"round(-ln(1 - U['5';'s{i}';c_custkey]), 6) AS s{i}" for i in range(4)) + " FROM customer"


def _scores(s, d):
    return spark_sql(s, d, _SCORES).select("id", F.array(*(f"s{i}" for i in range(4))).alias("s"))


_BAGG = [1.0, 2.0, 2.5, 1.75]  # suitability of the four tasks in this stated case
_WRAW = [1 / (r + 0.1) for r in sel.bad_rank(_BAGG, False)]
_WN = [round(float(w / sum(_WRAW)), 9) for w in _WRAW]
query("ensemble_min", f"WITH t AS ({_SCORES}) SELECT id, least(s0, s1, s2, s3) AS score FROM t")(lambda s, d: _scores(s, d).select("id", sc.ens_min(F.col("s")).alias("score")))
query("ensemble_low2mean", f"WITH t AS ({_SCORES}) SELECT id, list_avg(list_sort([s0, s1, s2, s3])[1:2]) AS score FROM t")(lambda s, d: _scores(s, d).select("id", sc.ens_low2mean(F.col("s")).alias("score")))
query("ensemble_weighted", f"WITH t AS ({_SCORES}) SELECT id, round({' + '.join(f's{i} * cast({w!r} AS double)' for i, w in enumerate(_WN))}, 6) AS score FROM t")(lambda s, d: _scores(s, d).select("id", F.round(sc.ens_weighted(F.col("s"), _WN), 6).alias("score")))
# the spread of these is 1.5, so the most suitable task alone decides
query("ensemble_spread", f"WITH t AS ({_SCORES}) SELECT id, s0 AS score FROM t")(
    lambda s, d: _scores(s, d).select("id", (sc.ens_min(F.col("s")) if len(_BAGG) >= 3 and max(_BAGG) - min(_BAGG) < 1.0 else F.element_at("s", _BAGG.index(min(_BAGG)) + 1)).alias("score"))
)

# ------------------------------------------------------------------ measures, on stated tables

_SCORED = "SELECT concat('d', cast(o_custkey % 7 AS TEXT)) AS dataset, CASE WHEN o_orderstatus = 'F' THEN 1 ELSE 0 END AS is_anom, round(U['3';'score';o_orderkey] + CASE WHEN o_orderstatus = 'F' THEN 0.2 ELSE 0 END, 2) AS score FROM orders"
query("auroc_by_dataset", f"WITH a AS ({_SCORED}), g AS (SELECT dataset, score, sum(is_anom) AS p, sum(1 - is_anom) AS q FROM a GROUP BY ALL) SELECT x.dataset, round(sum(CASE WHEN x.score > y.score THEN x.p * y.q WHEN x.score = y.score THEN x.p * y.q / 2.0 ELSE 0 END) / (SELECT sum(p) * 1.0 * sum(q) FROM g WHERE g.dataset = x.dataset), 6) AS auroc FROM g x JOIN g y ON x.dataset = y.dataset GROUP BY x.dataset")(
    lambda s, d: sc.auroc(spark_sql(s, d, _SCORED))
)
query("ap_by_dataset", f"WITH a AS ({_SCORED}), g AS (SELECT dataset, score, sum(is_anom) AS p, sum(1 - is_anom) AS q FROM a GROUP BY ALL), w AS (SELECT *, sum(p) OVER v AS cp, sum(q) OVER v AS cq FROM g WINDOW v AS (PARTITION BY dataset ORDER BY score DESC)) SELECT dataset, round(sum(p * cp / (cp + cq)) / sum(p), 6) AS ap FROM w GROUP BY dataset")(
    lambda s, d: sc.average_precision(spark_sql(s, d, _SCORED))
)

_RESULTS = """SELECT n_name AS dataset, method, round(0.6 + 0.03 * k + 0.3 * U['9';'res';concat(n_name, method)], 2) AS value, cast(n_nationkey AS bigint) * 700 AS n_rows FROM nation
CROSS JOIN (SELECT 'm1' AS method, 1 AS k UNION ALL SELECT 'm2', 2 UNION ALL SELECT 'm3', 3 UNION ALL SELECT 'm4', 1 UNION ALL SELECT 'm5', 0 UNION ALL SELECT 'm6', 4) AS m"""


def _results(s, d):
    return spark_sql(s, d, _RESULTS)


_RR = f"WITH r AS ({_RESULTS}), k AS (SELECT *, rank() OVER (PARTITION BY dataset ORDER BY value DESC) AS rnk FROM r)"
query("avg_rank", f"{_RR} SELECT method, round(avg(rnk), 6) AS avg_rank FROM k GROUP BY method")(lambda s, d: cmp.avg_rank(_results(s, d)))
query("top3_ratio", f"{_RR} SELECT method, round(avg((rnk <= 3)::INT), 6) AS top_ratio FROM k GROUP BY method")(lambda s, d: cmp.topk_ratio(_results(s, d)))
query("rank_box", f"{_RR} SELECT method, " + ", ".join(f"round(quantile_cont(rnk, {p}), 6) AS {n}" for n, p in (("lo", 0.0), ("q1", 0.25), ("mid", 0.5), ("q3", 0.75), ("hi", 1.0))) + " FROM k GROUP BY method")(lambda s, d: cmp.rank_box(_results(s, d)))
_WM = f"WITH r AS ({_RESULTS}), wm AS (SELECT x.method AS a, y.method AS b, sum(CASE WHEN x.value > y.value THEN 1.0 WHEN x.value = y.value THEN 0.5 ELSE 0.0 END)::DOUBLE AS points, count(*) AS games FROM r x JOIN r y ON x.dataset = y.dataset AND x.method <> y.method GROUP BY 1, 2)"
query("win_matrix", f"{_WM} SELECT * FROM wm")(lambda s, d: cmp.win_matrix(_results(s, d)))
_ELO = _WM.replace("WITH ", "WITH RECURSIVE ", 1) + """, it(i, method, beta) AS (SELECT 0, a, 1.0::DOUBLE FROM wm GROUP BY a UNION ALL
    SELECT i + 1, method, raw / exp(avg(ln(raw)) OVER ()) FROM (SELECT x.i, x.method, (SELECT sum(points) FROM wm WHERE wm.a = x.method) / sum(wm.games / (x.beta + y.beta)) AS raw FROM it x JOIN it y ON x.i = y.i AND x.method <> y.method JOIN wm ON wm.a = x.method AND wm.b = y.method WHERE x.i < 40 GROUP BY x.i, x.method))
    """
query("elo_iterated", _ELO + " SELECT method, round(1000 + 400 * log10(beta), 4) AS elo FROM it WHERE i = 40")(lambda s, d: cmp.elo(_results(s, d), 40))
query("elo_expected", _ELO + ", e AS (SELECT method, round(1000 + 400 * log10(beta), 4) AS elo FROM it WHERE i = 40) SELECT x.method AS a, y.method AS b, round(1 / (1 + pow(10, (y.elo - x.elo) / 400)), 6) AS expected FROM e x JOIN e y ON x.method < y.method")(
    lambda s, d: cmp.elo_expected(cmp.elo(_results(s, d), 40))
)


@query("total_rank", f"{_RR}, m AS (SELECT method, avg(value) AS v, avg(rnk) AS ar, avg((rnk <= 3)::INT) AS t FROM k GROUP BY method) SELECT method, round((rank() OVER (ORDER BY round(v, 6) DESC) + rank() OVER (ORDER BY round(t, 6) DESC) + rank() OVER (ORDER BY round(ar, 6))) / 3.0, 6) AS total_rank FROM m")
def total_rank(s, d):
    r = _results(s, d)
    m = r.groupBy("method").agg(F.round(F.avg("value"), 6).alias("v")).join(cmp.topk_ratio(r), "method").join(cmp.avg_rank(r), "method")
    return cmp.total_rank(m, ["v", "top_ratio"], ["avg_rank"])


_HOLES = f"(SELECT * FROM ({_RESULTS}) AS h0 WHERE U['9';'hole';concat(dataset, method)] >= 0.2)"
query("impute_missing", f"WITH r AS (SELECT dataset, method, value FROM {_HOLES}), g AS (SELECT n_name AS dataset, m.method FROM nation, (SELECT DISTINCT method FROM r) m) SELECT g.dataset, g.method, round(coalesce(value, avg(value) OVER (PARTITION BY g.dataset)), 6) AS value, value IS NULL AS imputed FROM g LEFT JOIN r ON r.dataset = g.dataset AND r.method = g.method")(
    lambda s, d: (lambda r: cmp.impute(r, spark_sql(s, d, "SELECT n_name AS dataset FROM nation"), r.select("method").distinct()))(spark_sql(s, d, f"SELECT dataset, method, value FROM {_HOLES} AS h1"))
)
query("complete_only", f"WITH r AS (SELECT dataset, method, value FROM {_HOLES}) SELECT dataset, method, value FROM (SELECT *, count(*) OVER (PARTITION BY dataset) AS k FROM r) WHERE k = 6")(lambda s, d: cmp.complete_only(spark_sql(s, d, f"SELECT dataset, method, value FROM {_HOLES} AS h1"), 6))
query("size_groups", f"WITH r AS ({_RESULTS}) SELECT CASE WHEN n_rows < 1000 THEN 'below 1K' WHEN n_rows < 10000 THEN '1K-10K' ELSE '10K and more' END AS size_group, method, round(avg(value), 6) AS mean_value FROM r GROUP BY 1, 2")(
    lambda s, d: _results(s, d).groupBy(cmp.size_group(F.col("n_rows")).alias("size_group"), "method").agg(F.round(F.avg("value"), 6).alias("mean_value"))
)


@query(
    "cost_counters",
    f"""SELECT source, id, m, g, splits AS s, h, m * g * splits AS fit_calls, m * g * splits * 2 * h AS fit_rows, m * n AS score_rows, d * n AS chain_rows, d FROM ({_held_sql(_LINE_SETS, "(1), (3)")}) AS hs,
    (VALUES (5::BIGINT), (6::BIGINT)) a(m), (VALUES (4::BIGINT), (8::BIGINT)) b(g), (VALUES (4::BIGINT), (50::BIGINT)) f(d)""",
)
def cost_counters(s, d):
    """Costs of a detector on each data set of lines, by tasks, candidates, folds and attributes."""
    from vtask.plans.cost import counters

    sets = _held_out(spark_sql(s, d, _LINE_SETS), (1, 3))
    for c, values in (("m", (5, 6)), ("g", (4, 8)), ("d", (4, 50))):
        sets = sets.withColumn(c, F.explode(F.array(*(F.lit(v).cast("long") for v in values))))
    names = "m g s h fit_calls fit_rows score_rows chain_rows d".split()
    return sets.select("source", "id", *(v.alias(c) for c, v in zip(names, counters(*map(F.col, ("m", "g", "splits", "h", "n", "d"))), strict=True)))
