"""The whole detector as one Spark plan, on categorical attributes with the count backbone.

Fitting holds a bounded context (the published cap), counts its tokens by class
and fold in one aggregation for all candidates, and takes a fold's counts off
for the context that a held-out row is scored against. Supports of all (task,
candidate, fold) are one plan: evaluation rows against classes and counts, both
bounded. Selection, calibration and ensemble follow on grouped rows. Scoring a
table is a projection with the kept tasks' counts as literals.

Every step has its SQL twin: SQL() states the same plan for the other engine.
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from vtask.kernels import selection as sel
from vtask.kernels.draws import drawn_subset
from vtask.operators import scoring as sc
from vtask.operators import tasks as tk
from vtask.plans.queries import _RK, _SUPPORT, _weighted, fx, query, rarity_sql
from vtask.sources.fixtures import FIXTURES, fixture

#: Rows of a context, as published.
CONTEXT_CAP = 100_000
FOLDS = 3
OPS = ("shuffle", "replace")  # jitter needs numbers
#: Counts that come to the driver: candidates x classes x tokens x folds, bounded by the type rule.
COUNTS_MOST = 1_000_000


@dataclass(frozen=True)
class Scalar:
    """A binned scalar: a projection (weights drawn by purpose) or the mean rarity, over some attributes."""

    task: str
    draw: int
    attrs: tuple[str, ...]
    rare: bool
    bins: int

    @property
    def cand(self) -> str:
        return f"{self.task}:{self.draw}:b{self.bins}"

    @property
    def purpose(self) -> str:
        return f"token.{self.task}" + (f"#{self.draw}" if self.draw else "")


def candidates(attrs: list[str], seed: int = 0, templates: str = "SLGD") -> list[Scalar]:
    """Four candidates for each scalar task: two bin numbers, two independent draws."""
    out = []
    for task in "LGD":
        for draw in (0, 1) if task in templates else ():
            some = drawn_subset(seed, f"{task}#{draw}" if draw else task, attrs) if task == "L" or (task == "D" and draw) else attrs
            out += [Scalar(task, draw, tuple(some), task == "D", b) for b in (2, 3)]
    return out


def eligible_targets(counts: dict[str, dict[str, int]], n: int, most: int = 4) -> list[str]:
    """Categorical targets with no degenerate or sparse classes, by falling entropy."""
    import math

    ok = []
    for a, c in counts.items():
        k = list(c.values())
        if 2 <= len(k) <= 10 and min(k) >= max(5, 0.01 * n) and max(k) <= 0.95 * n:
            ok.append((round(sum(x / n * math.log(x / n) for x in k), 9), a))
    return [a for _, a in sorted(ok)][:most]


# ------------------------------------------------------------------ Spark


class Fit:
    """Context, folds and labels of every candidate, and the counts behind all supports."""

    def __init__(self, df: DataFrame, attrs: list[str], templates: str = "SLGD", seed: int = 0, cap: int = CONTEXT_CAP):
        self.attrs, self.seed = attrs, seed
        view = self.view = tk.token_view({}, attrs)
        c = df.filter("split = 'context'").select("rid", *(view[a].alias(a) for a in attrs))
        total = c.count()
        if total > cap:
            c = c.orderBy(tk.u01(seed, "ctx", F.col("rid")), "rid").limit(cap)
        self.n = min(total, cap)
        self.h = sel.holdout_size(self.n, FOLDS)
        held = c.select("rid", tk.u01(seed, "fold", F.col("rid")).alias("u")).orderBy("u", "rid").limit(FOLDS * self.h).collect()  # bounded: three folds of at most 2048
        places = df.sparkSession.createDataFrame(list({r.rid: k // self.h for k, r in enumerate(held)}.items()), "rid string, fold int")
        self.context = c.join(F.broadcast(places), "rid", "left").select("rid", *attrs, F.coalesce("fold", F.lit(-1)).alias("fold")).repartition(df.sparkSession.sparkContext.defaultParallelism, "rid").cache()
        model = tk.TokenModel.fit(self.context, {a: F.col(a) for a in attrs})
        self.targets = eligible_targets(model.counts, self.n) if "S" in templates else []
        scalars = candidates(attrs, seed, templates)
        cols = {a: F.col(a) for a in attrs}

        def z(x: Scalar) -> Column:
            some = {a: cols[a] for a in x.attrs}
            return model.mean_rarity(some) if x.rare else model.projected(seed, x.purpose, some)

        # scalars are columns of their own, so that no label repeats their expression
        self.scalars = {f"z_{x.task}{x.draw}": z(x) for x in scalars}
        self.context = self.context.withColumns(self.scalars).cache()
        quant = self.context.agg(*(F.percentile(f"z_{x.task}{x.draw}", F.array(*(F.lit(i / x.bins) for i in range(1, x.bins)))).alias(x.cand) for x in scalars)).first() if scalars else {}
        # a candidate's label and what predicts it
        self.labels = {f"S:{a}": (cols[a], [b for b in attrs if b != a]) for a in self.targets}
        self.labels |= {x.cand: (tk.qbin(F.col(f"z_{x.task}{x.draw}"), sorted(set(quant[x.cand]))).cast("string"), attrs) for x in scalars}

    def rows(self, df: DataFrame, *keep: str) -> DataFrame:
        """A row a candidate: keep, cand, own label, tokens that predict it."""
        each = [F.struct(F.lit(c).alias("cand"), y.alias("own"), F.array(*(F.struct(F.lit(a).alias("attr"), F.col(a).alias("tok")) for a in p)).alias("toks")) for c, (y, p) in self.labels.items()]
        df = df if set(self.scalars) <= set(df.columns) else df.withColumns(self.scalars)
        return df.select(*keep, F.explode(F.array(*each)).alias("x")).select(*keep, "x.*")

    def counts(self) -> list:
        """(cand, y, attr, tok, fold, n) of the context; an empty attr counts rows."""
        toks = F.concat("toks", F.array(F.struct(F.lit("").alias("attr"), F.lit("").alias("tok"))))
        got = self.rows(self.context, "fold").select("cand", F.col("own").alias("y"), F.explode(toks).alias("t"), "fold").groupBy("cand", "y", "t.attr", "t.tok", "fold").agg(F.count("*").alias("n")).limit(COUNTS_MOST + 1).collect()
        if len(got) > COUNTS_MOST:
            raise ValueError("too many counts: not categorical by the type rule")
        return got

    def probes(self) -> DataFrame:
        """(rid, fold, attrs) of broken rows: an independent donor of the fold's train side for each cell; at most h a fold."""
        pdf = self.context.select("rid", "fold", *self.attrs).toPandas().sort_values("rid", ignore_index=True)  # bounded by the cap
        out = []
        from vtask.kernels.draws import u01

        for s in range(FOLDS):
            train, own = pdf[pdf["fold"] != s], pdf[pdf["fold"] == s]
            cells = {a: train[a].to_numpy() for a in self.attrs}
            for op, size in sel.probe_budget(self.h, list(OPS)).items():
                order = sorted(own.index, key=lambda i: (u01(self.seed, f"base.{op}", own["rid"][i]), own["rid"][i]))[:size]
                for i in order:
                    rid, row = own["rid"][i], {}
                    for a in self.attrs:
                        hit = op == "shuffle" or u01(self.seed, f"hit.{a}.{op}", rid) < 0.3
                        row[a] = str(cells[a][int(u01(self.seed, f"donor.{a}.{op}", rid) * len(train))]) if hit else own[a][i]
                    out.append((f"{op}|{rid}", s, *row.values()))
        return self.context.sparkSession.createDataFrame(out, "rid string, fold int, " + ", ".join(f"{a} string" for a in self.attrs))

    def supports(self) -> DataFrame:
        """(task, cand, kind, kappa) of held-out rows and probes, each against the context without its fold: one plan for all."""
        spark = self.context.sparkSession
        self.full = self.counts()
        less = {}
        for r in self.full:
            for s in range(FOLDS):
                if r.fold != s:
                    k = (r.cand, s, r.y, r.attr, r.tok)
                    less[k] = less.get(k, 0) + r.n
        n = spark.createDataFrame([(*k, v) for k, v in less.items()], "cand string, fold int, y string, attr string, tok string, n long")
        size = n.filter("attr = ''").select("cand", "fold", "y", F.col("n").alias("ny"))
        every = size.groupBy("cand", "fold").agg(F.sum("ny").alias("nn"), F.count("*").alias("classes"))
        kj = n.filter("attr <> ''").groupBy("cand", "fold", "attr").agg(F.count_distinct("tok").alias("kj"))
        held = self.context.filter("fold >= 0").withColumn("kind", F.lit("nom")).unionByName(self.probes().withColumns(self.scalars).withColumn("kind", F.lit("vio")))
        e = self.rows(held, "rid", "fold", "kind").join(F.broadcast(size.join(every.filter("classes > 1"), ["cand", "fold"])), ["cand", "fold"])
        t = e.select("cand", "fold", "kind", "rid", "own", "y", "ny", "nn", F.explode("toks").alias("t")).select("*", "t.attr", "t.tok")
        t = t.join(F.broadcast(kj), ["cand", "fold", "attr"]).join(F.broadcast(n), ["cand", "fold", "y", "attr", "tok"], "left")
        term = F.log((F.coalesce("n", F.lit(0)) + tk.ALPHA) / (F.col("ny") + tk.ALPHA * (F.col("kj") + 1)))
        lp = t.groupBy("cand", "fold", "kind", "rid", "own", "y", "ny", "nn").agg(F.sum(term).alias("s")).withColumn("lp", F.log(F.col("ny") / F.col("nn")) + F.col("s"))
        by = lp.groupBy("cand", "fold", "kind", "rid", "own").agg(F.collect_list(F.struct("y", "lp")).alias("c"))  # a few classes
        top = F.array_max("c.lp")
        mass = F.aggregate("c", F.lit(0.0), lambda a, x: a + F.exp(x["lp"] - top))
        own = F.aggregate(F.filter("c", lambda x: x["y"] == F.col("own")), F.lit(0.0), lambda a, x: a + F.exp(x["lp"] - top))
        kappa = F.round(F.when(own > 0, own / mass).otherwise(F.lit(sc.EPS)), 6)
        return by.select(F.substring("cand", 1, 1).alias("task"), "cand", "kind", kappa.alias("kappa"))

    def scores(self, df: DataFrame, support: DataFrame, kept: list[str]) -> DataFrame:
        """(rid, is_anom, s: calibrated surprisals of the kept candidates) of the query rows: a projection."""
        levels = {c: [] for c in kept}
        for r in support.filter("kind = 'nom'").filter(F.col("cand").isin(kept)).groupBy("cand", "kappa").agg(F.count("*").alias("n")).collect():  # at most the held-out rows
            levels[r.cand] += [r.kappa] * r.n
        q = df.filter("split = 'query'").select("rid", "is_anom", *(self.view[a].alias(a) for a in self.attrs))
        q = q.withColumns(self.scalars).withColumns({f"y{i}": self.labels[c][0] for i, c in enumerate(kept)})
        out = []
        for i, c in enumerate(kept):
            predictors = self.labels[c][1]
            model = {"size": {}, "table": {a: {} for a in predictors}}
            for r in self.full:
                if r.cand == c:
                    slot = model["size"] if r.attr == "" else model["table"][r.attr].setdefault(r.tok, {})
                    slot[r.y] = slot.get(r.y, 0) + r.n
            out.append(sc.surprisal(sc.counts_support(model, F.col(f"y{i}"), {a: F.col(a) for a in predictors}), levels[c]))
        return q.select("rid", "is_anom", F.array(*out).alias("s"))


def _fit(s, d, templates: str = "SLGD") -> tuple[DataFrame, Fit]:
    df = fixture(s, d, "line_cat")
    return df, Fit(df, list(FIXTURES["line_cat"].cat), templates)


# ------------------------------------------------------------------ the SQL twin

_A = list(FIXTURES["line_cat"].cat)
_CANDS = candidates(_A)


def _z_sql(x: Scalar) -> str:
    terms = []
    for j, a in enumerate(x.attrs):
        r = rarity_sql(n="nc.n", kj=f"q_{a}.kj", nj=f"coalesce(k_{a}.n, 0)") if x.rare else _weighted(x.purpose).format(n="nc.n", kj=f"q_{a}.kj", nj=f"coalesce(k_{a}.n, 0)", j=j, t=f"e.{a}")
        terms.append(r)
    return f"round(({' + '.join(terms)}) / cast({float(len(x.attrs)) if x.rare else float(len(x.attrs)) ** 0.5!r} AS double), 6)"


def SQL(tail: str, only: str = "") -> str:  # noqa: N802
    """CTEs up to sp(task, cand, kind, kappa), the supports, and ql(cand, rid, is_anom, kappa) for the query rows of the candidates in kp; tail goes on from sp."""
    name = {(x.task, x.draw): f"z_{x.task}{x.draw}" for x in _CANDS}
    zs = ", ".join(f"{_z_sql(next(x for x in _CANDS if (x.task, x.draw) == k))} AS {v}" for k, v in name.items())
    qs = ", ".join(f"quantile_cont({name[x.task, x.draw]}, {i / x.bins!r}) AS {name[x.task, x.draw]}_{x.bins}_{i}" for x in _CANDS for i in range(1, x.bins))

    def steps(x: Scalar) -> str:
        z = name[x.task, x.draw]
        return " + ".join(f"CASE WHEN {z} > {z}_{x.bins}_{i}" + (f" AND {z}_{x.bins}_{i} > {z}_{x.bins}_{i - 1}" if i > 1 else "") + " THEN 1 ELSE 0 END" for i in range(1, x.bins))

    labs = ", ".join([f"{{'cand': '{x.cand}', 'own': cast({steps(x)} AS TEXT)}}" for x in _CANDS] + [f"{{'cand': 'S:{a}', 'own': {a}}}" for a in _A])
    toks = ", ".join(f"{{'attr': '{a}', 'tok': {a}}}" for a in _A)
    probes = []
    for i, op in enumerate(OPS):
        cells = ", ".join((f"d_{a}.{a}" if op == "shuffle" else f"CASE WHEN U['0';'hit.{a}.{op}';b.rid] < 0.3 THEN d_{a}.{a} ELSE b.{a} END") + f" AS {a}" for a in _A)
        joins = " ".join(f"JOIN tr AS d_{a} ON d_{a}.at = b.fold * {2 * CONTEXT_CAP} + cast(floor(U['0';'donor.{a}.{op}';b.rid] * b.nt) AS bigint)" for a in _A)
        probes.append(f"SELECT '{op}|' || b.rid AS rid, b.fold, 'vio' AS kind, 0 AS is_anom, {cells} FROM (SELECT fo.*, nt, row_number() OVER (PARTITION BY fold ORDER BY U['0';'base.{op}';rid], rid) AS i FROM fo JOIN tn ON tn.s = fo.fold) AS b CROSS JOIN hh {joins} WHERE b.i <= h // {len(OPS)} + CASE WHEN {i} < h % {len(OPS)} THEN 1 ELSE 0 END")
    cols = ", ".join(_A)
    logs = "ln((coalesce(n.n, 0) + 1.0) / (z.ny + kj.kj + 1.0))"

    def sup(where: str) -> str:
        return f"""SELECT cand, fold, kind, rid, is_anom, round(coalesce(sum(CASE WHEN y = own THEN exp(lp - top) END) / sum(exp(lp - top)), 1e-9), 6) AS kappa FROM (SELECT *, max(lp) OVER (PARTITION BY cand, kind, rid) AS top FROM (
      SELECT l.cand, l.fold, l.kind, l.rid, l.is_anom, l.own, z.y, ln(z.ny / nn.n) + sum({logs}) AS lp FROM (SELECT cand, fold, kind, rid, is_anom, own, unnest(toks) AS t FROM la WHERE {where}) AS l JOIN nn ON nn.cand = l.cand AND nn.s = l.fold JOIN z ON z.cand = l.cand AND z.s = l.fold
      JOIN kj ON kj.cand = l.cand AND kj.s = l.fold AND kj.attr = l.t.attr LEFT JOIN n ON n.cand = l.cand AND n.s = l.fold AND n.y = z.y AND n.attr = l.t.attr AND n.tok = l.t.tok
      WHERE nn.classes > 1 GROUP BY l.cand, l.fold, l.kind, l.rid, l.is_anom, l.own, z.y, z.ny, nn.n) AS g) AS w GROUP BY cand, fold, kind, rid, is_anom"""

    counted = ", ".join(f"k_{a} AS (SELECT {a} AS tok, count(*) AS n FROM fo GROUP BY {a}), q_{a} AS (SELECT count(*) AS kj FROM k_{a})" for a in _A)
    beside = " ".join(f"CROSS JOIN q_{a} LEFT JOIN k_{a} ON k_{a}.tok = e.{a}" for a in _A)
    ents = " UNION ALL ".join(f"SELECT '{a}' AS attr, count(*) AS k, min(k_{a}.n) AS lo, max(k_{a}.n) AS hi, any_value(nc.n) AS n, round(sum(k_{a}.n * 1.0 / nc.n * ln(k_{a}.n * 1.0 / nc.n)), 9) AS e FROM k_{a}, nc" for a in _A)
    return f"""WITH a AS MATERIALIZED {fx('line_cat')}, cc AS MATERIALIZED (SELECT * FROM (SELECT *, row_number() OVER (ORDER BY U['0';'ctx';rid], rid) AS pos FROM a WHERE split = 'context') AS c0 WHERE pos <= {CONTEXT_CAP}),
    hh AS (SELECT least(2048, ceil(0.1 * count(*)), floor(count(*) / {FOLDS}), count(*) - 1)::BIGINT AS h FROM cc),
    fo AS MATERIALIZED (SELECT rid, {cols}, CASE WHEN k < {FOLDS} * h THEN (k // h)::INT ELSE -1 END AS fold FROM (SELECT *, row_number() OVER (ORDER BY U['0';'fold';rid], rid) - 1 AS k FROM cc) AS c1, hh),
    tr AS MATERIALIZED (SELECT s, {cols}, s * {2 * CONTEXT_CAP} + row_number() OVER (PARTITION BY s ORDER BY rid) - 1 AS at FROM fo, range({FOLDS}) AS r(s) WHERE fold <> s), tn AS (SELECT s, count(*) AS nt FROM tr GROUP BY s),
    nc AS (SELECT count(*) AS n FROM fo), {counted},
    e AS (SELECT rid, fold, 'nom' AS kind, 0 AS is_anom, {cols} FROM fo UNION ALL {' UNION ALL '.join(probes)} UNION ALL SELECT rid, 9, 'qry', is_anom, {cols} FROM a WHERE split = 'query'),
    ez AS MATERIALIZED (SELECT e.*, {zs} FROM e CROSS JOIN nc {beside}), bo AS (SELECT {qs} FROM ez WHERE kind = 'nom'),
    tg AS (SELECT 'S:' || attr AS cand FROM (SELECT attr, row_number() OVER (ORDER BY e, attr) AS r FROM ({ents}) AS en WHERE k BETWEEN 2 AND 10 AND lo >= greatest(5, 0.01 * n) AND hi <= 0.95 * n) AS er WHERE r <= 4),
    la AS MATERIALIZED (SELECT rid, fold, kind, is_anom, x.cand AS cand, x.own AS own, list_filter(toks, lambda t: x.cand <> 'S:' || t.attr) AS toks FROM (SELECT rid, fold, kind, is_anom, unnest([{labs}]) AS x, [{toks}] AS toks FROM ez CROSS JOIN bo) AS u
      WHERE (x.cand NOT LIKE 'S:%' OR x.cand IN (SELECT cand FROM tg)){f" AND x.cand = '{only}'" if only else ''}),
    cn AS MATERIALIZED (SELECT cand, own AS y, fold, t.attr AS attr, t.tok AS tok, count(*) AS n FROM (SELECT cand, own, fold, unnest(list_append(toks, {{'attr': '', 'tok': ''}})) AS t FROM la WHERE kind = 'nom') AS u GROUP BY ALL),
    n AS MATERIALIZED (SELECT cand, s, y, attr, tok, sum(n) AS n FROM cn, (VALUES (0), (1), (2), (9)) AS v(s) WHERE fold <> s GROUP BY cand, s, y, attr, tok),
    z AS (SELECT cand, s, y, n AS ny FROM n WHERE attr = ''), nn AS (SELECT cand, s, sum(ny) AS n, count(*) AS classes FROM z GROUP BY cand, s), kj AS (SELECT cand, s, attr, count(DISTINCT tok) AS kj FROM n WHERE attr <> '' GROUP BY cand, s, attr),
    sp0 AS ({sup("kind <> 'qry' AND fold >= 0")}), sp AS (SELECT left(cand, 1) AS task, cand, kind, kappa FROM sp0)
    {tail.replace('QL', sup("kind = 'qry' AND cand IN (SELECT cand FROM kp)"))}"""


_SELECT = _RK.replace(f"WITH sp AS ({_SUPPORT})", "").lstrip(", \n")
_SCORED = """, lv AS (SELECT cand, kappa, sum(count(*)) OVER (PARTITION BY cand ORDER BY kappa) AS below FROM sp WHERE kind = 'nom' AND cand IN (SELECT cand FROM kp) GROUP BY cand, kappa), ll AS (SELECT cand, max(below) AS n FROM lv GROUP BY cand),
    ql AS (QL), su AS (SELECT q.rid, q.is_anom, q.cand, round(-ln((1 + coalesce(max(lv.below), 0)) / (any_value(ll.n) + 1.0)), 6) AS s FROM (SELECT ql.*, (SELECT max(kappa) FROM lv WHERE lv.cand = ql.cand AND lv.kappa <= ql.kappa) AS at FROM ql) AS q JOIN ll USING (cand) LEFT JOIN lv ON lv.cand = q.cand AND lv.kappa = q.at GROUP BY q.rid, q.is_anom, q.cand)"""
_ONE = SQL(f", kp AS (SELECT 'S:return_flag' AS cand){_SCORED} TAIL", "S:return_flag")
_AUROC = """, g AS (SELECT score, sum(is_anom) AS p, sum(1 - is_anom) AS q FROM fin GROUP BY ALL), w AS (SELECT *, coalesce(sum(q) OVER (ORDER BY score ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0) AS below FROM g)
    SELECT 'line_cat' AS dataset, round(sum(p * (below + q / 2.0)) / (sum(p) * 1.0 * sum(q)), 6) AS auroc FROM w"""


def _return_flag(s, d) -> DataFrame:
    df, fit = _fit(s, d, "S")
    fit.labels = {k: v for k, v in fit.labels.items() if k == "S:return_flag"}
    return fit.scores(df, fit.supports(), ["S:return_flag"]).select("rid", "is_anom", F.element_at("s", 1).alias("surprisal"))


@query("surprisal_line_cat", _ONE.replace("TAIL", "SELECT rid, s AS surprisal FROM su"))
def surprisal_line_cat(s, d):
    """Supports of one task calibrated by those of held-out rows, each scored without its fold."""
    return _return_flag(s, d).select("rid", "surprisal")


@query("detect_line_cat_counts", _ONE.replace("TAIL", f", fin AS (SELECT is_anom, s AS score FROM su){_AUROC}"))
def detect_line_cat(s, d):
    return sc.auroc(_return_flag(s, d).select(F.lit("line_cat").alias("dataset"), "is_anom", F.col("surprisal").alias("score")))


def _selected(support: DataFrame) -> DataFrame:
    return sc.retain(sc.inter_rank(sc.intra_pick(sc.cand_stats(support)).drop("badness")), "all")


query("line_cat_cand_stats", SQL(", " + _SELECT.split(", fi AS (")[0] + " SELECT task, cand, med, var, rho, gap FROM st"))(lambda s, d: sc.cand_stats(_fit(s, d)[1].supports()))
query("line_cat_kept", SQL(", " + _SELECT + " SELECT task, cand, badness, place FROM rk"))(lambda s, d: _selected(_fit(s, d)[1].supports()))


def _detected(s, d) -> DataFrame:
    df, fit = _fit(s, d)
    support = fit.supports().cache()  # at most candidates x folds x 2 x 2048 rows
    kept = [r.cand for r in _selected(support).orderBy("place").collect()]
    return fit.scores(df, support, kept).select("rid", "is_anom", F.round(sc.ens_low2mean(F.col("s")) + F.lit(1e-9), 6).alias("score"))


_FULL = SQL(f", {_SELECT}, kp AS (SELECT cand FROM rk){_SCORED}, fin AS (SELECT rid, is_anom, round(list_avg(list_sort(list(s))[1:2]) + 1e-9, 6) AS score FROM su GROUP BY rid, is_anom) TAIL")


@query("detect_line_cat_full", _FULL.replace("TAIL", "SELECT rid, is_anom, score FROM fin"))
def detect_line_cat_full(s, d):
    """Grid, folds, probes, supports, both selections, calibration and ensemble."""
    return _detected(s, d)


@query("auroc_line_cat_full", _FULL.replace("TAIL", _AUROC))
def auroc_line_cat_full(s, d):
    return sc.auroc(_detected(s, d).select(F.lit("line_cat").alias("dataset"), "is_anom", "score"))
