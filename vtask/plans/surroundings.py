"""What a user needs around the method: views, joins, windows, cubes, set operations, nested data, event windows."""

from __future__ import annotations

from pyspark.sql import Window
from pyspark.sql import functions as F

from vtask.operators import features as ft
from vtask.operators import tasks as tk
from vtask.plans.queries import _RESULTS, _results, fx, query
from vtask.sources.fixtures import FIXTURES, fixture

_OW = FIXTURES["order_wide"]
query("order_wide_view", FIXTURES["order_wide"].sql)(lambda s, d: fixture(s, d, "order_wide"))
query("doc_features", FIXTURES["doc_quality"].sql)(lambda s, d: fixture(s, d, "doc_quality"))
query("user_profile_view", FIXTURES["user_profile"].sql)(lambda s, d: fixture(s, d, "user_profile"))


def _events(s, d):
    return s.read.parquet(f"{d}/events.parquet")


query("asof_prev_event", "SELECT event_id, lag(event_id) OVER w AS prev_id, (epoch(date_trunc('second', ts)) - epoch(date_trunc('second', lag(ts) OVER w)))::BIGINT AS gap_s FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id)")(
    lambda s, d: ft.previous_event(_events(s, d), "user_id", "ts", "event_id").select("event_id", "prev_id", "gap_s")
)
query("interval_events_1h", "WITH e AS (SELECT *, floor(epoch(ts))::BIGINT AS t FROM events) SELECT event_id, count(*) OVER (PARTITION BY user_id ORDER BY t RANGE BETWEEN 3600 PRECEDING AND CURRENT ROW) AS n_recent FROM e")(
    lambda s, d: ft.events_within(_events(s, d), "user_id", "ts", 3600).select("event_id", "n_recent")
)
query("unseen_tokens_anti", f"WITH a AS {fx('line_cat')} SELECT rid, disc FROM a WHERE split = 'query' AND disc NOT IN (SELECT disc FROM a WHERE split = 'context' AND U['0';'few';rid] < 0.0003)")(
    lambda s, d: (lambda a: ft.unseen(a.filter("split = 'query'"), "disc", a.filter((F.col("split") == "context") & (tk.u01(0, "few", F.col("rid")) < 0.0003))).select("rid", "disc"))(fixture(s, d, "line_cat"))
)
query("pool_semi", f"WITH a AS {fx('doc_quality')} SELECT rid FROM a WHERE rid IN (SELECT rid FROM a WHERE is_anom = 1 AND U['0';'pool';rid] < 0.5)")(
    lambda s, d: (lambda a: a.join(a.filter((F.col("is_anom") == 1) & (tk.u01(0, "pool", F.col("rid")) < 0.5)).select("rid"), "rid", "left_semi").select("rid"))(fixture(s, d, "doc_quality"))
)
_G = "CASE WHEN n_rows < 1000 THEN 'below 1K' WHEN n_rows < 10000 THEN '1K-10K' ELSE '10K and more' END"


def _grouped(s, d):
    from vtask.operators.compare import size_group

    return _results(s, d).withColumn("size_group", size_group(F.col("n_rows")))


for _k in ("cube", "rollup"):
    query(f"results_{_k}", f"WITH r AS (SELECT *, {_G} AS size_group FROM ({_RESULTS}) AS r0) SELECT method, size_group, grouping(method, size_group)::BIGINT AS gid, round(avg(value), 6) AS mean_value, count(*) AS n FROM r GROUP BY {_k.upper()}(method, size_group)")(
        lambda s, d, k=_k: getattr(_grouped(s, d), k)("method", "size_group").agg(F.grouping_id().cast("long").alias("gid"), F.round(F.avg("value"), 6).alias("mean_value"), F.count("*").alias("n"))
    )
query("topk_anomalies", "SELECT o_orderstatus AS status, o_orderkey AS id, o_totalprice AS score FROM (SELECT *, row_number() OVER (PARTITION BY o_orderstatus ORDER BY o_totalprice DESC, o_orderkey) AS r FROM orders) WHERE r <= 5")(
    lambda s, d: s.read.parquet(f"{d}/orders.parquet").withColumn("r", F.row_number().over(Window.partitionBy("o_orderstatus").orderBy(F.desc("o_totalprice"), "o_orderkey"))).filter("r <= 5").select(F.col("o_orderstatus").alias("status"), F.col("o_orderkey").alias("id"), F.col("o_totalprice").alias("score"))
)
query("token_pivot", f"WITH a AS {fx('line_cat')} SELECT return_flag, count(*) FILTER (WHERE line_status = 'F') AS f, count(*) FILTER (WHERE line_status = 'O') AS o FROM a GROUP BY return_flag")(
    lambda s, d: fixture(s, d, "line_cat").groupBy("return_flag").pivot("line_status", ["F", "O"]).count().select("return_flag", F.coalesce("F", F.lit(0)).alias("f"), F.coalesce("O", F.lit(0)).alias("o"))
)
query("token_unpivot", f"WITH a AS {fx('order_cat')} " + " UNION ALL ".join(f"SELECT rid, '{c}' AS attr, {c} AS tok FROM a" for c in FIXTURES["order_cat"].cat))(
    lambda s, d: fixture(s, d, "order_cat").unpivot("rid", list(FIXTURES["order_cat"].cat), "attr", "tok")
)
query("set_ops_features", f"WITH a AS {fx('order_cat')}, x AS (SELECT DISTINCT segment, priority FROM a WHERE split = 'context' AND region_key = '1'), y AS (SELECT DISTINCT segment, priority FROM a WHERE split = 'query' AND region_key = '2' AND status = 'P') SELECT 'both' AS side, * FROM (SELECT * FROM x INTERSECT SELECT * FROM y) UNION ALL SELECT 'first', * FROM (SELECT * FROM x EXCEPT SELECT * FROM y)")(
    lambda s, d: (lambda a: (lambda x, y: x.intersect(y).select(F.lit("both").alias("side"), "*").unionAll(x.exceptAll(y).select(F.lit("first").alias("side"), "*")))(
        a.filter("split = 'context' AND region_key = '1'").select("segment", "priority").distinct(), a.filter("split = 'query' AND region_key = '2' AND status = 'P'").select("segment", "priority").distinct()))(fixture(s, d, "order_cat"))
)
query("json_props", "SELECT event_id, JNUM[props;k] AS k FROM events")(lambda s, d: _events(s, d).select("event_id", F.get_json_object("props", "$.k").cast("double").alias("k")))
query("array_scores", "SELECT vec_id, round(list_sum(list_transform(embedding, lambda x: x::DOUBLE * x::DOUBLE)), 6) AS energy FROM embeddings")(
    lambda s, d: s.read.parquet(f"{d}/embeddings.parquet").select("vec_id", F.round(F.aggregate("embedding", F.lit(0.0), lambda a, x: a + x.cast("double") * x.cast("double")), 6).alias("energy"))
)
_ERR = "sum((event_type = 'error')::INT)::BIGINT AS alerts, count(*) AS n"


def _windowed(s, d, w):
    return _events(s, d).groupBy(w.alias("w")).agg(F.sum((F.col("event_type") == "error").cast("long")).alias("alerts"), F.count("*").alias("n")).select(F.unix_timestamp("w.start").alias("start_s"), "alerts", "n")


query("event_window_tumbling", f"SELECT (floor(epoch(ts) / 3600) * 3600)::BIGINT AS start_s, {_ERR} FROM events GROUP BY 1")(lambda s, d: _windowed(s, d, F.window("ts", "1 hour")))
query("event_window_sliding", f"SELECT ((floor(epoch(ts) / 1800) - k) * 1800)::BIGINT AS start_s, {_ERR} FROM events, (VALUES (0), (1)) AS v(k) GROUP BY 1")(lambda s, d: _windowed(s, d, F.window("ts", "1 hour", "30 minutes")))


@query("event_window_session", "WITH g AS (SELECT *, CASE WHEN lag(ts) OVER w IS NULL OR ts >= lag(ts) OVER w + INTERVAL 30 MINUTE THEN 1 ELSE 0 END AS new FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id)), k AS (SELECT *, sum(new) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS sid FROM g) SELECT user_id, floor(epoch(min(ts)))::BIGINT AS start_s, count(*) AS n FROM k GROUP BY user_id, sid")
def session_windows(s, d):
    return _events(s, d).groupBy("user_id", F.session_window("ts", "30 minutes").alias("w")).agg(F.count("*").alias("n")).select("user_id", F.unix_timestamp("w.start").alias("start_s"), "n")


@query("sql_functions", f"WITH a AS (SELECT rid, price FROM {fx('line_num')} AS a0) SELECT rid, (price > 20000)::INT + (price > 60000)::INT AS bin FROM a")
def sql_functions(s, d):
    """The same label by the registered SQL macro."""
    from vtask.functions.sqlapi import register

    register(s)
    fixture(s, d, "line_num").createOrReplaceTempView("vt_line_num")
    return s.sql("SELECT rid, vt_qbin(price, array(20000D, 60000D)) AS bin FROM vt_line_num")


@query("stream_scores_memory")
def stream_scores(s, d):
    """Events scored as a stream against frozen parameters; equals the batch result."""
    from vtask.streaming.jobs import run_to_files, score_events, stream_events

    return run_to_files(score_events(stream_events(s, d)).select("event_id", "user_id", "surprisal"))


@query("stream_alert_windows")
def stream_alerts(s, d):
    from vtask.streaming.jobs import alert_windows, run_once, score_events, stream_events

    return run_once(alert_windows(score_events(stream_events(s, d)), "1 hour", delay="1 hour"), "vt_alerts", "complete").select("start_s", "alerts", "n")




@query(
    "stream_user_state",
    "WITH e AS (SELECT user_id, round(-ln(((25 > value)::INT + (50 > value)::INT + (75 > value)::INT + (100 > value)::INT + (150 > value)::INT + 1) / 6.0), 6) AS z FROM events) "
    "SELECT user_id, count(*) AS n, sum((z >= 1)::INT)::BIGINT AS alerts, greatest(max(z), 0) AS peak FROM e GROUP BY user_id",
)
def stream_user_state(s, d):
    """The state of each user after the last batch: counts only grow, so the largest update is the last."""
    from vtask.streaming.jobs import run_once, score_events, stream_events, user_state

    got = run_once(user_state(score_events(stream_events(s, d))), "vt_users", "update")
    return got.groupBy("user_id").agg(F.max("n").alias("n"), F.max("alerts").alias("alerts"), F.max("peak").alias("peak"))
