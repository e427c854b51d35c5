"""The input views: (rid, split, is_anom, attributes), a text for both engines each.

Contexts are normal rows; the split draws 60 % of them. Where a table has no
labels, five per cent of the query rows are marked for planting (is_anom = 1)
and changed by vtask.plans.workloads. A line is named by the hash of its columns,
so no view needs a shuffle to name its rows; lines that are equal in every column
share name, side and score.
"""

from __future__ import annotations

from dataclasses import dataclass

_LINE = """
SELECT h AS rid, quantity, price, disc, tax, line_no, return_flag, line_status, net, charge
FROM (SELECT md5(concat_ws('|', l_orderkey, l_partkey, l_suppkey, l_linenumber, cast(round(l_quantity) AS bigint), cast(round(l_extendedprice * 100) AS bigint),
        cast(round(l_discount * 100) AS bigint), cast(round(l_tax * 100) AS bigint), l_returnflag, l_linestatus)) AS h,
    l_quantity AS quantity, l_extendedprice AS price, cast(cast(round(l_discount * 100) AS bigint) AS TEXT) AS disc, cast(cast(round(l_tax * 100) AS bigint) AS TEXT) AS tax,
    cast(l_linenumber AS TEXT) AS line_no, l_returnflag AS return_flag, l_linestatus AS line_status,
    l_extendedprice * (1 - l_discount) AS net, l_extendedprice * (1 - l_discount) * (1 + l_tax) AS charge
  FROM lineitem) AS t0
"""
_SPLIT = "CASE WHEN U['0';'split';rid] < 0.6 THEN 'context' ELSE 'query' END AS split"
_MARK = "CASE WHEN U['0';'split';rid] >= 0.6 AND U['0';'plant';rid] < 0.05 THEN 1 ELSE 0 END AS is_anom"


def _planted(body: str, attrs: str) -> str:
    return f"SELECT rid, {_SPLIT}, {_MARK}, {attrs} FROM ({body}) AS t1"


def _labelled(body: str, attrs: str) -> str:
    """body has rid and bad; bad rows are never context."""
    return f"SELECT rid, CASE WHEN bad = 0 AND U['0';'split';rid] < 0.6 THEN 'context' ELSE 'query' END AS split, bad AS is_anom, {attrs} FROM ({body}) AS t1"


_ORDER = """
SELECT cast(o_orderkey AS TEXT) AS rid, o_totalprice AS total, cast(DAYS[o_orderdate] AS double) AS order_day, c_acctbal AS balance,
    o_orderstatus AS status, o_orderpriority AS priority, c_mktsegment AS segment, cast(n_regionkey AS TEXT) AS region_key
FROM orders JOIN customer ON o_custkey = c_custkey JOIN nation ON c_nationkey = n_nationkey
"""
_PART = "SELECT cast(p_partkey AS TEXT) AS rid, cast(p_partkey % 1000 AS double) AS slot, p_retailprice AS retail, cast(p_size AS double) AS size_, p_retailprice / p_size AS per_size, p_type AS type FROM part"
_EVENT = "SELECT cast(event_id AS TEXT) AS rid, value AS val, cast(HOUR[ts] AS double) AS hour_, JNUM[props;k] AS k, event_type AS type, cast(DOW[ts] AS TEXT) AS dow FROM events"
_DOC = """
SELECT cast(d.doc_id AS TEXT) AS rid, {bad} AS bad, cast(length(text) AS double) AS chars, n_words, length(text) / n_words AS word_len,
    (length(text) - length(translate(text, '.,!?;:#$%&*|', ''))) / cast(length(text) AS double) AS punct, (length(text) - length(translate(text, 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', ''))) / cast(length(text) AS double) AS upper_, lang
FROM (SELECT *, cast(length(text) - length(replace(text, ' ', '')) + 1 AS double) AS n_words FROM documents WHERE length(text) > 0) AS d JOIN labels AS lab ON d.doc_id = lab.doc_id
"""
_CONV = """
SELECT concat_ws('-', conv_id, turn) AS rid, CASE WHEN role = 'system' THEN 1 ELSE 0 END AS bad, cast(length(text) AS double) AS chars, cast(length(text) - length(replace(text, ' ', '')) + 1 AS double) AS n_words,
    length(text) / cast(length(text) - length(replace(text, ' ', '')) + 1 AS double) AS word_len FROM conversations WHERE length(text) > 0
"""
_USER = """
SELECT cast(user_id AS TEXT) AS rid, cast(count(*) AS double) AS n_events, round(avg(value), 6) AS mean_val, max(value) AS max_val, round(avg(CASE WHEN event_type = 'click' THEN cast(1 AS double) ELSE cast(0 AS double) END), 6) AS click_share, round(avg(CASE WHEN event_type = 'error' THEN cast(1 AS double) ELSE cast(0 AS double) END), 6) AS error_share
FROM events GROUP BY user_id
"""
_PAGE = "SELECT cast(page_id AS TEXT) AS rid, cast(length(html) AS double) AS chars, cast(length(html) - length(replace(html, '<', '')) AS double) AS tags, cast(length(url) AS double) AS url_len, (length(html) - length(translate(html, '0123456789', ''))) / cast(length(html) AS double) AS digits FROM pages WHERE length(html) > 0"
_BENCH = "SELECT cast(item_id AS TEXT) AS rid, 0 AS bad, cast(length(text) AS double) AS chars, cast(length(text) - length(replace(text, ' ', '')) + 1 AS double) AS n_words FROM benchmark"
_SUPP = "SELECT cast(s_suppkey AS TEXT) AS rid, 0 AS bad, s_acctbal AS balance, cast(s_nationkey AS double) AS nation_key, cast(n_regionkey AS TEXT) AS region_key FROM supplier JOIN nation ON s_nationkey = n_nationkey"
_EMBED = "SELECT cast(vec_id AS TEXT) AS rid, CASE WHEN label = 3 THEN 1 ELSE 0 END AS bad, {cols} FROM embeddings"


@dataclass(frozen=True)
class Fixture:
    sql: str
    num: tuple[str, ...]
    cat: tuple[str, ...]
    side: str  # 'dev' or 'eval', by base table
    given: bool = False

    @property
    def attrs(self) -> list[str]:
        return [*self.num, *self.cat]


def _f(body, num, cat, side, given=False):
    num, cat = tuple(num.split()), tuple(cat.split())
    attrs = ", ".join((*num, *cat))
    return Fixture((_labelled if given else _planted)(body, attrs), num, cat, side, given)


_VEC = [f"e{i}" for i in range(16)]

FIXTURES = {
    "line_mixed": _f(_LINE, "quantity price", "disc tax line_no return_flag line_status", "eval"),
    "line_num": _f(_LINE, "quantity price net charge", "", "eval"),
    "line_cat": _f(_LINE, "", "disc tax line_no return_flag line_status", "eval"),
    "line_catdom": _f(_LINE, "price", "disc tax line_no return_flag line_status", "eval"),
    "order_wide": _f(_ORDER, "total order_day balance", "status priority segment region_key", "dev"),
    "order_cat": _f(_ORDER, "", "status priority segment region_key", "dev"),
    "part_dep": _f(_PART, "slot retail size_ per_size", "type", "eval"),
    "event_mix": _f(_EVENT, "val hour_ k", "type dow", "dev"),
    "event_err": _f(_EVENT.replace("SELECT ", "SELECT CASE WHEN event_type = 'error' THEN 1 ELSE 0 END AS bad, ", 1), "val hour_ k", "dow", "dev", True),
    "user_profile": _f(_USER, "n_events mean_val max_val click_share error_share", "", "dev"),
    "doc_quality": _f(_DOC.format(bad="CASE WHEN quality = 0 THEN 1 ELSE 0 END"), "chars n_words word_len punct upper_", "lang", "eval", True),
    "doc_toxic": _f(_DOC.format(bad="toxic"), "chars n_words word_len punct upper_", "lang", "eval", True),
    "conv_role": _f(_CONV, "chars n_words word_len", "", "eval", True),
    "page_shape": _f(_PAGE, "chars tags url_len digits", "", "eval"),
    "embed_3": _f(_EMBED.format(cols=", ".join(f"cast(AT[embedding;{i}] AS double) AS e{i}" for i in range(16))), " ".join(_VEC), "", "eval", True),
    "supp_small": _f(_SUPP, "balance nation_key", "region_key", "dev", True),
    "bench_clean": _f(_BENCH, "chars n_words", "", "eval", True),
}


def fixture(spark, sf_dir: str, name: str):
    """DataFrame of a fixture."""
    from vtask.sources.dialect import spark_sql

    return spark_sql(spark, sf_dir, FIXTURES[name].sql)
