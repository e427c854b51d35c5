"""One text for the input views of both engines, with macros for what the dialects spell differently.

U[seed;purpose;key] is the stateless uniform of kernels.draws; Q[expr;p] the
interpolating quantile; DAYS[ts] whole days since 1970; HOUR[ts]; JNUM[col;field]
a number in a JSON text; AT[array;i] its item from 0; TEXT the string type.
"""

from __future__ import annotations

import re

_MACRO = re.compile(r"\b(U|Q|DAYS|HOUR|DOW|JNUM|AT)\[([^\[\]]*)\]")

SPARK = {
    "U": "(cast(conv(substr(md5(concat_ws('|', {0}, {1}, {2})), 1, 13), 16, 10) AS double) / 4503599627370496.0D)",
    "Q": "percentile({0}, {1})",
    "DAYS": "cast(unix_date(cast({0} AS date)) AS bigint)",
    "HOUR": "cast(hour({0}) AS bigint)",
    "DOW": "cast(dayofweek({0}) - 1 AS bigint)",
    "JNUM": "cast(get_json_object({0}, '$.{1}') AS double)",
    "AT": "{0}[{1}]",
}
DUCK = {
    "U": "(cast(('0x' || substr(md5(concat_ws('|', {0}, {1}, {2})), 1, 13))::BIGINT AS double) / 4503599627370496.0)",
    "Q": "quantile_cont({0}, {1})",
    "DAYS": "cast(date_diff('day', DATE '1970-01-01', cast({0} AS date)) AS bigint)",
    "HOUR": "cast(hour({0}) AS bigint)",
    "DOW": "cast(dayofweek({0}) AS bigint)",
    "JNUM": "cast(json_extract_string({0}, '$.{1}') AS double)",
    "AT": "{0}[{1} + 1]",
}
TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()


def render(sql: str, dialect: dict[str, str]) -> str:
    for _ in range(4):  # macros nest
        sql, n = _MACRO.subn(lambda m: dialect[m[1]].format(*(a.strip() for a in m[2].split(";"))), sql)
        if not n:
            break
    return sql.replace("TEXT", "string" if dialect is SPARK else "varchar")


def duck(sql: str) -> str:
    return render(sql, DUCK)


def spark_sql(spark, sf_dir: str, sql: str):
    """DataFrame of a macro text over the tables of sf_dir; only the tables that it names are opened."""
    used = [t for t in TABLES if re.search(rf"\b{t}\b", sql)]
    frames = {t: spark.read.parquet(f"{sf_dir}/{t}.parquet") for t in used}
    text = render(sql, SPARK).replace("{", "{{").replace("}", "}}")
    for t in used:
        text = re.sub(rf"\b{t}\b(?!\.)", f"{{{t}}}", text)
    return spark.sql(text, **frames)
