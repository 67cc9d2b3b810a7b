"""The experiment tables as views over the given ones: one SQL text each, with the few functions that differ by engine."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from fuzzyfeat.plans.spec import Feature

SPARK = {
    "h": lambda x: f"cast(conv(substring(md5({x}), 1, 8), 16, 10) as bigint)",
    "hour": "hour(ts)", "weekday": "weekday(ts)", "month": "month", "k": "cast(get_json_object(props, '$.k') as int)",
    "split": lambda x, by: f"split({x}, {by})", "size": lambda x: f"size({x})", "distinct": lambda x: f"array_distinct({x})",
    "newline": "'\\n'", "drop": lambda x, p: f"regexp_replace({x}, '{p}', '')", "text": lambda x: f"cast({x} as string)", "epoch": lambda x: f"unix_seconds(cast({x} as timestamp))", "double": "double",
}
DUCKDB = {
    "h": lambda x: f"cast(('0x' || substr(md5({x}), 1, 8)) as bigint)",
    "hour": "hour(ts)", "weekday": "(isodow(ts) - 1)", "month": "month", "k": "cast(json_extract_string(props, '$.k') as int)",
    "split": lambda x, by: f"string_split({x}, {by})", "size": lambda x: f"len({x})", "distinct": lambda x: f"list_distinct({x})",
    "newline": "chr(10)", "drop": lambda x, p: f"regexp_replace({x}, '{p}', '', 'g')", "text": lambda x: f"cast({x} as varchar)", "epoch": lambda x: f"cast(epoch({x}) as bigint)", "double": "double",
}


def traffic_sql(d: dict, unknowns: bool = False) -> str:
    """Five skewed, interlaced and noisy classes planted into events."""
    xor = "((value > 35) <> (k >= 50))"
    hide = (lambda c, n: f"case when event_id % {n} = 0 then null else {c} end") if unknowns else lambda c, n: c
    return f"""SELECT row_id, cast({hide('value', 17)} as double) AS value, cast(k as double) AS k, cast({hide('hour', 29)} as double) AS hour, cast(weekday as double) AS weekday, {hide('event_type', 23)} AS event_type, label, label || '/' || event_type AS fine_label FROM (
      SELECT *, CASE WHEN {d['h']("'n' || " + d['text']('event_id'))} % 100 < 2 THEN 'flood' WHEN k < 5 AND value > 100 THEN 'root'
        WHEN event_type = 'signup' AND hour < 6 AND {xor} THEN 'remote' WHEN event_type = 'error' AND hour BETWEEN 6 AND 17 THEN 'scan' WHEN {xor} THEN 'benign' ELSE 'flood' END AS label
      FROM (SELECT event_id, event_id AS row_id, value, event_type, {d['k']} AS k, {d['hour']} AS hour, {d['weekday']} AS weekday FROM {d.get('events', 'events')}) e) t"""


def xor_sql(d: dict) -> str:
    return f"SELECT row_id, value, k, CASE WHEN (value > 35) <> (k >= 50) THEN 'odd' ELSE 'even' END AS label, CASE WHEN (value > 35) <> (k >= 50) THEN 'odd' ELSE 'even' END AS fine_label FROM (SELECT event_id AS row_id, value, cast({d['k']} as double) AS k FROM {d.get('events', 'events')}) e"


def quality_sql(d: dict, label: str = "quality") -> str:
    """Text measures of documents; the label is null where labels has none."""
    words = d["split"]("d.text", "' '")
    return f"""SELECT d.doc_id AS row_id, cast(d.n_chars as double) AS n_chars, cast({d['size'](words)} as double) AS n_words, cast({d['size'](d['split']('d.text', d['newline']))} as double) AS n_lines,
      cast(length({d['drop']('d.text', '[^A-Za-z]')}) as double) / greatest(length(d.text), 1) AS letter_ratio, cast({d['size'](d['distinct'](words))} as double) / {d['size'](words)} AS uniq_ratio,
      d.lang, d.source, {d['text']('l.' + label)} AS label, {d['text']('l.quality')} || '/' || {d['text']('l.toxic')} AS fine_label
    FROM {d.get('documents', 'documents')} d LEFT JOIN {d.get('labels', 'labels')} l ON l.doc_id = d.doc_id"""


def role_sql(d: dict) -> str:
    return f"""SELECT {d['text']('conv_id')} || '-' || {d['text']('turn')} AS row_id, cast(turn as double) AS turn, cast(length(text) as double) AS n_chars, cast({d['size'](d['split']('text', "' '"))} as double) AS n_words,
      CASE WHEN text LIKE '%?' THEN 'yes' ELSE 'no' END AS question, cast(count(*) OVER (PARTITION BY conv_id) as double) AS turns, role AS label, role AS fine_label FROM {d.get('conversations', 'conversations')}"""


def orders_sql(d: dict) -> str:
    return f"""SELECT o.o_orderkey AS row_id, o.o_totalprice AS o_totalprice, c.c_acctbal AS c_acctbal, cast(month(o.o_orderdate) as double) AS order_month, o.o_orderstatus AS o_orderstatus, c.c_mktsegment AS c_mktsegment, n.n_name AS n_name, r.r_name AS r_name,
      o.o_orderpriority AS label, o.o_orderpriority || '/' || o.o_orderstatus AS fine_label
    FROM {d.get('orders', 'orders')} o JOIN {d.get('customer', 'customer')} c ON c.c_custkey = o.o_custkey JOIN {d.get('nation', 'nation')} n ON n.n_nationkey = c.c_nationkey JOIN {d.get('region', 'region')} r ON r.r_regionkey = n.n_regionkey"""


def supplier_sql(d: dict) -> str:
    return f"SELECT s.s_suppkey AS row_id, s.s_acctbal AS s_acctbal, n.n_name AS nation, r.r_name AS label, r.r_name AS fine_label FROM {d.get('supplier', 'supplier')} s JOIN {d.get('nation', 'nation')} n ON n.n_nationkey = s.s_nationkey JOIN {d.get('region', 'region')} r ON r.r_regionkey = n.n_regionkey"


def part_sql(d: dict) -> str:
    return f"SELECT p_partkey AS row_id, cast(p_size as double) AS p_size, p_retailprice, p_brand, {d['split']('p_name', chr(39) + ' ' + chr(39))}[{d.get('one', 1)}] AS first_word, p_type AS label, p_type AS fine_label FROM {d.get('part', 'part')}"


EMB = 64


def emb_sql(d: dict) -> str:
    """The vectors' components as columns: many numeric features, among which clusters of equal centroids are likely."""
    parts = ", ".join(f"cast(embedding[{i + d.get('one', 1)}] as double) AS e{i}" for i in range(EMB))
    return f"SELECT vec_id AS row_id, {parts}, {d['text']('label')} AS label, {d['text']('label')} AS fine_label FROM {d.get('embeddings', 'embeddings')}"


def line_sql(d: dict) -> str:
    """Order lines by return flag: a control whose columns say next to nothing of the class, apart from the date."""
    return f"SELECT l_orderkey * 10 + l_linenumber AS row_id, cast(l_quantity as double) AS l_quantity, cast(l_extendedprice as double) AS l_extendedprice, cast(l_discount as double) AS l_discount, cast(l_tax as double) AS l_tax, cast(month(l_shipdate) as double) AS ship_month, l_returnflag AS label, l_returnflag || '/' || l_linestatus AS fine_label FROM {d.get('lineitem', 'lineitem')}"


SQL = {"traffic": traffic_sql, "unknowns": lambda d: traffic_sql(d, True), "xor": xor_sql, "quality": quality_sql, "toxic": lambda d: quality_sql(d, "toxic"), "role": role_sql, "orders": orders_sql, "supplier": supplier_sql, "part": part_sql, "emb": emb_sql, "line": line_sql}
C, O, S = "continuous", "ordinal", "symbolic"
_TRAFFIC = [Feature("value", C), Feature("k", C), Feature("hour", O, 24), Feature("event_type", S)]
_QUALITY = [Feature(c, C) for c in ("n_chars", "n_words", "n_lines", "letter_ratio", "uniq_ratio")] + [Feature("lang", S), Feature("source", S)]
SPECS = {
    "traffic": _TRAFFIC, "unknowns": _TRAFFIC, "xor": [Feature("value", C), Feature("k", C)], "quality": _QUALITY, "toxic": _QUALITY,
    "role": [Feature("turn", C), Feature("n_chars", C), Feature("n_words", C), Feature("question", S), Feature("turns", C)],
    "orders": [Feature("o_totalprice", C), Feature("c_acctbal", C), Feature("order_month", O, 13), Feature("o_orderstatus", S), Feature("c_mktsegment", S), Feature("r_name", S)],
    "supplier": [Feature("s_acctbal", C), Feature("nation", S)],
    "part": [Feature("p_size", O, 51), Feature("p_retailprice", C), Feature("p_brand", S), Feature("first_word", S)],
    "emb": [Feature(f"e{i}", C) for i in range(EMB)],
    "line": [Feature(c, C) for c in ("l_quantity", "l_extendedprice", "l_discount", "l_tax")] + [Feature("ship_month", O, 13)],
}
_TABLES = ("events", "documents", "labels", "conversations", "orders", "customer", "nation", "region", "supplier", "part", "embeddings", "lineitem")


def load(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    """A fixture as a DataFrame; only the tables and columns that it names are read."""
    d = SPARK | {t: "parquet.`" + f"{sf_dir}/{t}.parquet" + "`" for t in _TABLES} | {"one": 0}
    return spark.sql(SQL[name](d))


def duckdb_sql(name: str) -> str:
    return SQL[name](DUCKDB)
