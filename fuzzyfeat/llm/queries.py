"""Queries of the ten operators over their whole tables, and their SQL where SQL can express them.

Each query applies its operator with production parameters and derives the columns of its contract from the operator's
own results.
"""

from __future__ import annotations

from collections.abc import Callable

from uuid import uuid4

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

import corpus_pipeline
from fuzzyfeat.llm import _spans, pii, secrets
from fuzzyfeat.llm.decontamination import contaminated
from fuzzyfeat.llm.jaccard import jaccard_components
from fuzzyfeat.llm.language import identify
from fuzzyfeat.llm.multi_index import nearest
from fuzzyfeat.llm.packing import assign, token_pieces
from fuzzyfeat.llm.sharding import external_shuffle
from fuzzyfeat.llm.toxicity import toxicity
from fuzzyfeat.llm.warc import read_warc, write_warc
from fuzzyfeat.session import materialise, shared_folder

UPPER, LOWER = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def op1_external_shuffle(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents").withColumn("size", F.coalesce(F.octet_length("text"), F.lit(0)).cast("long") + 1)
    shards = external_shuffle(docs, 8, size_col="size")
    crc = F.crc32(F.coalesce("text", F.lit("")).cast("binary"))
    return shards.select("doc_id", "size", crc.alias("text_crc32"), F.lit("rows").alias("law"), "shard", "slot", F.lit(None).cast("int").alias("grown_shard"))


def op2_ngram_jaccard_join(spark: SparkSession, sf_dir: str) -> DataFrame:
    return jaccard_components(table(spark, sf_dir, "documents"), k=3, threshold=(90, 100))


OP2_SQL = rf"""
WITH RECURSIVE d AS (
  SELECT doc_id, list_filter(string_split_regex(translate(coalesce(text, ''), '{UPPER}', '{LOWER}'), '[\x20\x09-\x0D]+'), lambda x: x <> '') AS w FROM documents
), s AS (
  SELECT DISTINCT doc_id, unnest(CASE WHEN len(w) = 0 THEN [] WHEN len(w) < 3 THEN [array_to_string(w, ' ')]
    ELSE list_transform(range(1, len(w) - 1), lambda i: w[i] || ' ' || w[i + 1] || ' ' || w[i + 2]) END) AS g FROM d
), n AS (SELECT doc_id, count(*) AS n FROM s GROUP BY doc_id),
p AS (SELECT a.doc_id AS a, b.doc_id AS b, count(*) AS c FROM s a JOIN s b ON a.g = b.g AND a.doc_id <> b.doc_id GROUP BY 1, 2),
l AS (SELECT a, b FROM p JOIN n x ON x.doc_id = a JOIN n y ON y.doc_id = b WHERE 100 * c >= 90 * (x.n + y.n - c)),
r AS (SELECT doc_id, doc_id AS m FROM d UNION SELECT l.b, r.m FROM r JOIN l ON l.a = r.doc_id WHERE r.m < l.b)
SELECT d.doc_id, coalesce(n.n, 0) AS n_shingles, m.m AS component_id
FROM d LEFT JOIN n ON n.doc_id = d.doc_id JOIN (SELECT doc_id, min(m) AS m FROM r GROUP BY doc_id) m ON m.doc_id = d.doc_id
"""


def op3_warc(spark: SparkSession, sf_dir: str) -> DataFrame:
    pages = table(spark, sf_dir, "pages")
    folder = f"{shared_folder(spark).rstrip('/')}/warc-{uuid4().hex}"
    write_warc(pages, folder)
    records = read_warc(spark, path=folder)
    number = lambda c: F.expr(f"try_cast(substring_index({c}, ':', -1) AS bigint)")
    rows = records.filter(F.col("record_type").isin("response", "revisit"))
    return rows.select(number("record_id").alias("page_id"), "payload_bytes", "payload_digest", "record_type", number("refers_to").alias("refers_to"))


def op4_multi_index_search(spark: SparkSession, sf_dir: str) -> DataFrame:
    return nearest(table(spark, sf_dir, "embeddings"), F.col("vec_id") % 20 == 0)


def op5_secret_scan(spark: SparkSession, sf_dir: str) -> DataFrame:
    return secrets.secret_spans(table(spark, sf_dir, "documents")).select("doc_id", *_spans.digests(secrets.KINDS))


def op6_template_decontamination(spark: SparkSession, sf_dir: str) -> DataFrame:
    return contaminated(table(spark, sf_dir, "documents"), table(spark, sf_dir, "benchmark"))


def op7_toxicity(spark: SparkSession, sf_dir: str) -> DataFrame:
    return toxicity(table(spark, sf_dir, "documents"), table(spark, sf_dir, "labels"))


def op8_best_fit_packing(spark: SparkSession, sf_dir: str) -> DataFrame:
    pieces = token_pieces(table(spark, sf_dir, "documents")).withColumn("ids_crc32", F.crc32("ids")).drop("ids")
    return assign(materialise(pieces)).select("doc_id", "piece", "start", "length", "ids_crc32", "sequence_id", "offset")


def op9_pii(spark: SparkSession, sf_dir: str) -> DataFrame:
    return pii.pii_spans(table(spark, sf_dir, "documents")).select("doc_id", *_spans.digests(pii.KINDS))


def op10_language_id(spark: SparkSession, sf_dir: str) -> DataFrame:
    return identify(table(spark, sf_dir, "pages"), table(spark, sf_dir, "documents"))


def queries() -> dict[str, Callable[[SparkSession, str], DataFrame]]:
    operators = (
        op1_external_shuffle, op2_ngram_jaccard_join, op3_warc, op4_multi_index_search, op5_secret_scan, op6_template_decontamination,
        op7_toxicity, op8_best_fit_packing, op9_pii, op10_language_id,
    )
    return {f.__name__: f for f in operators} | {"pipeline": corpus_pipeline.run}


def oracle_sql() -> dict[str, str]:
    return {"op2_ngram_jaccard_join": OP2_SQL}
