"""Two-pass external shuffle into shards.

Pass 1 scatters the records by a seeded hash into buckets of a bounded number of bytes (Spark's shuffle files are the
external store). Pass 2 loads one bucket at a time, puts it in a canonical order, and permutes it with Fisher-Yates from a
generator seeded by (seed, bucket). Bucket after bucket this is one uniformly shuffled sequence; position p of it goes to
shard p mod n at slot p div n, so the shards' row counts are at most one apart and slots have no gaps (law `rows`).

A retried task repeats its bucket exactly, since neither the scatter nor the permutation depends on arrival order.
"""

from __future__ import annotations

import math

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from fuzzyfeat.session import prepare

BUCKET_BYTES = 16 << 20


def fisher_yates(n: int, generator: np.random.Generator) -> np.ndarray:
    """A uniform permutation of range(n)."""
    order = list(range(n))
    draws = generator.integers(0, np.arange(1, n + 1))
    for i in range(n - 1, 0, -1):
        j = draws[i]
        order[i], order[j] = order[j], order[i]
    return np.array(order, dtype=np.int64)


def external_shuffle(records: DataFrame, n_shards: int, seed: int = 42, size_col: str | None = None, bucket_bytes: int = BUCKET_BYTES, key_cols: tuple[str, ...] = ("doc_id",)) -> DataFrame:
    """The records with shard (0..n_shards-1) and slot (gapless from 0 in each shard).

    Any column may be null: nulls hash and sort like a value. Rows repeated as a whole are interchangeable, so their order
    does not matter. An empty table gives an empty result. Columns of `records` named shard, slot or __bucket are replaced.
    size_col names a column with the bytes of a record; without it a record counts as 1 KiB.
    """
    prepare(records.sparkSession)
    records = records.drop("shard", "slot", "__bucket", "__order")
    total = records.agg(F.sum(F.col(size_col) if size_col else F.lit(1024))).first()[0] or 0
    n_buckets = max(1, math.ceil(total / bucket_bytes))
    keys = [F.col(c) for c in key_cols]
    bucket = F.pmod(F.xxhash64(F.lit(seed), *keys), F.lit(n_buckets))
    counts = np.zeros(n_buckets, np.int64)
    for row in records.groupBy(bucket.alias("b")).count().collect():  # n_buckets rows at most
        counts[row["b"]] = row["count"]
    before = np.concatenate([[0], np.cumsum(counts)])
    scattered = records.withColumn("__bucket", bucket).withColumn("__order", F.xxhash64(F.lit(~seed), *keys, *(c for c in records.columns if c not in key_cols)))

    def shuffle_bucket(key, table):
        number = key[0].as_py()
        table = table.take(pa.compute.sort_indices(table, [("__order", "ascending")]))
        order = fisher_yates(len(table), np.random.default_rng([seed & 0xFFFFFFFF, number]))
        position = before[number] + np.arange(len(table))
        table = table.take(pa.array(order)).drop_columns(["__bucket", "__order"])
        return table.append_column("shard", pa.array((position % n_shards).astype(np.int32))).append_column("slot", pa.array(position // n_shards))

    schema = T.StructType([*records.schema.fields, T.StructField("shard", T.IntegerType()), T.StructField("slot", T.LongType())])
    return scattered.groupBy("__bucket").applyInArrow(shuffle_bucket, schema)


def write_shards(shuffled: DataFrame, path: str) -> None:
    """One folder per shard; within it, files in slot order by their least slot. No further shuffle."""
    shuffled.sortWithinPartitions("shard", "slot").write.partitionBy("shard").parquet(path)
