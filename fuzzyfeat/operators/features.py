"""Cluster features of a row, local to the row: strongest cluster, its strength, and the membership row."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from fuzzyfeat.operators.fcm import FcmModel, blocks, distance_column, membership_column, memberships_block, sqdist_block
from fuzzyfeat.operators.prepare import Scaler
from fuzzyfeat.session import prepare

DIGITS = 6  # memberships are rounded before the arg-max, so that float order can't flip the cluster
INLINE_TERMS = 400


def rounded(p: str | Column) -> Column:
    return F.transform(p, lambda x: F.round(x, DIGITS))


def basic_features(p: str | Column) -> tuple[Column, Column]:
    """(z, b): index of the strongest cluster from 0, the lowest on ties, and its membership."""
    r = rounded(p)
    return (F.array_position(r, F.array_max(r)) - 1).cast("int"), F.array_max(r)


def crisp_cluster(distances: str | Column) -> Column:
    """Index of the nearest centroid alone, as a crisp clustering has it; the lowest on ties."""
    r = F.transform(distances, lambda d: F.round(d, 9))
    return (F.array_position(r, F.array_min(r)) - 1).cast("int")


def extended_features(p: str | Column, k: int) -> list[Column]:
    return [F.get(p, F.lit(j)).alias(f"p_{j + 1}") for j in range(k)]


def with_memberships(df: DataFrame, scaler: Scaler, model: FcmModel, column: str = "p") -> DataFrame:
    """The frame with its membership rows: folded into the projection, or in an Arrow kernel where the expression would be long."""
    names = df.columns
    packed = scaler.pack(df, *names)
    if model.centroids.k * (len(model.gains_num) + len(model.gains_cat)) <= INLINE_TERMS:
        return packed.withColumn(column, membership_column(distance_column(model), model.alpha)).select(*names, column)
    prepare(df.sparkSession)
    n_num, n_cat = len(model.gains_num), len(model.gains_cat)

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            rows = [memberships_block(sqdist_block(x, s, model.centroids, model.gains_num, model.gains_cat, model.unknown), model.alpha) for x, s, _ in blocks(batch, n_num, n_cat)]
            p = np.concatenate(rows) if rows else np.zeros((0, model.centroids.k))
            lists = pa.ListArray.from_arrays(pa.array(np.arange(0, p.size + 1, p.shape[1]), pa.int32()), pa.array(p.reshape(-1)))
            yield pa.RecordBatch.from_arrays([*(batch.column(c) for c in names), lists], [*names, column])

    schema = ", ".join(f"`{f.name}` {f.dataType.simpleString()}" for f in df.schema.fields)
    return packed.withColumn("weight", F.lit(1.0)).mapInArrow(work, f"{schema}, {column} array<double>")


def augment(df: DataFrame, scaler: Scaler, model: FcmModel, T: int, subset: list[str] | None = None) -> DataFrame:
    """The raw columns with z and b (T=1), with all memberships too (T=2), or those of a selected subset (T=3); T=0 adds nothing."""
    if T == 0:
        return df if subset is None else df.select("row_id", *subset)
    z, b = basic_features("p")
    out = with_memberships(df, scaler, model).withColumn("z", z).withColumn("b", b)
    if T >= 2:
        out = out.select("*", *extended_features("p", model.centroids.k))
    out = out.drop("p")
    return out.select("row_id", *subset) if T == 3 and subset is not None else out
