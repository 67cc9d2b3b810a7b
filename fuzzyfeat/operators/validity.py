"""Cluster validity: the usual way to choose a cluster count, which candidate classifiers replace."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from fuzzyfeat.operators.fcm import FcmModel, blocks, distance_column, membership_column, memberships_block, sqdist_block
from fuzzyfeat.operators.features import INLINE_TERMS
from fuzzyfeat.session import prepare


def validity(packed: DataFrame, models: dict[int, FcmModel]) -> DataFrame:
    """(k, pc, pe, xb): partition coefficient and entropy, and Xie-Beni, all counts in one pass: as expressions, or in an Arrow kernel where these would be long."""
    if sum(m.centroids.k * (len(m.gains_num) + len(m.gains_cat)) for m in models.values()) > INLINE_TERMS:
        return _by_kernel(packed, models)
    rows = []
    for k, model in sorted(models.items()):
        d = distance_column(model)
        rows.append(F.struct(F.lit(k).alias("k"), d.alias("d"), membership_column(d, model.alpha).alias("p"), F.lit(separation(model)).alias("sep"), F.lit(model.alpha).alias("alpha")))
    each = packed.select(F.explode(F.array(*rows)).alias("r")).select("r.*")
    total = lambda xs, f: F.aggregate(xs, F.lit(0.0), lambda a, x: a + f(x))
    both = F.zip_with("p", "d", lambda p, d: F.pow(p, F.col("alpha")) * d)
    measured = each.groupBy("k").agg(F.avg(total(F.col("p"), lambda x: x * x)).alias("pc"), F.avg(total(F.col("p"), lambda x: F.when(x > 0, -x * F.ln(x)).otherwise(0.0))).alias("pe"), (F.sum(total(both, lambda x: x)) / (F.count("*") * F.first("sep"))).alias("xb"))
    return measured


def _by_kernel(packed: DataFrame, models: dict[int, FcmModel]) -> DataFrame:
    shared = prepare(packed.sparkSession).sparkContext.broadcast(models)
    any_ = next(iter(models.values()))
    m, c = len(any_.gains_num), len(any_.gains_cat)

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        sums = {k: np.zeros(4) for k in shared.value}
        for batch in batches:
            for x, s, weight in blocks(batch, m, c):
                for k, model in shared.value.items():
                    d = sqdist_block(x, s, model.centroids, model.gains_num, model.gains_cat, model.unknown)
                    p = memberships_block(d, model.alpha)
                    sums[k] += (p * p).sum(), -(p * np.log(np.where(p > 0, p, 1))).sum(), (p**model.alpha * d).sum(), len(x)
        yield pa.RecordBatch.from_arrays([pa.array(list(sums), pa.int32()), *(pa.array([float(t[i]) for t in sums.values()]) for i in range(4))], ["k", "pc", "pe", "within", "n"])

    parts = packed.select("x", "s", F.lit(1.0).alias("weight")).mapInArrow(work, "k int, pc double, pe double, within double, n double")
    apart = F.element_at(F.create_map(*(F.lit(v) for k, model in models.items() for v in (k, separation(model)))), F.col("k"))
    return parts.groupBy("k").agg(*(F.sum(x).alias(x) for x in ("pc", "pe", "within", "n"))).select("k", (F.col("pc") / F.col("n")).alias("pc"), (F.col("pe") / F.col("n")).alias("pe"), (F.col("within") / (F.col("n") * apart)).alias("xb"))


def separation(model: FcmModel) -> float:
    """Least squared distance between two centroids."""
    v = model.centroids
    d = sqdist_block(v.num, v.cat, v, model.gains_num, model.gains_cat, model.unknown)
    return float(min(d[i, j] for i in range(v.k) for j in range(i))) if v.k > 1 else 0.0


def best_k(table: DataFrame, index: str = "pc") -> int:
    """The count that the index prefers: most for pc, least for pe and xb; ties to the smaller."""
    order = F.desc(index) if index == "pc" else F.asc(index)
    return table.orderBy(order, "k").first()["k"]
