"""Reduced sets, splits and stratified folds. All are functions of hashed row ids, so a repeated task gives the same rows."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F
from pyspark.sql import types as T

from fuzzyfeat.functions.hashing import h

BUCKETS_BITS = 20  # of the 32-bit hash, the digits below a bucket


def train_test(df: DataFrame) -> DataFrame:
    """A `part` column: train or test, by the id's hash."""
    return df.withColumn("part", F.when(h("split", "row_id") % 2 == 0, "train").otherwise("test"))


def reduced(df: DataFrame, fractions: dict[str, float], column: str = "label") -> DataFrame:
    """The named strata thinned to a fraction, all others whole: a predicate, no shuffle."""
    keep = F.lit(True)
    for value, fraction in fractions.items():
        keep = F.when(F.col(column) == value, h("thin", "row_id") % 1000 < 1000 * fraction).otherwise(keep)
    return df.filter(keep)


def stratified_folds(df: DataFrame, stratum: str = "fine_label", q: int = 10, salt: str = "fold") -> DataFrame:
    """A `fold` column: the rank inside the stratum by (hash, row_id), modulo q.

    A stratum may hold most rows, so the rank is counted in two levels: inside buckets of the hash's leading digits, and over
    the counts of the buckets, which are few. The result is that of one sort of the whole stratum.
    """
    rows = df.withColumn("__h", h(salt, "row_id")).withColumn("__b", F.shiftright("__h", BUCKETS_BITS))
    inside = F.row_number().over(Window.partitionBy(stratum, "__b").orderBy("__h", "row_id")) - 1
    counts = rows.groupBy(stratum, "__b").count()
    before = counts.withColumn("__before", F.coalesce(F.sum("count").over(Window.partitionBy(stratum).orderBy("__b").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0))).drop("count")
    # null is a stratum like any other
    before = before.select(F.col(stratum).alias("__s"), F.col("__b").alias("__bb"), "__before")
    ranked = rows.withColumn("__rank", inside).join(before, F.col(stratum).eqNullSafe(F.col("__s")) & (F.col("__b") == F.col("__bb"))).drop("__s", "__bb")
    return ranked.withColumn("fold", ((F.col("__rank") + F.col("__before")) % q).cast("int")).drop("__h", "__b", "__rank", "__before")


def quotas(sizes: dict, most: int) -> dict:
    """How many rows of each stratum make up `most` rows: small strata whole, the rest in proportion.

    What every stratum has for certain is min(its size, f), with the largest f up to 1 % of `most` at which these take half of it.
    """
    total = sum(sizes.values())
    if total <= most:
        return dict(sizes)
    low, high = 0, max(1, most // 100)
    while low < high:
        f = (low + high + 1) // 2
        low, high = (f, high) if sum(min(n, f) for n in sizes.values()) <= most / 2 else (low, f - 1)
    sure = {k: min(n, low) for k, n in sizes.items()}
    left, rest = most - sum(sure.values()), total - sum(sure.values())
    exact = {k: (sizes[k] - sure[k]) * left / rest for k in sizes}
    out = {k: sure[k] + int(x) for k, x in exact.items()}
    # the rows that rounding down left go to the largest remainders
    for k in sorted(sizes, key=lambda k: (int(exact[k]) - exact[k], str(k)))[: most - sum(out.values())]:
        out[k] += 1
    return out


def bounded(df: DataFrame, most: int, stratum: str = "fine_label") -> DataFrame:
    """All rows, or `most` of them by the hash of row_id, dealt over the strata by `quotas`; null is a stratum of its own.

    A threshold on the hash lets a few more rows pass than a stratum may keep, so the exact cut ranks bounded sets only.
    """
    sizes = {r[stratum]: r["count"] for r in df.groupBy(stratum).count().collect()}
    keep = quotas(sizes, most)
    if keep == sizes:
        return df
    rows = [(k, q, min(2**32, int((q + 8 * q**0.5 + 10) / sizes[k] * 2**32) + 1)) for k, q in keep.items()]
    table = df.sparkSession.createDataFrame(rows, T.StructType([T.StructField("__s", df.schema[stratum].dataType), T.StructField("__q", T.LongType()), T.StructField("__t", T.LongType())]))
    near = df.withColumn("__h", h("thin", "row_id")).join(F.broadcast(table), F.col(stratum).eqNullSafe(F.col("__s"))).filter(F.col("__h") < F.col("__t"))
    ranked = near.withColumn("__r", F.row_number().over(Window.partitionBy(stratum).orderBy("__h", "row_id")))
    return ranked.filter(F.col("__r") <= F.col("__q")).select(df.columns)
