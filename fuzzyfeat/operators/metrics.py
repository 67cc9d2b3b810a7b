"""Confusion counts and the measures that follow from them."""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F


def confusion(df: DataFrame, label: str = "label", prediction: str = "prediction") -> DataFrame:
    """(label, prediction, n)."""
    return df.groupBy(F.col(label).alias("label"), F.col(prediction).alias("prediction")).agg(F.count("*").alias("n"))


def rates(counts: DataFrame) -> DataFrame:
    """(label, tpr, fpr, n) of every true class, also those never predicted; null where a rate has no base."""
    both = counts.select("n", F.explode(F.array(F.struct(F.col("label").alias("c"), F.lit(1).alias("true")), F.struct(F.col("prediction").alias("c"), F.lit(0).alias("true")))).alias("e"), "label", "prediction")
    per = both.groupBy(F.col("e.c").alias("label_")).agg(
        F.sum(F.when((F.col("e.true") == 1), F.col("n")).otherwise(0)).alias("n"),
        F.sum(F.when((F.col("e.true") == 1) & (F.col("label") == F.col("prediction")), F.col("n")).otherwise(0)).alias("tp"),
        F.sum(F.when((F.col("e.true") == 0) & (F.col("label") != F.col("prediction")), F.col("n")).otherwise(0)).alias("fp"),
    )
    total = per.withColumn("all", F.sum("n").over(Window.partitionBy(F.lit(0))))  # one row for each class
    return total.filter("n > 0").select(F.col("label_").alias("label"), F.try_divide("tp", "n").alias("tpr"), F.try_divide(F.col("fp"), F.col("all") - F.col("n")).alias("fpr"), F.col("n").cast("long").alias("n"))


def average_rates(table: DataFrame) -> DataFrame:
    """(avg_tpr, avg_fpr), weighted by class sizes."""
    return table.agg((F.sum(F.col("n") * F.col("tpr")) / F.sum("n")).alias("avg_tpr"), (F.sum(F.col("n") * F.col("fpr")) / F.sum("n")).alias("avg_fpr"))


def accuracy(counts: DataFrame) -> DataFrame:
    return counts.agg((F.sum(F.when(F.col("label") == F.col("prediction"), F.col("n")).otherwise(0)) / F.sum("n")).alias("accuracy"))


def mean_over_settings(table: DataFrame, family: str) -> DataFrame:
    """Plain means of the average rates over a family's settings."""
    return table.groupBy(family).agg(F.avg("avg_tpr").alias("avg_tpr"), F.avg("avg_fpr").alias("avg_fpr"))


def class_distribution(df: DataFrame, part: str = "part", label: str = "label") -> DataFrame:
    """(part, label, n) with the totals of each part and of all as nulls."""
    return df.rollup(part, label).agg(F.count("*").alias("n")).select(F.col(part).alias("part"), F.col(label).alias("label"), "n")
