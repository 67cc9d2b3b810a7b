"""Lifted input spaces for plain learners: principal components, degree-2 monomials, or Gaussian similarities to landmarks.

All three take the normalised numeric columns and one column per symbolic level; unknown values are 0. They are row-local
once fitted, so scoring is one projection.
"""

from __future__ import annotations

import math

from pyspark.ml.feature import PCA, PolynomialExpansion
from pyspark.ml.functions import array_to_vector, vector_to_array
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from fuzzyfeat.operators.prepare import Scaler, fit_scaler
from fuzzyfeat.plans.spec import Feature


def inputs(scaler: Scaler) -> Column:
    """The normalised columns and the level indicators of a row as one array."""
    numeric = [F.coalesce(scaler.numeric(f), F.lit(0.0)) for f in scaler.spec if f.numeric]
    levels = [F.coalesce((F.col(f.name).cast("string") == level).cast("double"), F.lit(0.0)) for f in scaler.spec if not f.numeric for level in scaler.levels[f.name]]
    return F.array(*numeric, *levels)


def lift(train: DataFrame, spec: list[Feature], kind: str, width: int = 8, gamma: float = 0.1) -> tuple[list[Feature], object]:
    """(columns of the lifted space, function that puts them in place of the raw ones), fitted on the training rows.

    kind: "pca" (width components), "poly" (monomials up to degree 2) or "rbf" (similarities to `width` rows of least hash).
    """
    scaler = fit_scaler(train, spec)
    packed = lambda df: df.withColumn("__v", array_to_vector(inputs(scaler)))
    size = sum(f.numeric for f in spec) + sum(len(scaler.levels[f.name]) for f in spec if not f.numeric)
    if kind == "pca":
        width = min(width, size)
        model = PCA(k=width, inputCol="__v", outputCol="__l").fit(packed(train))
        made = lambda df: model.transform(packed(df)).withColumn("__a", vector_to_array("__l"))
    elif kind == "poly":
        width = math.comb(size + 2, 2) - 1
        model = PolynomialExpansion(degree=2, inputCol="__v", outputCol="__l")
        made = lambda df: model.transform(packed(df)).withColumn("__a", vector_to_array("__l"))
    elif kind == "rbf":
        marks = [r["a"] for r in train.select(inputs(scaler).alias("a"), F.md5(F.col("row_id").cast("string")).alias("m")).orderBy("m").limit(width).collect()]
        width = len(marks)
        near = lambda mark: F.exp(-gamma * F.aggregate(F.zip_with("__x", F.array(*map(F.lit, mark)), lambda a, b: (a - b) * (a - b)), F.lit(0.0), lambda s, x: s + x))
        made = lambda df: df.withColumn("__x", inputs(scaler)).withColumn("__a", F.array(*(near(m) for m in marks)))
    else:
        raise ValueError(f"unknown lifted space {kind}")
    columns = [Feature(f"{kind}_{j + 1}", "continuous") for j in range(width)]

    def apply(df: DataFrame) -> DataFrame:
        rest = [c for c in df.columns if c not in {f.name for f in spec}]
        return made(df).select(*rest, *(F.get("__a", F.lit(j)).alias(f.name) for j, f in enumerate(columns)))

    return columns, apply
