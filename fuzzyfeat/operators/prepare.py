"""Normalisation and packing: statistics are fitted once on the training rows and frozen.

Only the clustering sees normalised values; learners get the raw columns.
"""

from __future__ import annotations

from dataclasses import dataclass, field

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from fuzzyfeat.plans.spec import Feature

MOST_LEVELS = 100_000


@dataclass
class Scaler:
    """Affine maps of the continuous features (value - shift) / scale, and the code of each symbolic level."""

    spec: list[Feature]
    method: str
    shift: dict[str, float] = field(default_factory=dict)
    scale: dict[str, float] = field(default_factory=dict)
    levels: dict[str, list[str]] = field(default_factory=dict)

    def numeric(self, f: Feature) -> Column:
        """A constant column maps to 0, ordinal ranks to rank / (levels - 1); values outside the training range are kept."""
        value = F.col(f.name).cast("double")
        if f.kind == "ordinal":
            return value / (f.levels - 1) if f.levels > 1 else F.when(value.isNotNull(), 0.0)
        if self.method == "none":
            return value
        return (value - self.shift[f.name]) / self.scale[f.name] if self.scale[f.name] else F.when(value.isNotNull(), 0.0)

    def symbolic(self, f: Feature) -> Column:
        """Code of the level; -1 for unknown, -2 for a level that training had not."""
        codes = F.map_from_arrays(F.array(*map(F.lit, self.levels[f.name])), F.array(*map(F.lit, range(len(self.levels[f.name]))))) if self.levels[f.name] else None
        return F.when(F.col(f.name).isNull(), -1).otherwise(F.coalesce(F.try_element_at(codes, F.col(f.name).cast("string")), F.lit(-2)) if codes is not None else F.lit(-2))

    def pack(self, df: DataFrame, *keep: str) -> DataFrame:
        """x array<double> (unknown: NaN) and s array<int> beside the kept columns: one projection."""
        x = [F.coalesce(self.numeric(f), F.lit(float("nan"))) for f in self.spec if f.numeric]
        s = [self.symbolic(f) for f in self.spec if not f.numeric]
        return df.select(*keep, (F.array(*x) if x else F.array().cast("array<double>")).alias("x"), (F.array(*s) if s else F.array().cast("array<int>")).alias("s"))

    def columns(self) -> list[Column]:
        return [self.numeric(f).alias(f.name) for f in self.spec if f.numeric]


def fit_scaler(df: DataFrame, spec: list[Feature], method: str = "minmax") -> Scaler:
    """minmax, zscore or none: one aggregate for the statistics and one for the levels of symbolic features."""
    out = Scaler(spec, method)
    continuous = [f for f in spec if f.kind == "continuous"]
    aggregates = [a for f in continuous for a in ((F.min(f.name), F.max(f.name)) if method == "minmax" else (F.avg(f.name), F.stddev_pop(f.name)))]
    row = df.agg(*aggregates).first() if aggregates and method != "none" else ()
    for i, f in enumerate(continuous if method != "none" else []):
        low, high = row[2 * i] or 0.0, row[2 * i + 1] or 0.0
        out.shift[f.name], out.scale[f.name] = float(low), float(high - low if method == "minmax" else high)
    for f in spec:
        if not f.numeric:
            levels = [r[0] for r in df.select(F.col(f.name).cast("string")).distinct().limit(MOST_LEVELS + 1).collect() if r[0] is not None]
            if len(levels) > MOST_LEVELS:
                raise ValueError(f"{f.name} has more than {MOST_LEVELS} levels: bin or hash it first")
            out.levels[f.name] = sorted(levels)
    return out
