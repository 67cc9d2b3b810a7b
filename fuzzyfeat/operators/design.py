"""The columns that learners see: raw ones and, beside them, those of a clustering."""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from fuzzyfeat.operators.fcm import Clustering
from fuzzyfeat.operators.features import DIGITS
from fuzzyfeat.operators.learners.data import Frame
from fuzzyfeat.operators.prepare import Scaler
from fuzzyfeat.plans.spec import Feature

BLOCK = 8192


def raw_columns(df: DataFrame, scaler: Scaler, *keep: str) -> DataFrame:
    """row arrays r (raw numeric values, NaN for unknown), x and s."""
    numeric = [F.coalesce(F.col(f.name).cast("double"), F.lit(float("nan"))) for f in scaler.spec if f.numeric]
    packed = scaler.pack(df.withColumn("r", F.array(*numeric) if numeric else F.array().cast("array<double>")), *keep, "r")
    return packed


def frame_of(r: np.ndarray, s: np.ndarray, spec: list[Feature]) -> Frame:
    return Frame(r, s, [f.name for f in spec if f.numeric], [f.name for f in spec if not f.numeric])


def cluster_frame(x: np.ndarray, s: np.ndarray, model: Clustering | None, T: int) -> Frame | None:
    """z, b and, for T of 2 or 3, the membership columns."""
    if T == 0 or model is None:
        return None
    p = np.round(model.memberships(x, s), DIGITS)
    num, names = [p.max(axis=1)], ["b"]
    if T >= 2:
        num += list(p.T)
        names += [f"p_{j + 1}" for j in range(p.shape[1])]
    return Frame(np.stack(num, axis=1), p.argmax(axis=1)[:, None], names, ["z"])


def design(raw: Frame, x: np.ndarray, s: np.ndarray, model: Clustering | None, T: int) -> Frame:
    extra = cluster_frame(x, s, model, T)
    return raw if extra is None else raw.beside(extra)


@dataclass
class View:
    """The design of each count, read from batches of packed rows (r, x, s)."""

    spec: list[Feature]
    models: dict[int, Clustering | None]
    T: int
    subsets: dict[int, list[str]] = field(default_factory=dict)

    def frame(self, k: int, r: np.ndarray, x: np.ndarray, s: np.ndarray) -> Frame:
        out = design(frame_of(r, s, self.spec), x, s, self.models[k], self.T)
        return out.only(self.subsets[k]) if k in self.subsets else out

    def empty(self, k: int) -> Frame:
        n = sum(f.numeric for f in self.spec)
        return self.frame(k, np.zeros((0, n)), np.zeros((0, n)), np.zeros((0, len(self.spec) - n), np.int64))

    def blocks(self, batches: Iterator[pa.RecordBatch], counts: list[int]) -> Iterator[tuple[dict[int, Frame], np.ndarray, np.ndarray, pa.RecordBatch]]:
        """(frame of each count, classes, folds, the rows themselves) of at most BLOCK rows at a time."""
        n = sum(f.numeric for f in self.spec)
        for batch in batches:
            for at in range(0, len(batch), BLOCK):
                part = batch.slice(at, BLOCK)
                r, x, s = (np.asarray(part.column(c).flatten(), t).reshape(len(part), m) for c, t, m in (("r", float, n), ("x", float, n), ("s", np.int64, len(self.spec) - n)))
                yield {k: self.frame(k, r, x, s) for k in counts}, np.asarray(part.column("y"), np.int64), np.asarray(part.column("fold"), np.int64), part
