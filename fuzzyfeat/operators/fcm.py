"""Fuzzy c-means under the gain-weighted mixed distance, for many cluster counts in one scan a round.

The squared distance sums, over the features, the gain times the squared difference of the feature's kind: absolute
difference of normalised values or scaled ranks, 0 or 1 for symbolic levels, 1 for unknowns. Memberships go as the inverse
of it to the power 1 / (alpha - 1); a row that lies on centroids shares itself equally among them. Centroids are means with
the memberships to the power alpha as weights, and the heaviest level for symbolic features: each minimises the objective
for fixed memberships, which therefore never rises.

A round is one job: Arrow blocks of packed rows against all centroids of all unfinished counts, partial sums per task, a
tree of sums, and a result of a few thousand numbers whatever the number of rows.
"""

from __future__ import annotations

import pickle
from collections.abc import Iterator
from dataclasses import dataclass, field
from typing import Protocol

import numpy as np
import pyarrow as pa
from pyspark import StorageLevel
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from fuzzyfeat.session import prepare

BLOCK, LOCAL_POINTS = 8192, 100_000
SMALL, FEW_LEVELS = 1024, 64  # rows whose distances to 50 centroids stay in a core's cache; levels that are summed as columns


@dataclass
class Centroids:
    """num: k x numeric features (NaN: unknown); cat: k x symbolic features (codes, -1: unknown)."""

    num: np.ndarray
    cat: np.ndarray

    @property
    def k(self) -> int:
        return len(self.num)


@dataclass
class FcmModel:
    centroids: Centroids
    gains_num: np.ndarray
    gains_cat: np.ndarray
    alpha: float
    unknown: str = "both"
    trace: list[float] = field(default_factory=list)
    converged: bool = False

    @property
    def degenerate(self) -> bool:
        """All gains are zero: distances vanish and memberships are uniform."""
        return not (self.gains_num.any() or self.gains_cat.any())

    def memberships(self, x: np.ndarray, s: np.ndarray) -> np.ndarray:
        """Rows of memberships of packed rows."""
        return memberships_block(sqdist_block(x, s, self.centroids, self.gains_num, self.gains_cat, self.unknown), self.alpha)


class Clustering(Protocol):
    """What the method needs of a fitted clustering: a membership row for any packed row."""

    def memberships(self, x: np.ndarray, s: np.ndarray) -> np.ndarray: ...


class Clusterer(Protocol):
    """Any fuzzy clusterer may take the place of fuzzy c-means: it fits all counts on packed rows (row_id, x, s)."""

    def fit(self, packed: DataFrame, counts: list[int], gains_num: list[float], gains_cat: list[float], n_levels: list[int]) -> dict[int, Clustering]: ...


@dataclass
class FuzzyCMeans:
    """The clusterer of the method; alpha 1 makes it crisp."""

    alpha: float = 3.0
    tol: float = 1e-6
    max_iter: int = 300
    init: str = "hash"
    unknown: str = "both"
    criterion: str = "objective"

    def fit(self, packed: DataFrame, counts: list[int], gains_num: list[float], gains_cat: list[float], n_levels: list[int]) -> dict[int, FcmModel]:
        return fit_many(packed, counts, gains_num, gains_cat, n_levels, self.alpha, self.tol, self.max_iter, self.init, self.unknown, criterion=self.criterion)


@dataclass
class Fitted:
    """Clusterings that exist already, in place of a clusterer: for many classifiers on the same rows."""

    models: dict[int, FcmModel]

    def fit(self, packed: DataFrame, counts: list[int], gains_num: list[float], gains_cat: list[float], n_levels: list[int]) -> dict[int, FcmModel]:
        return {k: self.models[k] for k in counts}


def sqdist_block(x: np.ndarray, s: np.ndarray, v: Centroids, gains_num: np.ndarray, gains_cat: np.ndarray, unknown: str = "both") -> np.ndarray:
    """Squared mixed distances, rows by centroids. unknown: a difference of 1 where both are unknown, or where either is."""
    return distances(expanded(x), s, v, gains_num, gains_cat, unknown)


def expanded(x: np.ndarray) -> np.ndarray:
    """Squares, known marks, values and, if there are any, unknown marks side by side: a distance to any centroid is linear in them."""
    lost = np.isnan(x)
    x0 = np.where(lost, 0, x)
    return np.concatenate([x0**2, ~lost, x0, *([lost] if lost.any() else [])], axis=1)


def distances(terms: np.ndarray, s: np.ndarray, v: Centroids, gains_num: np.ndarray, gains_cat: np.ndarray, unknown: str) -> np.ndarray:
    """sqdist_block of expanded rows: one product, and a table of the levels for each symbolic feature."""
    there = ~np.isnan(v.num)
    v0, absent = np.where(there, v.num, 0), gains_num * ~there
    factors = [gains_num * there, v0**2 * gains_num + (absent if unknown == "either" else 0), -2 * gains_num * v0]
    if terms.shape[1] > 3 * len(gains_num):
        factors.append(absent if unknown == "both" else np.broadcast_to(gains_num, v0.shape))
    d = terms @ np.concatenate(factors, axis=1).T
    np.maximum(d, 0, out=d)
    for j in range(s.shape[1]):
        a, b = np.arange(-2, max(s[:, j].max(initial=-1), v.cat[:, j].max(initial=-1)) + 1)[:, None], v.cat[:, j][None, :]
        unknown_j = ((a == -1) & (b == -1)) if unknown == "both" else ((a == -1) | (b == -1))
        d += (gains_cat[j] * np.where(unknown_j, 1.0, ((a != b) & (a != -1) & (b != -1)).astype(float))).take(s[:, j] + 2, axis=0)
    return d


def memberships_block(d: np.ndarray, alpha: float) -> np.ndarray:
    """Rows of memberships from squared distances; alpha 1: all to the nearest centroid, the first of equals."""
    if alpha <= 1:
        return (np.arange(d.shape[1])[None, :] == d.round(9).argmin(axis=1)[:, None]).astype(float)
    least = d.min(axis=1, keepdims=True)
    on = least[:, 0] <= 0
    with np.errstate(divide="ignore", invalid="ignore"):
        w = np.sqrt(least / d) if alpha == 3 else (d / least) ** (-1 / (alpha - 1))
    w[on] = d[on] <= 0
    return w / w.sum(axis=1, keepdims=True)


def membership_column(distances: Column, alpha: float) -> Column:
    """The same as an array expression over an array of squared distances."""
    if alpha <= 1:
        near = F.transform(distances, lambda d: F.round(d, 9))
        return F.transform(near, lambda d, i: (i + 1 == F.array_position(near, F.array_min(near))).cast("double"))
    least = F.array_min(distances)
    w = F.transform(distances, lambda d: F.when(least <= 0, (d <= 0).cast("double")).otherwise(F.pow(d / least, F.lit(-1 / (alpha - 1)))))
    return F.transform(w, lambda x: x / F.aggregate(w, F.lit(0.0), lambda a, b: a + b))


def distance_column(model: FcmModel) -> Column:
    """Array of squared distances of the packed columns x and s to the centroids: constants are folded into the plan."""
    out = []
    for i in range(model.centroids.k):
        terms = [F.lit(0.0)]
        for q, g in enumerate(model.gains_num):
            v, x = model.centroids.num[i, q], F.get("x", F.lit(q))
            lost = F.isnan(x) if np.isnan(v) or model.unknown == "either" else F.lit(False)
            lost = F.lit(True) if np.isnan(v) and model.unknown == "either" else lost
            terms.append(F.lit(float(g)) * F.when(lost, 1.0).when(F.isnan(x) | F.lit(bool(np.isnan(v))), 0.0).otherwise(F.pow(x - F.lit(0.0 if np.isnan(v) else float(v)), F.lit(2))))
        for q, g in enumerate(model.gains_cat):
            c, s = int(model.centroids.cat[i, q]), F.get("s", F.lit(q))
            lost = ((s == -1) & F.lit(c == -1)) if model.unknown == "both" else ((s == -1) | F.lit(c == -1))
            terms.append(F.lit(float(g)) * F.when(lost, 1.0).when((s == -1) | F.lit(c == -1), 0.0).otherwise((s != c).cast("double")))
        out.append(sum(terms[1:], terms[0]))
    return F.array(*out)


def seeds(packed: DataFrame, k: int, salt: str = "seed") -> Centroids:
    """The k distinct packed rows of least md5 of the row's id."""
    mark = F.md5(F.concat(F.lit(salt), F.col("row_id").cast("string")))
    rows = packed.groupBy("x", "s").agg(F.min(F.struct(mark.alias("m"), F.col("row_id").cast("string").alias("i"))).alias("m")).orderBy("m").limit(k).collect()
    if len(rows) < k:
        raise ValueError(f"{len(rows)} distinct rows can't seed {k} clusters")
    return Centroids(np.array([r["x"] for r in rows], float).reshape(k, -1), np.array([r["s"] for r in rows], np.int64).reshape(k, -1))


def farthest_seeds(packed: DataFrame, k: int, gains_num: np.ndarray, gains_cat: np.ndarray) -> Centroids:
    """Seeds far from each other: the row of least md5, then k - 1 times the row farthest from those before it, over all rows."""
    prepare(packed.sparkSession)
    m, c = len(gains_num), len(gains_cat)
    rows = packed.select(F.md5(F.col("row_id").cast("string")).alias("mark"), "x", "s")
    first = rows.orderBy("mark").first()
    chosen = Centroids(np.array([first["x"]], float).reshape(1, m), np.array([first["s"]], np.int64).reshape(1, c))
    while chosen.k < k:
        now = chosen

        def farthest(batches: Iterator[pa.RecordBatch], now: Centroids = now) -> Iterator[pa.RecordBatch]:
            for batch in batches:
                x = np.asarray(batch.column("x").flatten(), np.float64).reshape(len(batch), m)
                s = np.asarray(batch.column("s").flatten(), np.int64).reshape(len(batch), c)
                d = sqdist_block(x, s, now, gains_num, gains_cat).min(axis=1)
                at = np.flatnonzero(d == d.max())
                at = min(at, key=lambda i: batch.column("mark")[int(i)].as_py())
                yield pa.RecordBatch.from_arrays([*(y.slice(int(at), 1) for y in batch.columns), pa.array([float(d[at])])], [*batch.schema.names, "d"])

        top = rows.mapInArrow(farthest, "mark string, x array<double>, s array<int>, d double").orderBy(F.desc("d"), "mark").first()
        chosen = Centroids(np.concatenate([chosen.num, np.array([top["x"]], float).reshape(1, m)]), np.concatenate([chosen.cat, np.array([top["s"]], np.int64).reshape(1, c)]))
    return chosen


def parallel_seeds(packed: DataFrame, k: int, gains_num: np.ndarray, gains_cat: np.ndarray, rounds: int = 4) -> Centroids:
    """Seeds by oversampling: each round takes about 2 k rows, by chance in proportion to their squared distance, and the few candidates, weighted by the rows nearest to them, are reduced to k far ones.

    Chance is a hash of the row's id and the round, so a repeated task draws the same rows.
    """
    prepare(packed.sparkSession)
    m, c = len(gains_num), len(gains_cat)
    rows = packed.select(F.col("row_id").cast("string").alias("i"), "x", "s")
    arrays = lambda found: Centroids(np.array([r["x"] for r in found], float).reshape(len(found), m), np.array([r["s"] for r in found], np.int64).reshape(len(found), c))
    chosen = arrays([rows.orderBy(F.md5("i"), "i").first()])

    def nearest(now: Centroids):
        def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            for batch in batches:
                x = np.asarray(batch.column("x").flatten(), np.float64).reshape(len(batch), m)
                s = np.asarray(batch.column("s").flatten(), np.int64).reshape(len(batch), c)
                d = sqdist_block(x, s, now, gains_num, gains_cat)
                yield pa.RecordBatch.from_arrays([*batch.columns, pa.array(d.min(axis=1)), pa.array(d.argmin(axis=1).astype(np.int32))], [*batch.schema.names, "d", "z"])

        return rows.mapInArrow(work, "i string, x array<double>, s array<int>, d double, z int")

    for number in range(rounds):
        far = nearest(chosen)
        cost = far.agg(F.sum("d")).first()[0] or 0.0
        if cost <= 0:
            break
        chance = F.pmod(F.xxhash64("i", F.lit(number)), F.lit(1 << 30)) / float(1 << 30)
        drawn = far.filter(chance < 2 * k * F.col("d") / cost).select("i", "x", "s").orderBy("i").collect()
        new = arrays(drawn)
        chosen = Centroids(np.concatenate([chosen.num, new.num]), np.concatenate([chosen.cat, new.cat]))
    weight = np.zeros(chosen.k)
    for r in nearest(chosen).groupBy("z").count().collect():
        weight[r["z"]] = r["count"]
    between = sqdist_block(chosen.num, chosen.cat, chosen, gains_num, gains_cat)
    picks = [int(weight.argmax())]
    while len(picks) < k:
        gain = between[:, picks].min(axis=1) * weight
        if gain.max() <= 0:
            raise ValueError(f"{len(picks)} distinct rows can't seed {k} clusters")
        picks.append(int(gain.argmax()))
    return Centroids(chosen.num[picks], chosen.cat[picks])


def blocks(batch: pa.RecordBatch, n_num: int, n_cat: int) -> Iterator[tuple[np.ndarray, np.ndarray, np.ndarray]]:
    """(x, s, weight) of at most BLOCK rows at a time."""
    for at in range(0, len(batch), BLOCK):
        part = batch.slice(at, BLOCK)
        x = np.asarray(part.column("x").flatten(), np.float64).reshape(len(part), n_num)
        s = np.asarray(part.column("s").flatten(), np.int64).reshape(len(part), n_cat)
        yield x, s, np.asarray(part.column("weight"), np.float64)


def _sums(terms, s, weight, v: Centroids, gains_num, gains_cat, alpha: float, unknown: str, n_levels: list[int]) -> np.ndarray:
    """Of each centroid, over expanded rows: the weighted values and known weights of numeric features, level masses, and the objective. alpha 1 is a crisp clustering."""
    m, d = len(gains_num), distances(terms, s, v, gains_num, gains_cat, unknown)
    p = memberships_block(d, alpha)
    u = (p * p * p if alpha == 3 else p**alpha) * weight[:, None]
    masses = [u.T @ (s[:, q][:, None] == np.arange(n)) if n <= FEW_LEVELS else np.stack([np.bincount(s[s[:, q] >= 0, q], u[s[:, q] >= 0, j], n) for j in range(v.k)]) for q, n in enumerate(n_levels)]
    sums = u.T @ terms[:, m : 3 * m]
    return np.concatenate([sums[:, m:], sums[:, :m], *masses, np.einsum("ij,ij->j", u, d)[:, None]], axis=1)


def _partials(live: dict[int, Centroids], gains_num, gains_cat, alpha: float, unknown: str, n_levels: list[int]):
    """Sums of one task: a row for each count k and centroid."""

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        sums: dict[int, np.ndarray] = {}
        for batch in batches:
            for x, s, weight in blocks(batch, len(gains_num), len(gains_cat)):
                terms = expanded(x)
                for k, v in live.items():
                    sums[k] = sums.get(k, 0) + _sums(terms, s, weight, v, gains_num, gains_cat, alpha, unknown, n_levels)
        for k, total in sums.items():
            for j in range(k):
                yield pa.RecordBatch.from_arrays([pa.array([k], pa.int32()), pa.array([j], pa.int32()), pa.array([total[j].tolist()], pa.list_(pa.float64()))], ["k", "j", "sums"])

    return work


def advance(model: FcmModel, total: np.ndarray, n_levels: list[int], tol: float, criterion: str) -> None:
    """One round of a model from its sums: trace, convergence, and new centroids if it goes on."""
    m = len(model.gains_num)
    model.trace.append(float(total[:, -1].sum()))
    moved = abs(model.trace[-2] - model.trace[-1]) / max(abs(model.trace[-2]), 1e-300) if len(model.trace) > 1 else np.inf
    if criterion == "objective" and moved < tol:
        model.converged = True
        return
    with np.errstate(divide="ignore", invalid="ignore"):
        num = np.where(total[:, m : 2 * m] > 0, total[:, :m] / total[:, m : 2 * m], np.nan)
    cat, at = np.full((len(total), len(n_levels)), -1, np.int64), 2 * m
    for q, n in enumerate(n_levels):
        mass = total[:, at : at + n]
        cat[:, q] = np.where(mass.sum(axis=1) > 0, mass.argmax(axis=1), -1) if n else -1
        at += n
    empty = total[:, m:-1].sum(axis=1) <= 0  # a crisp cluster may lose all its rows: it stays where it is
    num[empty], cat[empty] = model.centroids.num[empty], model.centroids.cat[empty]
    if criterion == "centroids":
        step = np.abs(np.nan_to_num(num) - np.nan_to_num(model.centroids.num)).max(initial=0.0)
        model.converged = bool(step < tol and (cat == model.centroids.cat).all())
    model.centroids = Centroids(num, cat)


def _summed(partials: DataFrame) -> DataFrame:
    """Element-wise sums of the arrays by (k, j), partially summed before they are dealt out."""
    return partials.select("k", "j", F.posexplode("sums").alias("at", "x")).groupBy("k", "j", "at").agg(F.sum("x").alias("x"))


def fit_many(packed: DataFrame, counts: list[int], gains_num, gains_cat, n_levels: list[int], alpha: float = 3.0, tol: float = 1e-6, max_iter: int = 300, init: dict[int, Centroids] | str = "hash", unknown: str = "both", compress: bool | None = None, criterion: str = "objective", local_points: int = LOCAL_POINTS) -> dict[int, FcmModel]:
    """A model for each cluster count, all advanced in the same scans; a count that has converged drops out.

    packed: row_id, x, s. alpha 1: crisp. criterion: "objective" (its relative change is under tol) or "centroids" (none
    moves by tol). compress: equal packed rows become one with a weight, which changes no result; None: if a count of
    distinct rows says that this halves them at least. At most `local_points` distinct rows travel to one task per count,
    which runs all its rounds; beyond that each round is one scan for all counts.
    """
    spark = prepare(packed.sparkSession)
    gains_num, gains_cat = np.asarray(gains_num, float), np.asarray(gains_cat, float)
    models = {k: FcmModel(v, gains_num, gains_cat, alpha, unknown) for k, v in start(packed, counts, gains_num, gains_cat, init).items()}
    if compress is None:
        n = packed.agg(F.count("*").alias("n"), F.approx_count_distinct(F.xxhash64("x", "s")).alias("d")).first()
        compress = n["d"] <= 0.5 * n["n"]
    points = (packed.groupBy("x", "s").agg(F.count("*").cast("double").alias("weight")) if compress else packed.select("x", "s", F.lit(1.0).alias("weight"))).persist(StorageLevel.MEMORY_AND_DISK)
    try:
        if tol > 0 and points.count() <= local_points:
            return _fit_local(spark, points, models, n_levels, tol, max_iter, criterion)
        live = set(models)
        for _ in range(max_iter):
            any_ = next(iter(models.values()))
            for k, total in round_sums(points, {k: models[k].centroids for k in sorted(live)}, any_, n_levels).items():
                advance(models[k], total, n_levels, tol, criterion)
            live = {k for k in live if not models[k].converged}
            if not live:
                break
        return models
    finally:
        points.unpersist()


def round_sums(points: DataFrame, live: dict[int, Centroids], model: FcmModel, n_levels: list[int]) -> dict[int, np.ndarray]:
    """The sums of one round over points (x, s, weight) for the centroids of all counts: one job. Gains, alpha and rule are the model's."""
    width = 2 * len(model.gains_num) + sum(n_levels) + 1
    totals = {k: np.zeros((k, width)) for k in live}
    partials = points.mapInArrow(_partials(live, model.gains_num, model.gains_cat, model.alpha, model.unknown, n_levels), "k int, j int, sums array<double>")
    for r in _summed(partials).collect():
        totals[r["k"]][r["j"], r["at"]] = r["x"]
    return totals


def start(packed: DataFrame, counts: list[int], gains_num, gains_cat, init: dict[int, Centroids] | str) -> dict[int, Centroids]:
    """Starting centroids of each count. Those of hash and farthest are nested, so one pass for the largest count serves all."""
    if isinstance(init, dict):
        return {k: init[k] for k in counts}
    if init == "parallel":
        return {k: parallel_seeds(packed, k, gains_num, gains_cat) for k in counts}
    most = seeds(packed, max(counts)) if init == "hash" else farthest_seeds(packed, max(counts), gains_num, gains_cat)
    return {k: Centroids(most.num[:k], most.cat[:k]) for k in counts}


def _fit_local(spark, points: DataFrame, models: dict[int, FcmModel], n_levels: list[int], tol: float, max_iter: int, criterion: str) -> dict[int, FcmModel]:
    """All rounds of a count in one task, the counts side by side: for points that are few enough to travel."""
    any_ = next(iter(models.values()))
    m, c = len(any_.gains_num), len(any_.gains_cat)
    rows = points.orderBy("x", "s").select("x", "s", "weight").toArrow().combine_chunks()
    x, s, weight = (np.concatenate([np.zeros(0, t), *(np.asarray(y.flatten() if n != "weight" else y, t) for y in rows.column(n).chunks)]) for n, t in (("x", float), ("s", np.int64), ("weight", float)))
    shared = spark.sparkContext.broadcast((x.reshape(len(rows), m), s.reshape(len(rows), c), weight, models))

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        x, s, weight, models = shared.value
        parts = [(expanded(x[i : i + SMALL]), s[i : i + SMALL], weight[i : i + SMALL]) for i in range(0, max(1, len(x)), SMALL)]
        for batch in batches:
            for k in batch.column(0).to_pylist():
                model = models[k]
                for _ in range(max_iter):
                    total = sum(_sums(terms, *part, model.centroids, model.gains_num, model.gains_cat, model.alpha, model.unknown, n_levels) for terms, *part in parts)
                    advance(model, total, n_levels, tol, criterion)
                    if model.converged:
                        break
                yield pa.RecordBatch.from_arrays([pa.array([k], pa.int32()), pa.array([pickle.dumps(model)], pa.binary())], ["k", "model"])

    # the largest counts first, one task each
    jobs = spark.createDataFrame([(k,) for k in sorted(models, reverse=True)], "k int").repartition(len(models), "k")
    return {r["k"]: pickle.loads(r["model"]) for r in sorted(jobs.mapInArrow(work, "k int, model binary").collect(), key=lambda r: r["k"])}
