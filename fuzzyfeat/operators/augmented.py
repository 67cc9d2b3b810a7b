"""Classifiers on cluster-augmented rows: one candidate for each cluster count, the best by stratified cross validation.

Clusterings of all counts run over all rows in shared scans. Trees and kernel machines train on all rows: up to
TRAVEL numbers, every executor gets them once and the (count, fold) jobs spread over the cluster; beyond that, they are trained
by scans over all rows. Votes of levels train on counts over all rows, however many. Only ensembles and naive-Bayes-leaf trees
train on a reduced set of at most MAX_TRAIN rows. Only the winner is fitted without leaving out a fold.
New rows are scored in one pass without a shuffle.

Scope "paper": gains, centroids and the selected subset come from all training rows, once for each count, before the folds.
Scope "nested": all of these are fitted anew without the rows of each fold, so that no score has seen its test rows.
"""

from __future__ import annotations

import json
import pickle
import time
from collections.abc import Callable, Iterator
from dataclasses import dataclass, field
from functools import partial

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from fuzzyfeat.operators.design import View, cluster_frame, design, frame_of, raw_columns
from fuzzyfeat.operators.fcm import Clusterer, Clustering, FcmModel, FuzzyCMeans
from fuzzyfeat.operators.features import DIGITS
from fuzzyfeat.operators.infogain import gains, uncertainty
from fuzzyfeat.operators.learners.data import Frame
from fuzzyfeat.operators.learners.svm import KernelSVM
from fuzzyfeat.operators.learners.tree import AdaBoostM1, Bagging, C45Tree, LevelVote, NBTree
from fuzzyfeat.operators.prepare import Scaler, fit_scaler
from fuzzyfeat.operators.sampling import bounded, stratified_folds
from fuzzyfeat.operators.selection import CfsSelector
from fuzzyfeat.operators.whole import fit_machines, grow_trees, verdicts
from fuzzyfeat.plans.spec import Feature
from fuzzyfeat.session import materialise, prepare, release, scratch

MAX_TRAIN = 50_000
JOB = pa.schema([("k", pa.int32()), ("fold", pa.int32()), ("score", pa.float64()), ("n", pa.int64()), ("model", pa.binary())])
LEARNERS: dict[str, Callable] = {
    "dt": lambda **o: C45Tree(**o), "psvm": lambda **o: KernelSVM("poly", **o), "rsvm": lambda **o: KernelSVM("rbf", **o),
    "vote": lambda **o: LevelVote(**o), "boost": lambda **o: AdaBoostM1(**o), "bag": lambda **o: Bagging(**o), "nbtree": lambda **o: NBTree(**o),
}
WHOLE = ("dt", "psvm", "rsvm")  # learners that train on all rows
TRAVEL, NODE = 4_000_000, 8_000_000  # numbers of a training set up to which it travels to the executors, and of a tree's node up to which one task grows the rest


def _share(hit: np.ndarray, w: np.ndarray | None, of: np.ndarray) -> float:
    """Mean of hit over the rows `of`; w: how often each row counts."""
    return float(np.average(hit[of], weights=None if w is None else w[of]))


def _accuracy(y: np.ndarray, said: np.ndarray, w: np.ndarray | None = None) -> float:
    return _share(y == said, w, np.ones(len(y), bool))


def _balanced(y: np.ndarray, said: np.ndarray, w: np.ndarray | None = None) -> float:
    """Plain mean of the classes' true-positive rates."""
    return float(np.mean([_share(said == c, w, y == c) for c in np.unique(y)]))


def _rate_gap(y: np.ndarray, said: np.ndarray, w: np.ndarray | None = None) -> float:
    """Average true-positive rate less average false-positive rate, weighted by class sizes."""
    whole = np.ones(len(y), bool)
    return float(sum(_share(y == c, w, whole) * (_share(said == c, w, y == c) - (_share(said == c, w, y != c) if (y != c).any() else 0.0)) for c in np.unique(y)))


#: What a candidate is scored by on the rows of a fold: (true classes, predicted ones, how often each row counts; None: once) -> the more the better.
MEASURES: dict[str, Callable[..., float]] = {"accuracy": _accuracy, "balanced": _balanced, "rate_gap": _rate_gap}


@dataclass
class Reduced:
    """The reduced training set as arrays: raw columns for learners, normalised ones for memberships."""

    raw: Frame
    x: np.ndarray
    s: np.ndarray
    y: np.ndarray
    fold: np.ndarray
    classes: list[str]


def _jobs(spark, data: Reduced, models: dict[int, Clustering | None], jobs: list[tuple[int, int]], T: int, learner: str, options: dict, subsets: dict[int, list[str]], selector=None, measure: str = "accuracy") -> dict[tuple[int, int], tuple]:
    """(k, fold) -> (score, rows, (trained, subset)) of each job; fold -1 trains on all rows. One task a job; the arrays are bounded by MAX_TRAIN.

    subsets: the columns of each count, if chosen before; else the selector chooses them from the job's own training rows.
    """
    shared = spark.sparkContext.broadcast((data, models))

    def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        data, models = shared.value
        for batch in batches:
            for k, fold in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), strict=True):
                rows, test = np.flatnonzero(data.fold != fold), np.flatnonzero(data.fold == fold)
                frame = design(data.raw, data.x, data.s, models[k], T)
                subset = subsets.get(k)
                if subset is None and selector is not None:
                    subset = selector.select(frame.rows(rows), data.y[rows], len(data.classes))
                frame = frame.only(subset) if subset is not None else frame
                trained = LEARNERS[learner](**options).fit(frame.rows(rows), data.y[rows], len(data.classes))
                score = MEASURES[measure](data.y[test], trained.predict(frame.rows(test))) if len(test) else 0.0
                yield pa.RecordBatch.from_pydict({"k": [k], "fold": [fold], "score": [score], "n": [len(test)], "model": [pickle.dumps((trained, subset)) if fold < 0 else b""]}, schema=JOB)

    frame = spark.createDataFrame(jobs, "k int, fold int").repartition(max(1, len(jobs)), "k", "fold")
    return {(r["k"], r["fold"]): (r["score"], r["n"], pickle.loads(r["model"]) if r["model"] else None) for r in frame.mapInArrow(work, "k int, fold int, score double, n long, model binary").collect()}


def _whole_jobs(df: DataFrame, scaler: Scaler, models: dict[int, Clustering | None], jobs: list[tuple[int, int]], T: int, learner: str, options: dict, subsets: dict[int, list[str]], q: int, label: str, classes: list[str], node: int, measure: str = "accuracy") -> dict[tuple[int, int], tuple]:
    """The same as _jobs by scans over all rows; of a tree, what lies below a node of at most `node` rows is grown in one task."""
    y = F.array_position(F.array(*map(F.lit, classes)), F.col(label).cast("string")).cast("int") - 1
    dealt = df if "fold" in df.columns else stratified_folds(df, "fine_label", q)
    view, make = View(scaler.spec, models, T, subsets), partial(LEARNERS[learner], **options)
    with scratch(prepare(df.sparkSession)) as keep:
        rows = keep(raw_columns(dealt.withColumn("y", y).withColumn("id", F.col("row_id").cast("string")), scaler, "id", "y", "fold"))
        fitted = grow_trees(rows, view, jobs, make, len(classes), node) if learner == "dt" else fit_machines(rows, view, jobs, make, len(classes))
        told = verdicts(rows, view, {job: model for job, model in fitted.items() if job[1] >= 0})
    score = lambda job: (MEASURES[measure](*told[job]), int(told[job][2].sum())) if job in told else (0.0, 0)
    return {(k, f): (*score((k, f)), (model, subsets.get(k)) if f < 0 else None) for (k, f), model in fitted.items()}


def _vote_jobs(df: DataFrame, scaler: Scaler, models: dict[int, Clustering | None], jobs: list[tuple[int, int]], T: int, options: dict, q: int, label: str, classes: list[str], measure: str = "accuracy") -> dict[tuple[int, int], tuple]:
    """The same as _jobs for votes of levels, on all rows: their folds, classes and levels are counted in one scan for all models.

    What is collected is bounded by folds, classes and the levels of the columns that may vote, whatever the number of rows.
    """
    spark, spec = prepare(df.sparkSession), scaler.spec
    n_num, raw = sum(f.numeric for f in spec), [f.name for f in spec if not f.numeric]
    voting = lambda n: options.get("column") in (None, n)
    y = F.array_position(F.array(*map(F.lit, classes)), F.col(label).cast("string")).cast("int") - 1
    dealt = df if "fold" in df.columns else stratified_folds(df, "fine_label", q)
    rows = scaler.pack(dealt.withColumn("y", y), "y", "fold")
    shared = spark.sparkContext.broadcast(models)

    def count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        sums: dict[tuple[int, ...], int] = {}
        for batch in batches:
            x, s = (np.asarray(batch.column(c).flatten(), t).reshape(len(batch), n) for c, t, n in (("x", float, n_num), ("s", np.int64, len(raw))))
            head = [np.asarray(batch.column(c), np.int64) for c in ("fold", "y")]
            for k, model in shared.value.items():
                extra = cluster_frame(x, s, model, min(T, 1))
                codes = [s[:, j] for j, n in enumerate(raw) if voting(n)] + ([extra.cat[:, 0]] if extra is not None and voting("z") else [])
                values, times = np.unique(np.stack(head + codes, axis=1), axis=0, return_counts=True)
                for cell, n in zip(values.tolist(), times.tolist(), strict=True):
                    sums[k, *cell] = sums.get((k, *cell), 0) + n
        if sums:
            cells = [(k, fold, y, codes, n) for (k, fold, y, *codes), n in sums.items()]
            yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*cells, strict=True), (pa.int32(), pa.int32(), pa.int32(), pa.list_(pa.int32()), pa.int64()), strict=True)], ["k", "fold", "y", "codes", "n"])

    cells = rows.mapInArrow(count, "k int, fold int, y int, codes array<int>, n long").groupBy("k", "fold", "y", "codes").agg(F.sum("n").alias("n")).collect()
    out = {}
    for k in models:
        names = [n for n in raw + ["z"] * (T > 0) if voting(n)]
        own = [r for r in cells if r["k"] == k]
        codes = np.array([r["codes"] for r in own], np.int64).reshape(len(own), len(names))
        y, fold, n = (np.array([r[c] for r in own], np.int64) for c in ("y", "fold", "n"))
        frame = Frame(np.zeros((len(own), 0)), codes, [], names)
        for f in (f for kk, f in jobs if kk == k):
            rest, test = np.flatnonzero(fold != f), np.flatnonzero(fold == f)
            trained = LEARNERS["vote"](**options).fit(frame.rows(rest), y[rest], len(classes), n[rest].astype(float))
            score = MEASURES[measure](y[test], trained.predict(frame.rows(test)), n[test]) if len(test) else 0.0
            out[k, f] = (score, int(n[test].sum()), (trained, None) if f < 0 else None)
    return out


def associations(df: DataFrame, spec: list[Feature], scaler: Scaler, models: dict[int, Clustering | None], T: int, label: str, bins: int = 10) -> dict[int, tuple[list[str], np.ndarray, np.ndarray]]:
    """For each count: names, associations with the class and mutual associations of the raw and cluster columns, counted over all rows in one scan.

    Continuous columns are counted in bins of equal width, between their extremes or, for strengths and memberships, between 0 and 1.
    """
    spark = prepare(df.sparkSession)
    numeric, symbolic = [f for f in spec if f.numeric], [f for f in spec if not f.numeric]
    ends = df.agg(*(a for f in numeric for a in (F.min(f.name), F.max(f.name)))).first() if numeric else ()
    low = np.array([float(ends[2 * i] or 0) for i in range(len(numeric))])
    width = np.array([float(ends[2 * i + 1] or 0) for i in range(len(numeric))]) - low
    classes = sorted(r[0] for r in df.select(F.col(label).cast("string")).distinct().collect() if r[0] is not None)
    y = F.array_position(F.array(*map(F.lit, classes)), F.col(label).cast("string")).cast("int") - 1
    rows = raw_columns(df.filter(F.col(label).isNotNull()).withColumn("y", y), scaler, "y")
    n_raw = len(numeric) + len(symbolic)
    shared = spark.sparkContext.broadcast(models)

    def binned(x: np.ndarray, f: Feature, a: float, w: float) -> np.ndarray:
        known = ~np.isnan(x)
        value = np.where(known, x, 0.0)
        code = np.minimum(np.floor((value - a) * bins / w), bins - 1) if f.kind == "continuous" and w else value * (f.kind != "continuous")
        return np.where(known, code, -1).astype(np.int64)

    def count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        sums: dict[tuple[int, int, int], dict[tuple[int, int], int]] = {}

        def add(k: int, f: int, g: int, a: np.ndarray, b: np.ndarray) -> None:
            both = (a >= 0) & (b >= 0)
            if both.any():
                values, times = np.unique(np.stack([a[both], b[both]], axis=1), axis=0, return_counts=True)
                held = sums.setdefault((k, f, g), {})
                for (i, j), n in zip(values.tolist(), times.tolist(), strict=True):
                    held[i, j] = held.get((i, j), 0) + n

        for batch in batches:
            for at in range(0, len(batch), 8192):
                part = batch.slice(at, 8192)
                r, x, s = (np.asarray(part.column(c).flatten(), t).reshape(len(part), n) for c, t, n in (("r", float, len(numeric)), ("x", float, len(numeric)), ("s", np.int64, len(symbolic))))
                raw = [binned(r[:, i], f, low[i], width[i]) for i, f in enumerate(numeric)] + [s[:, i] for i in range(len(symbolic))] + [np.asarray(part.column("y"), np.int64)]
                for f in range(len(raw)):
                    for g in range(f):
                        add(0, f, g, raw[f], raw[g])
                for k, model in shared.value.items():
                    if model is None or not T:
                        continue
                    p = np.round(model.memberships(x, s), DIGITS)
                    own = [p.argmax(axis=1), *(np.minimum(np.floor(c * bins), bins - 1).astype(np.int64) for c in (p.max(axis=1), *(p.T if T >= 2 else ())))]
                    for i, code in enumerate(own):
                        for f in range(len(raw)):
                            add(k, n_raw + 1 + i, f, code, raw[f])
                        for j in range(i):
                            add(k, n_raw + 1 + i, n_raw + 1 + j, code, own[j])
        if sums:
            flat = [(*key, a, b, n) for key, cells in sums.items() for (a, b), n in cells.items()]
            yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*flat, strict=True), (pa.int32(),) * 5 + (pa.int64(),), strict=True)], ["k", "f", "g", "a", "b", "n"])

    cells = rows.mapInArrow(count, "k int, f int, g int, a int, b int, n long").groupBy("k", "f", "g", "a", "b").agg(F.sum("n").alias("n"))
    found: dict[int, dict[tuple[int, int], float]] = {}
    for row in uncertainty(cells, "k", "f", "g").collect():  # columns ** 2 / 2 numbers for each count
        found.setdefault(row["k"], {})[row["f"], row["g"]] = row["su"]
    out = {}
    raw_names = [f.name for f in numeric] + [f.name for f in symbolic]
    for k, model in models.items():
        extra = [] if model is None or not T else ["z", "b", *(f"p_{j + 1}" for j in range(k if T >= 2 else 0))]
        # as in the learners' frames: numeric columns, cluster ones after them, then symbolic columns
        order = [*range(len(numeric)), *range(n_raw + 2, n_raw + 1 + len(extra)), *range(len(numeric), n_raw), *([n_raw + 1] if extra else [])]
        names = [(raw_names[i] if i < n_raw else extra[i - n_raw - 1]) for i in order]
        both = {**found.get(0, {}), **found.get(k, {})}
        su = lambda f, g, both=both: both.get((max(f, g), min(f, g)), 0.0)
        mutual = np.array([[1.0 if f == g else su(f, g) for g in order] for f in order]).reshape(len(order), len(order))
        out[k] = (names, np.array([su(f, n_raw) for f in order]), mutual)
    return out


@dataclass
class CacModel:
    """A trained classifier with all that new rows need: normaliser, centroids, subset."""

    scaler: Scaler
    fcm: Clustering | None
    T: int
    learner: object
    subset: list[str] | None
    classes: list[str]
    k: int
    scores: dict[int, float]
    cost: dict[str, float] = field(default_factory=dict)

    def transform(self, df: DataFrame) -> DataFrame:
        """The frame with z, b (null for T=0) and prediction."""
        spark = prepare(df.sparkSession)
        shared, names, spec = spark.sparkContext.broadcast(self), df.columns, self.scaler.spec
        packed = raw_columns(df, self.scaler, *names)

        def work(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            model = shared.value
            n_num = sum(f.numeric for f in spec)
            for batch in batches:
                for at in range(0, len(batch), 8192):
                    part = batch.slice(at, 8192)
                    arrays = [np.asarray(part.column(c).flatten(), t).reshape(len(part), n) for c, t, n in (("r", float, n_num), ("x", float, n_num), ("s", np.int64, len(spec) - n_num))]
                    frame = design(frame_of(arrays[0], arrays[2], spec), arrays[1], arrays[2], model.fcm, model.T)
                    said = model.learner.predict(frame.only(model.subset) if model.subset is not None else frame)
                    extra = cluster_frame(arrays[1], arrays[2], model.fcm, 1)
                    z = pa.array(extra.cat[:, 0].astype(np.int32)) if extra else pa.nulls(len(part), pa.int32())
                    b = pa.array(extra.num[:, 0]) if extra else pa.nulls(len(part), pa.float64())
                    yield pa.RecordBatch.from_arrays([*(part.column(c) for c in names), z, b, pa.array([model.classes[i] for i in said], pa.string())], [*names, "z", "b", "prediction"])

        schema = ", ".join(f"`{f.name}` {f.dataType.simpleString()}" for f in df.schema.fields)
        return packed.mapInArrow(work, f"{schema}, z int, b double, prediction string")

    def save(self, spark, path: str) -> None:
        """One row: a readable summary and the trained state, written by Spark to any store that it knows."""
        summary = json.dumps({"T": self.T, "k": self.k, "classes": self.classes, "subset": self.subset, "scores": self.scores, "cost": self.cost})
        spark.createDataFrame([(summary, pickle.dumps(self))], "summary string, state binary").coalesce(1).write.mode("overwrite").parquet(path)

    @staticmethod
    def load(spark, path: str) -> "CacModel":
        """Only for paths that one trusts: the state is a pickle."""
        return pickle.loads(spark.read.parquet(path).first()["state"])


def reduce_rows(df: DataFrame, scaler: Scaler, label: str, q: int, most: int, classes: list[str]) -> Reduced:
    """The reduced set of rows; of rows that have a `fold` already, with those folds."""
    dealt = df if "fold" in df.columns else stratified_folds(df, "fine_label", q)
    y = F.array_position(F.array(*map(F.lit, classes)), F.col(label).cast("string")).cast("int") - 1
    rows = raw_columns(bounded(dealt, most).withColumn("__y", y), scaler, "row_id", "__y", "fold").orderBy("row_id").drop("row_id").toArrow()
    n_num, n = sum(f.numeric for f in scaler.spec), len(rows)
    flat = lambda c, t: np.concatenate([np.zeros(0, t), *(np.asarray(a.flatten(), t) for a in rows.column(c).chunks)])
    r, x, s = (flat(c, t).reshape(n, m) for c, t, m in (("r", float, n_num), ("x", float, n_num), ("s", np.int64, len(scaler.spec) - n_num)))
    return Reduced(frame_of(r, s, scaler.spec), x, s, *(rows.column(c).to_numpy().astype(np.int64) for c in ("__y", "fold")), classes)


def fit_cac(
    df: DataFrame, spec: list[Feature], K: list[int], learner: str = "dt", T: int = 1, selector=None, q: int = 10, label: str = "label", alpha: float = 3.0, tol: float = 1e-6, max_iter: int = 300, options: dict | None = None,
    evaluator: str = "cv", normalise: str = "minmax", weighted: bool = True, most: int = MAX_TRAIN, init: str = "hash", scope: str = "paper", measure: str = "accuracy", unknown: str = "both", clusterer: Clusterer | None = None, local: int | None = None, chosen: dict[int, list[str]] | None = None,
) -> CacModel:
    """The best candidate over K. T=0: the plain learner (with selector: on its selected columns). evaluator: cv, holdout (one fold) or validity.

    scope: "paper" or "nested", see above. measure: one of MEASURES. clusterer: anything that fits memberships, in place of fuzzy c-means.
    most: rows of the reduced set of learners that need one. local: rows beyond which the others train by scans; None: as many as TRAVEL numbers hold.
    chosen: the subset of each count (0: of the raw columns) that other fits on the same rows and clusterings have selected; filled here.
    """
    spark = prepare(df.sparkSession)
    df = df.filter(F.col(label).isNotNull())
    options, clock = options or {}, {"begin": time.time()}
    classes = sorted(r[0] for r in df.select(label).distinct().collect())
    if T == 3 and selector is None:
        selector = CfsSelector()
    selector = selector if T in (0, 3) else None
    clusterer = clusterer or FuzzyCMeans(alpha, tol, max_iter, init, unknown)

    def clusterings(rows: DataFrame) -> tuple[Scaler, dict[int, Clustering | None]]:
        scaler = fit_scaler(rows, spec, normalise)
        if not T:
            return scaler, {0: None}
        g = gains(rows, spec, label) if weighted else {f.name: 1.0 for f in spec}
        return scaler, clusterer.fit(scaler.pack(rows, "row_id"), list(K), [g[f.name] for f in spec if f.numeric], [g[f.name] for f in spec if not f.numeric], [len(scaler.levels[f.name]) for f in spec if not f.numeric])

    scaler, models = clusterings(df)
    clock["cluster"] = time.time()
    by_counts = learner == "vote" and selector is None
    total = df.count()
    node = max(most, NODE // (len(spec) + 2 + (max(K, default=0) if T > 1 else 0))) if local is None else local
    if learner in WHOLE:
        most = max(most, TRAVEL // (2 * len(spec) + 2)) if local is None else local
    whole = learner in WHOLE and total > most and options.get("bins") is None  # quantiles are worked out where all rows are
    choosing = selector is not None and hasattr(selector, "choose")
    data = None if by_counts or (whole and (selector is None or choosing)) else reduce_rows(df, scaler, label, q, most, classes)
    subsets: dict[int, list[str]] = {} if chosen is None or selector is None else chosen
    if selector is not None and scope == "paper" and not set(models) <= set(subsets):
        counted = associations(df, spec, scaler, models, T, label, selector.bins) if choosing else {}
        for k, model in models.items():
            if k in counted:
                subsets[k] = selector.choose(*counted[k])
            else:
                subsets[k] = selector.select(design(data.raw, data.x, data.s, model, T), data.y, len(classes))
    clock["select"] = time.time()
    scores: dict[int, float] = {}
    folds = range(q if evaluator == "cv" else 1)
    if len(models) > 1 and evaluator == "validity":
        from fuzzyfeat.operators.validity import validity

        scores = {r["k"]: r["pc"] for r in validity(scaler.pack(df, "row_id"), models).collect()}
    elif len(models) > 1 or T == 0:
        if scope == "nested":
            done, dealt = {}, materialise(stratified_folds(df, "fine_label", q))  # each fold's fit scans it many times
            kept = dealt if by_counts or whole else materialise(bounded(dealt, most))
            for f in folds:
                rest = dealt.filter(F.col("fold") != f).drop("fold")
                own_scaler, own = clusterings(rest)
                jobs = [(k, f) for k in own]
                if by_counts:
                    done |= _vote_jobs(dealt, own_scaler, own, jobs, T, options, q, label, classes, measure)
                elif whole:
                    picked = {k: selector.choose(*c) for k, c in associations(rest, spec, own_scaler, own, T, label, selector.bins).items()} if choosing else {}
                    done |= _whole_jobs(dealt, own_scaler, own, jobs, T, learner, options, picked, q, label, classes, node, measure)
                else:
                    done |= _jobs(spark, reduce_rows(kept, own_scaler, label, q, most, classes), own, jobs, T, learner, options, {}, selector, measure)
            release(dealt, *([] if kept is dealt else [kept]))
        else:
            jobs = [(k, f) for k in models for f in folds]
            if by_counts:
                done = _vote_jobs(df, scaler, models, jobs, T, options, q, label, classes, measure)
            elif whole:
                done = _whole_jobs(df, scaler, models, jobs, T, learner, options, subsets, q, label, classes, node, measure)
            else:
                done = _jobs(spark, data, models, jobs, T, learner, options, subsets, selector, measure)
        for k in models:
            own = [score for (kk, _), (score, n, _) in done.items() if kk == k and n]
            scores[k] = float(np.mean(own)) if own else 0.0
    clock["folds"] = time.time()
    best = min(models, key=lambda k: (-round(scores.get(k, 0.0), 12), k))
    only, last = {best: models[best]}, [(best, -1)]
    if by_counts:
        final = _vote_jobs(df, scaler, only, last, T, options, q, label, classes)
    elif whole:
        final = _whole_jobs(df, scaler, only, last, T, learner, options, {k: subsets[k] for k in only if k in subsets}, q, label, classes, node)
    else:
        final = _jobs(spark, data, only, last, T, learner, options, subsets, selector)
    trained, subset = final[best, -1][2]
    rounds = {k: len(m.trace) for k, m in models.items() if isinstance(m, FcmModel)}
    marks = list(clock.items()) + [("train", time.time())]
    cost = {f"{name}_seconds": round(now - before, 3) for (_, before), (name, now) in zip(marks, marks[1:], strict=False)}
    cost |= {"rounds": max(rounds.values(), default=0), "row_centroids_per_row": sum(k * n for k, n in rounds.items()), "not_converged": sum(isinstance(m, FcmModel) and not m.converged for m in models.values()), "models_fitted": len(folds) * len(models) * (evaluator != "validity") * (len(models) > 1 or T == 0) + 1, "training_rows": total if by_counts or whole else len(data.y)}
    return CacModel(scaler, models[best], T, trained, subset, classes, best, scores, cost)
