"""The experiments on the given tables: every method on the same train and test rows, reported by class and on average."""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from fuzzyfeat import fixtures
from fuzzyfeat.operators import metrics, sampling
from fuzzyfeat.operators.augmented import MAX_TRAIN, MEASURES, CacModel, associations, fit_cac, reduce_rows
from fuzzyfeat.operators.fcm import Fitted, FuzzyCMeans
from fuzzyfeat.operators.infogain import gains
from fuzzyfeat.operators.learners.data import Frame
from fuzzyfeat.operators.learners.tree import AdaBoostM1, C45Tree, LevelVote
from fuzzyfeat.operators.lift import lift
from fuzzyfeat.operators.prepare import fit_scaler
from fuzzyfeat.operators.selection import CfsSelector, FilterSelector, WrapperSelector, association, exhaustive, merit
from fuzzyfeat.session import materialise
from fuzzyfeat.sources.tables import stream_table
from fuzzyfeat.streaming import ops

#: The reference's settings: all counts from 2 to 50, ten folds, and rounds until the objective stands still.
K_FULL, FOLDS, ROUNDS = tuple(range(2, 51)), 10, 300
#: The counts of the queries that train many classifiers; `k_curve_full_*` and `cac_dt_t1_full_*` run over K_FULL.
K = (2, 3, 4, 5, 6, 8, 10)


def split(spark: SparkSession, sf_dir: str, name: str) -> tuple[DataFrame, DataFrame]:
    """Training and test rows of a fixture, worked out once: a fit scans them many times."""
    df = materialise(sampling.train_test(fixtures.load(spark, sf_dir, name).filter("label IS NOT NULL")))
    return tuple(df.filter(F.col("part") == p).drop("part") for p in ("train", "test"))


def train(spark: SparkSession, sf_dir: str, name: str, learner: str, T: int, select: bool = False, K: tuple[int, ...] = K, q: int = FOLDS, max_iter: int = ROUNDS, parts: tuple[DataFrame, DataFrame] | None = None, **options) -> tuple[CacModel, DataFrame]:
    """A classifier and its test rows. parts: the split, if it serves many classifiers."""
    rows, test = parts or split(spark, sf_dir, name)
    return fit_cac(rows, fixtures.SPECS[name], list(K), learner, T, CfsSelector() if select or T == 3 else None, q=q, max_iter=max_iter, **options), test


def per_class(name: str, learner: str, T: int, select: bool, spark: SparkSession, sf_dir: str, **options) -> DataFrame:
    """(label, tpr, fpr, n) on the test rows."""
    model, test = train(spark, sf_dir, name, learner, T, select, **options)
    return metrics.rates(metrics.confusion(model.transform(test)))


def average(name: str, learner: str, T: int, select: bool, spark: SparkSession, sf_dir: str, **options) -> tuple[float, float]:
    row = metrics.average_rates(per_class(name, learner, T, select, spark, sf_dir, **options)).first()
    return row["avg_tpr"], row["avg_fpr"]


def clusterer_of(spark: SparkSession, sf_dir: str, name: str, K: tuple[int, ...] = K, parts: tuple[DataFrame, DataFrame] | None = None) -> Fitted:
    """The clusterings of a fixture's training rows, fitted once for many classifiers on the same rows."""
    rows, _ = parts or split(spark, sf_dir, name)
    spec = fixtures.SPECS[name]
    scaler, g = fit_scaler(rows, spec), gains(rows, spec)
    return Fitted(FuzzyCMeans(max_iter=ROUNDS).fit(scaler.pack(rows, "row_id"), list(K), [g[f.name] for f in spec if f.numeric], [g[f.name] for f in spec if not f.numeric], [len(scaler.levels[f.name]) for f in spec if not f.numeric]))


def sweep(name: str, learner: str, parameter: str, values: list, spark: SparkSession, sf_dir: str) -> DataFrame:
    """The plain learner at each setting, and the cluster-augmented one at its own, with the mean of each family."""
    parts = split(spark, sf_dir, name)
    rows = [(learner, str(v), *average(name, learner, 0, False, spark, sf_dir, options={parameter: v}, parts=parts)) for v in values]
    fitted = clusterer_of(spark, sf_dir, name, parts=parts)
    rows += [(f"cac_{learner}", f"T={t}", *average(name, learner, t, False, spark, sf_dir, clusterer=fitted, parts=parts)) for t in (1, 2, 3)]
    each = spark.createDataFrame(rows, "family string, setting string, avg_tpr double, avg_fpr double")
    return each.unionByName(metrics.mean_over_settings(each, "family").withColumn("setting", F.lit("mean")))


def average_report(name: str, spark: SparkSession, sf_dir: str) -> DataFrame:
    """(method, avg_tpr, avg_fpr) of nine plain learners and nine cluster-augmented ones on the same rows."""
    plain = [("boost", False), ("bag", False), ("nbtree", False), *((x, fs) for x in ("dt", "psvm", "rsvm") for fs in (False, True))]
    shared = {"parts": split(spark, sf_dir, name), "chosen": {}}
    rows = [(x + "_fs" * fs, *average(name, x, 0, fs, spark, sf_dir, **shared)) for x, fs in plain]
    shared["clusterer"] = clusterer_of(spark, sf_dir, name, parts=shared["parts"])
    rows += [(f"cac_{x}_t{t}", *average(name, x, t, False, spark, sf_dir, **shared)) for x in ("dt", "psvm", "rsvm") for t in (1, 2, 3)]
    return spark.createDataFrame(rows, "method string, avg_tpr double, avg_fpr double")


def selection_ablation(name: str, spark: SparkSession, sf_dir: str) -> DataFrame:
    """What selection does on raw columns and on augmented ones, for each inducer."""
    parts, rows = split(spark, sf_dir, name), []
    shared = {"parts": parts, "chosen": {}, "clusterer": clusterer_of(spark, sf_dir, name, parts=parts)}
    for learner in ("dt", "psvm", "rsvm"):
        got = [average(name, learner, t, fs, spark, sf_dir, **shared)[0] for t, fs in ((0, False), (0, True), (2, False), (3, False))]
        rows.append((learner, *got, got[1] - got[0], got[3] - got[2]))
    return spark.createDataFrame(rows, "learner string, raw double, raw_selected double, augmented double, augmented_selected double, gain_raw double, gain_augmented double")


def scopes(name: str, spark: SparkSession, sf_dir: str, K: tuple[int, ...] = (2, 3, 5), q: int = 5) -> DataFrame:
    """(scope, k, score): candidates scored with clusters of all training rows, and with clusters of each fold's own."""
    rows = []
    for scope in ("paper", "nested"):
        model, _ = train(spark, sf_dir, name, "dt", 1, K=K, q=q, scope=scope)
        rows += [(scope, k, float(v)) for k, v in sorted(model.scores.items())]
    return spark.createDataFrame(rows, "scope string, k int, score double")


def measures(name: str, spark: SparkSession, sf_dir: str) -> DataFrame:
    """(measure, k, avg_tpr, avg_fpr): the count that each measure of performance chooses, and how it does on the test rows."""
    fitted, rows = clusterer_of(spark, sf_dir, name), []
    for measure in MEASURES:
        model, test = train(spark, sf_dir, name, "dt", 1, measure=measure, clusterer=fitted)
        got = metrics.average_rates(metrics.rates(metrics.confusion(model.transform(test)))).first()
        rows.append((measure, model.k, got["avg_tpr"], got["avg_fpr"]))
    return spark.createDataFrame(rows, "measure string, k int, avg_tpr double, avg_fpr double")


def lifted(name: str, learner: str, kind: str, spark: SparkSession, sf_dir: str) -> DataFrame:
    """(label, tpr, fpr, n) of a plain learner on a lifted space."""
    rows, test = split(spark, sf_dir, name)
    columns, apply = lift(rows, fixtures.SPECS[name], kind)
    model = fit_cac(apply(rows), columns, [], learner, 0, q=FOLDS)
    return metrics.rates(metrics.confusion(model.transform(apply(test))))


def crisp_contrast(name: str, spark: SparkSession, sf_dir: str) -> DataFrame:
    """(clusters, avg_tpr, avg_fpr) of the tree with features of fuzzy clusters, and of crisp ones (z alone tells, b is 1)."""
    rows = [(kind, *average(name, "dt", 1, False, spark, sf_dir, clusterer=FuzzyCMeans(alpha=alpha, max_iter=ROUNDS))) for kind, alpha in (("fuzzy", 3.0), ("crisp", 1.0))]
    return spark.createDataFrame(rows, "clusters string, avg_tpr double, avg_fpr double")


def seeding(name: str, spark: SparkSession, sf_dir: str, k: int = 5) -> DataFrame:
    """(init, criterion, rounds, objective): where each way of seeding and of stopping ends."""
    rows, _ = split(spark, sf_dir, name)
    spec = fixtures.SPECS[name]
    scaler, g = fit_scaler(rows, spec), gains(rows, spec)
    out = []
    for init in ("hash", "farthest", "parallel"):
        for criterion in ("objective", "centroids"):
            model = FuzzyCMeans(init=init, criterion=criterion).fit(scaler.pack(rows, "row_id"), [k], [g[f.name] for f in spec if f.numeric], [g[f.name] for f in spec if not f.numeric], [len(scaler.levels[f.name]) for f in spec if not f.numeric])[k]
            out.append((init, criterion, len(model.trace), model.trace[-1], model.converged))
    return spark.createDataFrame(out, "init string, criterion string, rounds int, objective double, converged boolean")


def costs(name: str, spark: SparkSession, sf_dir: str) -> DataFrame:
    """(counter, value): what one run of the method over K costs."""
    model, _ = train(spark, sf_dir, name, "dt", 1)
    return spark.createDataFrame([(k, float(v)) for k, v in sorted(model.cost.items())], "counter string, value double")


def k_curve(name: str, K: tuple[int, ...], spark: SparkSession, sf_dir: str, **options) -> DataFrame:
    """Cross-validated accuracy of each candidate, and which one wins."""
    model, _ = train(spark, sf_dir, name, "dt", 1, K=tuple(K), **options)
    return spark.createDataFrame([(k, float(s), k == model.k) for k, s in sorted(model.scores.items())], "k int, score double, chosen boolean")


def vote_curve(name: str, spark: SparkSession, sf_dir: str) -> DataFrame:
    """The same over all labelled rows with the class vote of each cluster as the inducer, three folds and two rounds of clustering: few enough steps for SQL to follow."""
    df = fixtures.load(spark, sf_dir, name)
    model = fit_cac(df, fixtures.SPECS[name], [2, 3, 5], "vote", 1, q=3, tol=0.0, max_iter=2, options={"column": "z"})
    return spark.createDataFrame([(k, round(float(s), 6), k == model.k) for k, s in sorted(model.scores.items())], "k int, score double, chosen boolean")


def vote_boosting(name: str, spark: SparkSession, sf_dir: str, rounds: int = 3) -> DataFrame:
    """(round, column, error, vote) of boosting over stumps of symbolic columns, on all labelled rows: rows of equal levels and class keep equal weights, so each such group is one row that counts as often as it occurs."""
    df = fixtures.load(spark, sf_dir, name).filter("label IS NOT NULL")
    spec = [f for f in fixtures.SPECS[name] if not f.numeric]
    groups = fit_scaler(df, spec).pack(df, "label").groupBy("s", "label").count().orderBy("s", "label").collect()
    classes = sorted({r["label"] for r in groups})
    frame = Frame(np.zeros((len(groups), 0)), np.array([r["s"] for r in groups], np.int64).reshape(len(groups), len(spec)), [], [f.name for f in spec])
    model = AdaBoostM1(rounds, LevelVote).fit(frame, np.array([classes.index(r["label"]) for r in groups], np.int64), len(classes), np.array([r["count"] for r in groups], float))
    return spark.createDataFrame([(i + 1, m.chosen, round(e, 6), round(v, 6)) for i, (m, e, v) in enumerate(zip(model.members, model.errors, model.votes, strict=False))], "round int, column string, error double, vote double")


def validity_choice(name: str, K: list[int], spark: SparkSession, sf_dir: str) -> DataFrame:
    """The usual practice: the count that the partition coefficient prefers."""
    model, test = train(spark, sf_dir, name, "dt", 1, K=tuple(K), evaluator="validity")
    return metrics.average_rates(metrics.rates(metrics.confusion(model.transform(test)))).withColumn("k", F.lit(model.k))


def xor_case(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Greedy trees where only two columns together tell: alone, and with clusters of 10 and 20."""
    rows = [("dt", *average("xor", "dt", 0, False, spark, sf_dir)), ("cac_dt", *average("xor", "dt", 1, False, spark, sf_dir, K=(10, 20)))]
    return spark.createDataFrame(rows, "method string, avg_tpr double, avg_fpr double")


def score_unlabelled(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The operation phase on the documents that have no label."""
    model = fit_cac(fixtures.load(spark, sf_dir, "quality"), fixtures.SPECS["quality"], list(K), "dt", 1, q=FOLDS)
    return model.transform(fixtures.load(spark, sf_dir, "quality").filter("label IS NULL")).select("row_id", "z", F.round("b", 5).alias("b"), "prediction")


def stream_score(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Events scored as a stream by a model trained on the table: the same answers as in batch."""
    rows, _ = split(spark, sf_dir, "traffic")
    model = fit_cac(rows, fixtures.SPECS["traffic"], list(K), "dt", 1, q=FOLDS)
    stream = stream_table(spark, sf_dir, "events")
    shaped = stream.select(F.col("event_id").alias("row_id"), "value", F.get_json_object("props", "$.k").cast("double").alias("k"), F.hour("ts").cast("double").alias("hour"), "event_type")
    return ops.run_once(ops.score(shaped, model).select("row_id", "z", "prediction"))


def reduced_design(spark: SparkSession, sf_dir: str, name: str):
    """The raw columns of the labelled rows as arrays, for selectors and local learners."""
    df = fixtures.load(spark, sf_dir, name).filter("label IS NOT NULL")
    scaler = fit_scaler(df, fixtures.SPECS[name])
    classes = sorted(r[0] for r in df.select("label").distinct().collect())
    return reduce_rows(df, scaler, "label", FOLDS, MAX_TRAIN, classes)


def subsets(name: str, spark: SparkSession, sf_dir: str) -> DataFrame:
    """(technique, subset, merit) of each selection technique on the raw columns."""
    data = reduced_design(spark, sf_dir, name)
    names, to_class, mutual = association(data.raw, data.y)
    techniques = {"genetic": CfsSelector(), "exhaustive": CfsSelector("exhaustive"), "filter": FilterSelector(3), "wrapper": WrapperSelector(C45Tree)}
    rows = []
    for technique, selector in techniques.items():
        chosen = selector.select(data.raw, data.y, len(data.classes))
        rows.append((technique, "+".join(sorted(chosen)), round(merit([names.index(c) for c in chosen], to_class, mutual), 6)))
    return spark.createDataFrame(rows, "technique string, subset string, merit double")


def boosting_rounds(name: str, spark: SparkSession, sf_dir: str) -> DataFrame:
    """(round, error, vote) of the boosted trees."""
    data = reduced_design(spark, sf_dir, name)
    model = AdaBoostM1(10).fit(data.raw, data.y, len(data.classes))
    return spark.createDataFrame([(i + 1, float(e), float(v)) for i, (e, v) in enumerate(zip(model.errors, model.votes, strict=False))], "round int, error double, vote double")


def best_subset(name: str, spark: SparkSession, sf_dir: str, model=None, scaler=None) -> DataFrame:
    """(subset, merit): the best of all subsets of the raw columns, or of these and the cluster columns of a model, by counts over all labelled rows."""
    df = fixtures.load(spark, sf_dir, name).filter("label IS NOT NULL")
    k = model.centroids.k if model else 0
    names, to_class, mutual = associations(df, fixtures.SPECS[name], scaler or fit_scaler(df, fixtures.SPECS[name]), {k: model}, 3 if model else 0, "label")[k]
    best, value = exhaustive(to_class, mutual)
    return spark.createDataFrame([("+".join(sorted(names[i] for i in best)), round(value, 6))], "subset string, merit double")


def border_rows(name: str, spark: SparkSession, sf_dir: str) -> DataFrame:
    """Accuracy of the degree-2 machine with and without cluster features, on the rows of weakest membership and on the others."""
    with_model, test = train(spark, sf_dir, name, "psvm", 1)
    plain, _ = train(spark, sf_dir, name, "psvm", 0)
    scored = with_model.transform(test).select("row_id", "label", "b", F.col("prediction").alias("augmented")).join(plain.transform(test).select("row_id", F.col("prediction").alias("plain")), "row_id")
    cut = scored.approxQuantile("b", [0.25], 0.001)[0]
    rows = scored.withColumn("zone", F.when(F.col("b") <= cut, "border").otherwise("inside"))
    return rows.groupBy("zone").agg(F.count("*").alias("n"), *(F.avg((F.col(c) == F.col("label")).cast("double")).alias(c) for c in ("plain", "augmented")))
