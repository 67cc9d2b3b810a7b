"""The experiments: floors for every method, directions that the reference reports, and variants against each other."""

import numpy as np
import pytest
from pyspark.sql import functions as F

from fuzzyfeat import fixtures, workloads
from fuzzyfeat.operators import augmented, fcm, infogain, prepare, sampling
from fuzzyfeat.operators.learners.data import Frame
from fuzzyfeat.operators.learners.svm import KernelSVM
from fuzzyfeat.operators.learners.tree import AdaBoostM1, C45Tree, LevelVote

SF = "/root/testdata/sf0.01"


def frame(x, cat=None):
    x = np.asarray(x, float)
    cat = np.zeros((len(x), 0), np.int64) if cat is None else np.asarray(cat)
    return Frame(x, cat, [f"x{i}" for i in range(x.shape[1])], [f"c{i}" for i in range(cat.shape[1])])


@pytest.fixture(scope="module")
def fitted(spark):
    return workloads.clusterer_of(spark, SF, "traffic", K=(2, 5, 10))


@pytest.fixture(scope="module")
def rates(spark, fitted):
    known = {}

    def of(learner, T, select=False):
        if (learner, T, select) not in known:
            known[learner, T, select] = workloads.average("traffic", learner, T, select, spark, SF, K=(2, 5, 10), q=3, clusterer=fitted)
        return known[learner, T, select]

    return of


@pytest.mark.parametrize(("learner", "T", "select", "floor"), [
    ("boost", 0, False, 0.50), ("bag", 0, False, 0.72), ("nbtree", 0, False, 0.93), ("dt", 0, False, 0.48), ("dt", 0, True, 0.45), ("psvm", 0, False, 0.80), ("psvm", 0, True, 0.45), ("rsvm", 0, False, 0.55), ("rsvm", 0, True, 0.45),
    ("dt", 1, False, 0.75), ("dt", 2, False, 0.70), ("dt", 3, False, 0.45), ("psvm", 1, False, 0.80), ("psvm", 2, False, 0.80), ("psvm", 3, False, 0.45), ("rsvm", 1, False, 0.55), ("rsvm", 2, False, 0.60), ("rsvm", 3, False, 0.45),
])
def test_floors(rates, learner, T, select, floor):
    tpr, fpr = rates(learner, T, select)
    assert tpr >= floor and fpr <= 0.5


def test_cluster_columns_help_where_two_columns_tell_jointly(rates):
    assert rates("dt", 1)[0] > rates("dt", 0)[0] + 0.1
    assert rates("dt", 1)[1] < rates("dt", 0)[1]
    assert rates("psvm", 1)[0] > rates("psvm", 0)[0] - 0.02


def test_full_set_of_counts(spark):
    rows = workloads.k_curve("quality", workloads.K_FULL, spark, SF).collect()
    assert [r["k"] for r in rows] == list(range(2, 51)) and all(0 <= r["score"] <= 1 for r in rows)
    best = max(round(r["score"], 12) for r in rows)
    assert [r["k"] for r in rows if r["chosen"]] == [min(r["k"] for r in rows if round(r["score"], 12) == best)]


def test_scopes_and_measures(spark):
    df = fixtures.load(spark, SF, "quality")
    for scope in ("paper", "nested"):
        model = augmented.fit_cac(df, fixtures.SPECS["quality"], [2, 3], "dt", 3, q=3, scope=scope)
        assert set(model.scores) == {2, 3} and min(model.scores.values()) > 0.9 and model.subset and model.cost["rounds"] > 1
    y, said = np.array([0, 0, 0, 1]), np.array([0, 0, 1, 1])
    assert augmented.MEASURES["accuracy"](y, said) == 0.75 and augmented.MEASURES["balanced"](y, said) == pytest.approx((2 / 3 + 1) / 2)
    assert augmented.MEASURES["rate_gap"](y, said) == pytest.approx(0.75 * (2 / 3 - 0) + 0.25 * (1 - 1 / 3))


HALVES = '''
import numpy as np


class Halves:
    """Two soft halves of the first column."""

    def memberships(self, x, s):
        p = np.clip(np.nan_to_num(x[:, :1]), 0, 1)
        return np.concatenate([p, 1 - p], axis=1)


class Clusterer:
    def fit(self, packed, counts, gains_num, gains_cat, n_levels):
        return {2: Halves()}
'''


def test_any_clusterer_may_take_the_place(spark, tmp_path, monkeypatch):
    (tmp_path / "soft_halves.py").write_text(HALVES)
    spark.sparkContext.addPyFile(str(tmp_path / "soft_halves.py"))
    monkeypatch.syspath_prepend(str(tmp_path))
    from soft_halves import Clusterer

    df = fixtures.load(spark, SF, "quality").filter("label IS NOT NULL")
    data = augmented.reduce_rows(df, prepare.fit_scaler(df, fixtures.SPECS["quality"]), "label", 3, 1000, ["0", "1"])
    models = Clusterer().fit(None, [2], [], [], [])
    design = augmented.design(data.raw, data.x, data.s, models[2], 2)
    model = augmented.fit_cac(df, fixtures.SPECS["quality"], [2], "dt", 2, q=3, clusterer=Clusterer())
    assert model.k == 2 and model.transform(df).filter("prediction = label").count() > 0.9 * df.count()
    assert design.num_names[-3:] == ["b", "p_1", "p_2"] and np.allclose(design.num[:, -2:].sum(axis=1), 1)


def test_seeds_tolerances_and_strategies_agree(spark):
    df = fixtures.load(spark, SF, "quality").filter("label IS NOT NULL")
    spec = fixtures.SPECS["quality"]
    scaler, g = prepare.fit_scaler(df, spec), infogain.gains(df, spec)
    packed = scaler.pack(df, "row_id").cache()
    gn, gc = [g[f.name] for f in spec if f.numeric], [g[f.name] for f in spec if not f.numeric]
    levels = [len(scaler.levels[f.name]) for f in spec if not f.numeric]
    there = fcm.fit_many(packed, [2, 4], gn, gc, levels)
    spread = fcm.fit_many(packed, [2, 4], gn, gc, levels, local_points=0)
    for k in (2, 4):
        assert there[k].converged and len(there[k].trace) == len(spread[k].trace) and np.allclose(there[k].centroids.num, spread[k].centroids.num)
        assert abs(there[k].trace[-2] - there[k].trace[-1]) <= 1e-6 * there[k].trace[-2]
    moved = fcm.fit_many(packed, [4], gn, gc, levels, criterion="centroids")[4]
    assert moved.converged and len(moved.trace) >= len(there[4].trace)
    for init in ("farthest", "parallel"):
        model = fcm.fit_many(packed, [4], gn, gc, levels, init=init)[4]
        assert model.converged and len(np.unique(model.centroids.num.round(6), axis=0)) == 4
    crisp = fcm.fit_many(packed, [3], gn, gc, levels, alpha=1.0)[3]
    assert crisp.converged and all(a >= b - 1e-9 for a, b in zip(crisp.trace, crisp.trace[1:], strict=False))


def rows_with_strata(spark, sizes):
    return spark.createDataFrame([(f"{s}-{i}", s) for s, n in sizes.items() for i in range(n)], "row_id string, fine_label string")


def test_reduced_sets_are_exact(spark):
    small = {f"s{i}": 45 for i in range(150)}
    for sizes, most in (({**small, "big": 13_250}, 5000), (small, 5000), ({**small, None: 900, "big": 4000}, 3000), ({"a": 7, None: 3}, 50)):
        df = rows_with_strata(spark, sizes)
        kept = {r["fine_label"]: r["count"] for r in sampling.bounded(df, most).groupBy("fine_label").count().collect()}
        assert kept == sampling.quotas(sizes, most) and sum(kept.values()) == min(most, sum(sizes.values()))
        assert set(kept) == set(sizes)
    quotas = sampling.quotas({"rare": 20, "big": 100_000, "other": 100_000}, 10_000)
    assert quotas["rare"] == 20 and abs(quotas["big"] - quotas["other"]) <= 1


def test_folds_keep_rows_without_a_stratum(spark):
    df = rows_with_strata(spark, {None: 5, "a": 7})
    sizes = {(r["fine_label"], r["fold"]): r["count"] for r in sampling.stratified_folds(df, q=3).groupBy("fine_label", "fold").count().collect()}
    assert sum(sizes.values()) == 12 and sorted(n for (s, _), n in sizes.items() if s is None) == [1, 2, 2]


@pytest.mark.parametrize("degree", [2, 3])
def test_exact_machine_is_the_explicit_one(degree):
    g = np.random.default_rng(5)
    x = g.random((160, 3))
    y = ((x[:, 0] > 0.5) != (x[:, 1] > 0.5)).astype(int)
    a, b = (KernelSVM("poly", degree, C=10, approx=how).fit(frame(x), y, 2) for how in ("explicit", "exact"))
    probe = frame(g.random((400, 3)))
    assert (a.predict(probe) == b.predict(probe)).mean() > 0.995
    assert KernelSVM("poly", 2).fit(frame(x), y, 2).approx == "explicit" and KernelSVM("rbf").fit(frame(x), y, 2).approx == "exact"
    assert KernelSVM("rbf").fit(frame(g.random((1600, 2))), g.integers(0, 2, 1600), 2).approximate


def test_tree_takes_exact_thresholds():
    x = np.arange(400.0)[:, None] ** 2
    y = (np.arange(400) >= 137).astype(int)
    tree = C45Tree().fit(frame(x), y, 2)
    assert tree.root.threshold == pytest.approx((136**2 + 137**2) / 2) and (tree.predict(frame(x)) == y).all()


def test_votes_of_boosting():
    c = np.array([0] * 40 + [1] * 60)
    y = np.array([0] * 32 + [1] * 8 + [1] * 48 + [0] * 12)
    model = AdaBoostM1(2, LevelVote).fit(frame(np.zeros((100, 0)), c[:, None]), y, 2)
    assert model.errors[0] == pytest.approx(0.2) and model.votes[0] == pytest.approx(np.log(4))
    assert model.errors[1] == pytest.approx(0.5)  # right and wrong rows weigh the same in the second round


def test_lifted_spaces(spark):
    for kind, floor in (("pca", 0.8), ("poly", 0.5), ("rbf", 0.5)):
        from fuzzyfeat.operators import metrics

        got = metrics.average_rates(workloads.lifted("traffic", "dt", kind, spark, SF)).first()
        assert got["avg_tpr"] > floor
    columns, apply = __import__("fuzzyfeat.operators.lift", fromlist=["lift"]).lift(fixtures.load(spark, SF, "traffic"), fixtures.SPECS["traffic"], "poly")
    row = apply(fixtures.load(spark, SF, "traffic").limit(1)).select(F.array(*(f.name for f in columns)).alias("a")).first()["a"]
    assert len(row) == len(columns) and any(v == pytest.approx(row[0] * row[0]) for v in row[1:])


def test_validity_as_expressions_and_in_the_kernel(spark, monkeypatch):
    from fuzzyfeat.operators import validity

    df = fixtures.load(spark, SF, "quality").filter("label IS NOT NULL")
    spec = fixtures.SPECS["quality"]
    scaler = prepare.fit_scaler(df, spec)
    packed = scaler.pack(df, "row_id").cache()
    models = fcm.fit_many(packed, [2, 3], [1.0] * 5, [0.5, 0.5], [len(scaler.levels[f.name]) for f in spec if not f.numeric], max_iter=3)
    inline = {r["k"]: (r["pc"], r["pe"], r["xb"]) for r in validity.validity(packed, models).collect()}
    monkeypatch.setattr(validity, "INLINE_TERMS", 0)
    kernel = {r["k"]: (r["pc"], r["pe"], r["xb"]) for r in validity.validity(packed, models).collect()}
    assert set(inline) == {2, 3} and all(np.allclose(inline[k], kernel[k]) for k in inline)
    assert validity.best_k(validity.validity(packed, models)) in (2, 3)
