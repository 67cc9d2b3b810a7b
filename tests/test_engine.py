"""The Spark side: equal results of equal formulations, invariants, and rows against the SQL oracles at the smallest size."""

import duckdb
import numpy as np
import pandas as pd
import pytest

from fuzzyfeat import fixtures, queries
from fuzzyfeat.operators import augmented, features, metrics, sampling
from fuzzyfeat.operators.fcm import fit_many
from fuzzyfeat.operators.prepare import fit_scaler

SF = "/root/testdata/sf0.001"


@pytest.fixture(scope="module")
def traffic(spark):
    return fixtures.load(spark, SF, "traffic").filter("label IS NOT NULL").cache()


@pytest.fixture(scope="module")
def packed(traffic):
    scaler = fit_scaler(traffic, fixtures.SPECS["traffic"])
    return scaler, scaler.pack(traffic, "row_id").cache()


def fit(packed, counts, **options):
    scaler, rows = packed
    return fit_many(rows, counts, [1.0, 1.0, 1.0], [0.5], [len(scaler.levels["event_type"])], tol=0.0, **options)


def test_objective_never_rises_and_counts_share_scans(packed):
    both = fit(packed, [2, 4], max_iter=6)
    alone = fit(packed, [4], max_iter=6, compress=False)[4]
    assert all(a >= b - 1e-9 for m in both.values() for a, b in zip(m.trace, m.trace[1:], strict=False))
    assert np.allclose(both[4].centroids.num, alone.centroids.num) and np.allclose(both[4].trace, alone.trace)


def test_expression_and_kernel_agree(traffic, packed, monkeypatch):
    model = fit(packed, [3], max_iter=2)[3]
    inline = features.with_memberships(traffic, packed[0], model).select("row_id", "p").orderBy("row_id").collect()
    monkeypatch.setattr(features, "INLINE_TERMS", 0)
    kernel = features.with_memberships(traffic, packed[0], model).select("row_id", "p").orderBy("row_id").collect()
    assert np.allclose([r["p"] for r in inline], [r["p"] for r in kernel])


def test_folds_are_even_and_split_is_disjoint(traffic):
    folds = sampling.stratified_folds(traffic, q=5)
    sizes = {}
    for r in folds.groupBy("fine_label", "fold").count().collect():
        sizes.setdefault(r["fine_label"], []).append(r["count"])
    assert folds.count() == traffic.count()
    assert all(max(v) - (min(v) if len(v) == 5 else 0) <= 1 for v in sizes.values())


def test_weighted_tpr_is_accuracy(traffic):
    from pyspark.sql import functions as F

    counts = metrics.confusion(traffic.withColumn("prediction", F.expr(queries.RULE)))
    assert metrics.average_rates(metrics.rates(counts)).first()["avg_tpr"] == pytest.approx(metrics.accuracy(counts).first()["accuracy"])


def test_model_survives_storage(spark, traffic, tmp_path):
    model = augmented.fit_cac(traffic, fixtures.SPECS["traffic"], [2, 3], "dt", 1, q=3, max_iter=4)
    model.save(spark, str(tmp_path / "model"))
    again = augmented.CacModel.load(spark, str(tmp_path / "model"))
    a, b = (m.transform(traffic).select("row_id", "z", "prediction").orderBy("row_id").collect() for m in (model, again))
    assert a == b and model.k in model.scores and len(a) == traffic.count()


def rows_of(frame):
    names = sorted(frame.columns)
    clean = lambda x: None if pd.isna(x) else round(float(x), 4) if isinstance(x, float | int | np.number) else str(x)
    return sorted(tuple(str(clean(v)) for v in r) for r in frame[names].itertuples(index=False, name=None))


@pytest.mark.parametrize("name", ["info_gain_traffic", "cfs_merit_quality", "mixed_distance_quality", "fcm_multi_k_traffic", "fcm_objective_trace_traffic", "cluster_features_t2_quality", "validity_by_k_quality", "stratified_folds_traffic", "class_distribution_traffic", "rates_traffic", "traffic_counters", "asof_latest_error", "rates_cube_orders", "stream_session", "udtf_memberships", "crisp_centroids_3iter_quality", "mixed_distance_unknown_either", "cfs_best_exhaustive_quality", "t3_best_subset_quality", "vote_k_curve_quality", "vote_boosting_quality", "unlabelled_features_quality", "stream_late", "stream_rolling_rates", "stream_drift", "stream_user_state", "read_formats"])
def test_oracle(spark, name):
    con = duckdb.connect()
    for t in ("events", "documents", "labels", "orders", "customer", "nation", "region", "lineitem", "part", "supplier", "conversations"):
        con.execute(f"CREATE VIEW {t} AS SELECT * FROM read_parquet('{SF}/{t}.parquet')")
    ours, theirs = queries.Q[name](spark, SF).toPandas(), con.execute(queries.SQL[name]).df()
    assert sorted(ours.columns) == sorted(theirs.columns)
    assert rows_of(ours) == rows_of(theirs)


@pytest.mark.parametrize("name", ["vote_boosting_quality", "vote_k_curve_quality", "vote_k_curve_traffic"])
def test_votes_count_all_rows_of_tables_beyond_the_reduced_set(spark, monkeypatch, name):
    monkeypatch.setattr(augmented, "bounded", lambda df, most: df.filter("row_id % 5 = 0"))
    test_oracle(spark, name)


@pytest.mark.parametrize("scope, column", [("paper", None), ("nested", "z")])
def test_votes_from_counts_are_those_of_the_rows(spark, traffic, monkeypatch, scope, column):
    settings = dict(q=3, max_iter=3, scope=scope, measure="rate_gap", options={"column": column})
    counted = augmented.fit_cac(traffic, fixtures.SPECS["traffic"], [2, 3], "vote", 1, **settings)
    monkeypatch.setitem(augmented.LEARNERS, "rows", augmented.LEARNERS["vote"])
    plain = augmented.fit_cac(traffic, fixtures.SPECS["traffic"], [2, 3], "rows", 1, **settings)
    assert counted.k == plain.k and counted.scores == pytest.approx(plain.scores) and counted.learner.said.tolist() == plain.learner.said.tolist()
    assert counted.learner.chosen == plain.learner.chosen and counted.cost["training_rows"] == plain.cost["training_rows"]


def test_sql_functions_name_their_argument_once(spark):
    from fuzzyfeat.functions import udx

    udx.register(spark)
    rows = spark.createDataFrame([([4.0, 1.0, 9.0],), ([0.0, 2.0, 0.0],), (None,)], "d array<double>")
    got = rows.selectExpr("fuzzy_membership(transform(d, x -> x + 0), 3D) AS p").selectExpr("p", "cluster_id(p) AS z", "cluster_strength(p) AS b")
    assert [(r["p"] and [round(x, 6) for x in r["p"]], r["z"], r["b"]) for r in got.collect()] == [([0.272727, 0.545455, 0.181818], 1, 0.545455), ([0.5, 0.0, 0.5], 0, 0.5), (None, None, None)]
    plan = queries.Q["sqlfunc_membership"](spark, SF)._jdf.queryExecution().optimizedPlan().toString()
    assert plan.count("regexp_replace(") <= 1 and plan.count("split(") <= 4  # measures of a text are worked out once a row


def test_nested_scope_deals_the_rows_once(spark, traffic, monkeypatch):
    calls, dealt = [], augmented.stratified_folds
    monkeypatch.setattr(augmented, "stratified_folds", lambda *a: calls.append(a) or dealt(*a))
    model = augmented.fit_cac(traffic, fixtures.SPECS["traffic"], [2, 3], "dt", 1, q=3, max_iter=2, scope="nested")
    assert len(calls) == 2 and set(model.scores) == {2, 3}  # for the winner's training rows, and for all folds


def test_distances_stay_in_the_jvm(packed):
    from fuzzyfeat.operators.fcm import distance_column

    model = fit(packed, [2], max_iter=1)[2]
    plan = packed[1].select(distance_column(model).alias("d"))._jdf.queryExecution().executedPlan().toString()
    assert "Python" not in plan and "Cartesian" not in plan


def same_tree(a, b):
    assert (a.feature, sorted(a.children)) == (b.feature, sorted(b.children)) and np.allclose(a.counts, b.counts)
    assert not a.children or a.threshold == pytest.approx(b.threshold, abs=1e-12)
    for c in a.children:
        same_tree(a.children[c], b.children[c])


@pytest.mark.parametrize("name, T, scope", [("traffic", 1, "paper"), ("unknowns", 2, "paper"), ("traffic", 3, "nested")])
def test_trees_beyond_the_reduced_set_are_those_of_all_rows(spark, monkeypatch, name, T, scope):
    from fuzzyfeat.operators import whole

    df, settings = fixtures.load(spark, SF, name).filter("label IS NOT NULL").cache(), dict(q=2, max_iter=2, scope=scope)
    plain = augmented.fit_cac(df, fixtures.SPECS[name], [2, 3], "dt", T, **settings)
    monkeypatch.setattr(whole, "CELLS", 500)  # a feature's values lie in several ranges
    spread = augmented.fit_cac(df, fixtures.SPECS[name], [2, 3], "dt", T, most=250, local=250, **settings)
    assert spread.cost["training_rows"] == plain.cost["training_rows"] == df.count() > 250
    if scope == "paper":
        assert spread.scores == pytest.approx(plain.scores) and spread.k == plain.k and spread.subset == plain.subset
        same_tree(spread.learner.root, plain.learner.root)
        assert plain.learner.root.leaves() > 4


@pytest.mark.parametrize("learner, options", [("psvm", {}), ("psvm", {"multiclass": "ovr"}), ("rsvm", {"features": 40}), ("rsvm", {"approx": "rff", "features": 40})])
def test_kernel_machines_beyond_the_reduced_set_are_those_of_all_rows(spark, learner, options):
    from fuzzyfeat.operators.learners.svm import newton

    df, spec = fixtures.load(spark, SF, "unknowns").filter("label IS NOT NULL").cache(), fixtures.SPECS["unknowns"]
    spread = augmented.fit_cac(df, spec, [2, 3], learner, 1, q=2, max_iter=2, options=options, most=150, local=150)
    assert spread.cost["training_rows"] == df.count() > 150 and spread.learner.approximate == (learner == "rsvm")
    if spread.learner.approx != "nystrom":  # its landmarks are chosen in another way
        plain = augmented.fit_cac(df, spec, [2, 3], learner, 1, q=2, max_iter=2, options=options)
        assert spread.scores == pytest.approx(plain.scores) and spread.k == plain.k
        assert [m[:2] for m in spread.learner.models] == [m[:2] for m in plain.learner.models]
        assert all(np.allclose(a[2], b[2], atol=1e-5) for a, b in zip(spread.learner.models, plain.learner.models, strict=True))
        return
    data = augmented.reduce_rows(df, spread.scaler, "label", 2, 10**6, spread.classes)
    z = spread.learner.mapped(augmented.design(data.raw, data.x, data.s, spread.fcm, 1))
    for a, b, w in spread.learner.models:
        own = (data.y == a) | (data.y == b)
        assert np.allclose(w, newton(z[own], np.where(data.y[own] == a, 1.0, -1.0), 1.0), atol=1e-5)
    assert 5 < len(spread.learner.landmarks) <= 40 and min(spread.scores.values()) > 0.5


def test_subsets_are_selected_once_for_many_learners(spark, traffic, monkeypatch):
    calls, counted = [], augmented.associations
    monkeypatch.setattr(augmented, "associations", lambda *a: calls.append(a) or counted(*a))
    chosen, fits = {}, []
    for learner in ("dt", "psvm"):
        fits.append(augmented.fit_cac(traffic, fixtures.SPECS["traffic"], [2, 3], learner, 3, q=2, max_iter=2, chosen=chosen))
    alone = augmented.fit_cac(traffic, fixtures.SPECS["traffic"], [2, 3], "psvm", 3, q=2, max_iter=2)
    assert len(calls) == 2 and set(chosen) == {2, 3} and fits[1].subset == chosen[fits[1].k] == alone.subset and fits[1].scores == pytest.approx(alone.scores)
