"""Queries over the experiment tables, and DuckDB SQL with the same rows for those that SQL can express."""

from __future__ import annotations

from collections.abc import Callable
from functools import partial
from uuid import uuid4

import numpy as np
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from fuzzyfeat import fixtures, workloads
from fuzzyfeat.functions import udx
from fuzzyfeat.operators import features, infogain, metrics, sampling, validity
from fuzzyfeat.operators.fcm import Centroids, FcmModel, distance_column, fit_many, membership_column, seeds
from fuzzyfeat.operators.augmented import associations
from fuzzyfeat.operators.prepare import fit_scaler
from fuzzyfeat.operators.selection import CfsSelector
from fuzzyfeat.plans.spec import Feature
from fuzzyfeat.session import materialise, remove, shared_folder
from fuzzyfeat.sources.tables import load, read_any, stream_table, write_any
from fuzzyfeat.streaming import ops

ALPHA, SEEDED = 3.0, 3
Q: dict[str, Callable[[SparkSession, str], DataFrame]] = {}
SQL: dict[str, str] = {}


def query(name: str, sql: str | None = None):
    def keep(f):
        Q[name] = f
        if sql:
            SQL[name] = sql
        return f

    return keep


def labelled(spark, sf_dir, name):
    return fixtures.load(spark, sf_dir, name).filter("label IS NOT NULL")


def fixture_cte(name: str) -> str:
    return f"f AS (SELECT * FROM ({fixtures.duckdb_sql(name)}) q WHERE label IS NOT NULL)"


# --- normalisation -------------------------------------------------------------------------------------------------------
def _scaled(name: str, method: str, columns: list[str]):
    def run(spark, sf_dir):
        df = labelled(spark, sf_dir, name)
        scaler = fit_scaler(df, [f for f in fixtures.SPECS[name] if f.name in columns], method)
        return df.select("row_id", *(F.round(c, 6).alias(n) for c, n in zip(scaler.columns(), columns, strict=True)))

    return run


query("minmax_scale_traffic", f"WITH {fixture_cte('traffic')} SELECT row_id, round((value - min(value) OVER ()) / (max(value) OVER () - min(value) OVER ()), 6) AS value, round((k - min(k) OVER ()) / (max(k) OVER () - min(k) OVER ()), 6) AS k, round(hour / 23, 6) AS hour FROM f")(_scaled("traffic", "minmax", ["value", "k", "hour"]))
_TEXT = ["n_chars", "n_words", "n_lines", "letter_ratio", "uniq_ratio"]
query("zscore_scale_quality", f"WITH {fixture_cte('quality')} SELECT row_id, {', '.join(f'round(({c} - avg({c}) OVER ()) / stddev_pop({c}) OVER (), 6) AS {c}' for c in _TEXT)} FROM f")(_scaled("quality", "zscore", _TEXT))


# --- information gain ----------------------------------------------------------------------------------------------------
def gain_ctes(name: str, bins: int = 10) -> str:
    """CTEs up to gain_t (feature, gain, gain_ratio, sym_uncert) over f."""
    arms = []
    for x in fixtures.SPECS[name]:
        code = f"CASE WHEN {x.name} IS NULL THEN NULL ELSE cast(cast(least(floor(({x.name} - lo) * {bins} / (hi - lo)), {bins - 1}) AS bigint) AS varchar) END" if x.kind == "continuous" else f"cast({x.name} AS varchar)"
        source = f"f, (SELECT min({x.name}) AS lo, max({x.name}) AS hi FROM f) r" if x.kind == "continuous" else "f"
        arms.append(f"SELECT '{x.name}' AS feature, {code} AS bin, label FROM {source}")
    return f"""b AS ({' UNION ALL '.join(arms)}), c AS (SELECT feature, bin, label, count(*) AS n FROM b GROUP BY ALL),
      known AS (SELECT *, sum(n) OVER (PARTITION BY feature) AS t, sum(n) OVER (PARTITION BY feature, bin) AS m FROM c WHERE bin IS NOT NULL), everything AS (SELECT feature, sum(n) AS a FROM c GROUP BY feature),
      hy AS (SELECT feature, sum(-n / t * log2(n / t)) AS h FROM (SELECT feature, label, sum(n) AS n, any_value(t) AS t FROM known GROUP BY feature, label) q GROUP BY feature),
      hb AS (SELECT feature, sum(m / t * h) AS rest, sum(-m / t * log2(m / t)) AS hf FROM (SELECT feature, bin, sum(-n / m * log2(n / m)) AS h, any_value(m) AS m, any_value(t) AS t FROM known GROUP BY feature, bin) q GROUP BY feature),
      gain_t AS (SELECT hy.feature, greatest((h - rest) * t / a, 0) AS gain, CASE WHEN hf > 1e-12 THEN (h - rest) * t / a / hf ELSE 0 END AS gain_ratio, CASE WHEN hf + h > 1e-12 THEN 2 * (h - rest) * t / a / (hf + h) ELSE 0 END AS sym_uncert
        FROM hy JOIN hb USING (feature) JOIN everything USING (feature) JOIN (SELECT feature, any_value(t) AS t FROM known GROUP BY feature) k USING (feature))"""


def _gain(name, spark, sf_dir):
    table = infogain.information_gain(labelled(spark, sf_dir, name), fixtures.SPECS[name])
    return table.select("feature", *(F.round(c, 6).alias(c) for c in ("gain", "gain_ratio", "sym_uncert")))


for _name in ("traffic", "quality", "supplier", "part", "orders", "role"):
    query(f"info_gain_{_name}", f"WITH {fixture_cte(_name)}, {gain_ctes(_name)} SELECT feature, round(gain, 6) AS gain, round(gain_ratio, 6) AS gain_ratio, round(sym_uncert, 6) AS sym_uncert FROM gain_t")(partial(_gain, _name))


def pair_ctes(name: str, bins: int = 10, spec: list[Feature] | None = None) -> str:
    spec = spec or fixtures.SPECS[name]
    codes = [f"CASE WHEN x.{x.name} IS NULL THEN NULL ELSE cast(cast(least(floor((x.{x.name} - lo_{x.name}) * {bins} / (hi_{x.name} - lo_{x.name})), {bins - 1}) AS bigint) AS varchar) END AS {x.name}" if x.kind == "continuous" else f"cast(cast(least(floor(x.{x.name} * {bins}), {bins - 1}) AS bigint) AS varchar) AS {x.name}" if x.kind == "share" else f"cast(x.{x.name} AS varchar) AS {x.name}" for x in spec]
    ends = ", ".join(f"min({x.name}) AS lo_{x.name}, max({x.name}) AS hi_{x.name}" for x in spec if x.kind == "continuous")
    names = sorted([x.name for x in spec] + ["label"])
    arms = " UNION ALL ".join(f"SELECT '{a}' AS f, '{b}' AS g, {a} AS a, {b} AS b FROM codes" for i, a in enumerate(names) for b in names[i + 1 :])
    return f"""codes AS (SELECT {', '.join(codes)}, x.label FROM f x, (SELECT {ends} FROM f) r), p AS (SELECT f, g, a, b, count(*) AS n FROM ({arms}) q WHERE a IS NOT NULL AND b IS NOT NULL GROUP BY ALL),
      pt AS (SELECT *, sum(n) OVER (PARTITION BY f, g) AS t FROM p), hj AS (SELECT f, g, sum(-n / t * log2(n / t)) AS hj FROM pt GROUP BY f, g),
      ha AS (SELECT f, g, sum(-n / t * log2(n / t)) AS ha FROM (SELECT f, g, a, sum(n) AS n, any_value(t) AS t FROM pt GROUP BY f, g, a) q GROUP BY f, g), hbb AS (SELECT f, g, sum(-n / t * log2(n / t)) AS hb FROM (SELECT f, g, b, sum(n) AS n, any_value(t) AS t FROM pt GROUP BY f, g, b) q GROUP BY f, g),
      su AS (SELECT f, g, CASE WHEN ha + hb > 1e-12 THEN 2 * (ha + hb - hj) / (ha + hb) ELSE 0 END AS su FROM hj JOIN ha USING (f, g) JOIN hbb USING (f, g))"""


@query("sym_uncert_pairs_quality", f"WITH {fixture_cte('quality')}, {pair_ctes('quality')} SELECT f, g, round(su, 6) AS su FROM su")
def _pairs(spark, sf_dir):
    return infogain.pair_uncertainty(labelled(spark, sf_dir, "quality"), fixtures.SPECS["quality"]).select("f", "g", F.round("su", 6).alias("su"))


SUBSETS = (("letter_ratio",), ("letter_ratio", "uniq_ratio"), ("lang", "n_chars", "uniq_ratio"), ("lang", "letter_ratio", "n_chars", "n_lines", "n_words", "source", "uniq_ratio"))


def _merit_sql() -> str:
    arms = []
    for s in SUBSETS:
        inside = ", ".join(f"'{x}'" for x in s)
        to_class = f"(SELECT avg(su) FROM su WHERE (f = 'label' AND g IN ({inside})) OR (g = 'label' AND f IN ({inside})))"
        mutual = f"coalesce((SELECT avg(su) FROM su WHERE f IN ({inside}) AND g IN ({inside})), 0)"
        arms.append(f"SELECT '{'+'.join(s)}' AS subset, round({len(s)} * {to_class} / sqrt({len(s)} + {len(s) * (len(s) - 1)} * {mutual}), 6) AS merit")
    return f"WITH {fixture_cte('quality')}, {pair_ctes('quality')} " + " UNION ALL ".join(arms)


@query("cfs_merit_quality", _merit_sql())
def _merits(spark, sf_dir):
    pairs = infogain.pair_uncertainty(labelled(spark, sf_dir, "quality"), fixtures.SPECS["quality"])
    arms = []
    for s in SUBSETS:
        to_class = F.avg(F.when((F.col("f").isin(*s) & (F.col("g") == "label")) | (F.col("g").isin(*s) & (F.col("f") == "label")), F.col("su")))
        mutual = F.coalesce(F.avg(F.when(F.col("f").isin(*s) & F.col("g").isin(*s), F.col("su"))), F.lit(0.0))
        r = len(s)
        arms.append(F.struct(F.lit("+".join(s)).alias("subset"), F.round(r * to_class / F.sqrt(r + r * (r - 1) * mutual), 6).alias("merit")))
    return pairs.agg(F.array(*arms).alias("a")).select(F.explode("a").alias("a")).select("a.*")


# --- fuzzy c-means -------------------------------------------------------------------------------------------------------
def _numeric(name):
    return [x for x in fixtures.SPECS[name] if x.numeric]


def _symbolic(name):
    return [x for x in fixtures.SPECS[name] if not x.numeric]


def fcm_ctes(name: str, k: int, steps: int, weighted: bool = True, unknown: str = "both", tag: str = "", crisp: bool = False, others: str = "") -> str:
    """CTEs n, v0..v<steps>, w0..w<steps>: normalised rows, centroids and memberships of each round. others: a condition on rows of the fixture that take the last memberships (table wo) and no other part."""
    num, cat = _numeric(name), _symbolic(name)
    scaled = [f"x.{c.name} / {c.levels - 1} AS {c.name}" if c.kind == "ordinal" else f"(x.{c.name} - lo_{c.name}) / (hi_{c.name} - lo_{c.name}) AS {c.name}" for c in num]
    ends = ", ".join(f"min({c.name}) AS lo_{c.name}, max({c.name}) AS hi_{c.name}" for c in num if c.kind == "continuous")
    names = [c.name for c in num + cat]
    g = {c: f"(SELECT gain FROM gain_t WHERE feature = '{c}')" if weighted else "1" for c in names}
    out = [f"n{tag} AS (SELECT row_id, {', '.join(scaled + ['x.' + c.name for c in cat])} FROM f x, (SELECT {ends} FROM f) r)"] if not tag or tag == "_first" else []
    n = "n"
    if others:
        out.append(f"no AS (SELECT row_id, {', '.join(scaled + ['x.' + c.name for c in cat])} FROM (SELECT * FROM ({fixtures.duckdb_sql(name)}) q WHERE {others}) x, (SELECT {ends} FROM f) r)")
    out.append(f"v{tag}0 AS (SELECT row_number() OVER (ORDER BY m) - 1 AS j, {', '.join(names)} FROM (SELECT {', '.join(names)}, min(md5('seed' || cast(row_id AS varchar))) AS m FROM {n} GROUP BY ALL ORDER BY m LIMIT {k}) q)")
    for i in range(steps + 1):
        terms = [f"{g[c.name]} * CASE WHEN n.{c.name} IS NULL {'AND' if unknown == 'both' else 'OR'} v.{c.name} IS NULL THEN 1 WHEN n.{c.name} IS NULL OR v.{c.name} IS NULL THEN 0 ELSE (n.{c.name} - v.{c.name}) * (n.{c.name} - v.{c.name}) END" for c in num]
        terms += [f"{g[c.name]} * CASE WHEN n.{c.name} IS NULL {'AND' if unknown == 'both' else 'OR'} v.{c.name} IS NULL THEN 1 WHEN n.{c.name} IS NULL OR v.{c.name} IS NULL THEN 0 WHEN n.{c.name} <> v.{c.name} THEN 1 ELSE 0 END" for c in cat]
        if others and i == steps:
            out.append(f"d_o AS (SELECT n.row_id, v.j, {' + '.join(terms)} AS d2 FROM no n, v{tag}{i} v)")
            out.append(f"u_o AS (SELECT *, CASE WHEN min(d2) OVER (PARTITION BY row_id) <= 0 THEN CASE WHEN d2 <= 0 THEN 1.0 ELSE 0.0 END ELSE power(d2 / min(d2) OVER (PARTITION BY row_id), {-1 / (ALPHA - 1)}) END AS u FROM d_o)")
            out.append("wo AS (SELECT *, u / sum(u) OVER (PARTITION BY row_id) AS w FROM u_o)")
        out.append(f"d{tag}{i} AS (SELECT n.row_id, v.j, {', '.join('n.' + c for c in names)}, {' + '.join(terms)} AS d2 FROM {n} n, v{tag}{i} v)")
        if crisp:
            out.append(f"u{tag}{i} AS (SELECT *, CASE WHEN row_number() OVER (PARTITION BY row_id ORDER BY round(d2, 9), j) = 1 THEN 1.0 ELSE 0.0 END AS u FROM d{tag}{i})")
        else:
            out.append(f"u{tag}{i} AS (SELECT *, CASE WHEN min(d2) OVER (PARTITION BY row_id) <= 0 THEN CASE WHEN d2 <= 0 THEN 1.0 ELSE 0.0 END ELSE power(d2 / min(d2) OVER (PARTITION BY row_id), {-1 / (ALPHA - 1)}) END AS u FROM d{tag}{i})")
        out.append(f"w{tag}{i} AS (SELECT *, u / sum(u) OVER (PARTITION BY row_id) AS w FROM u{tag}{i})")
        if i < steps:
            means = ", ".join(f"sum(CASE WHEN {c.name} IS NOT NULL THEN power(w, {ALPHA}) * {c.name} END) / sum(CASE WHEN {c.name} IS NOT NULL THEN power(w, {ALPHA}) END) AS {c.name}" for c in num)
            modes = "".join(f" JOIN (SELECT j, {c.name} FROM (SELECT j, {c.name}, row_number() OVER (PARTITION BY j ORDER BY sum(power(w, {ALPHA})) DESC, {c.name}) AS r FROM w{tag}{i} WHERE {c.name} IS NOT NULL GROUP BY j, {c.name}) q WHERE r = 1) m_{c.name} USING (j)" for c in cat)
            out.append(f"v{tag}{i + 1} AS (SELECT j, {', '.join(['a.' + c.name for c in num] + [f'm_{c.name}.{c.name}' for c in cat])} FROM (SELECT j, {means} FROM w{tag}{i} GROUP BY j) a{modes})")
    return ", ".join(out)


def _centroid_rows(name: str, table: str, extra: str = "") -> str:
    arms = [f"SELECT {extra}j, '{c.name}' AS feature, round({c.name}, 5) AS v, cast(NULL AS varchar) AS level FROM {table}" for c in _numeric(name)]
    arms += [f"SELECT {extra}j, '{c.name}' AS feature, cast(NULL AS double) AS v, {c.name} AS level FROM {table}" for c in _symbolic(name)]
    return " UNION ALL ".join(arms)


def _start(spark, sf_dir, name, weighted=True):
    df = materialise(labelled(spark, sf_dir, name))  # measures of texts and fields of JSON, which each scan would work out again
    spec = fixtures.SPECS[name]
    scaler = fit_scaler(df, spec)
    g = infogain.gains(df, spec) if weighted else {x.name: 1.0 for x in spec}
    packed = scaler.pack(df, "row_id")
    return df, scaler, packed, np.array([g[x.name] for x in _numeric(name)]), np.array([g[x.name] for x in _symbolic(name)])


def _models(spark, sf_dir, name, counts, steps, weighted=True, alpha=ALPHA) -> tuple:
    df, scaler, packed, gn, gc = _start(spark, sf_dir, name, weighted)
    return df, scaler, packed, fit_many(packed, counts, gn, gc, [len(scaler.levels[x.name]) for x in _symbolic(name)], alpha, tol=0.0, max_iter=steps)


def _centroid_frame(spark, name, scaler, models: dict[int, FcmModel], with_k: bool):
    rows = []
    for k, m in models.items():
        for j in range(k):
            head = (k, j) if with_k else (j,)
            rows += [(*head, x.name, round(float(m.centroids.num[j, q]), 5), None) for q, x in enumerate(_numeric(name))]
            rows += [(*head, x.name, None, scaler.levels[x.name][m.centroids.cat[j, q]]) for q, x in enumerate(_symbolic(name))]
    return spark.createDataFrame(rows, ("k int, " if with_k else "") + "j long, feature string, v double, level string")


def _centroids(name, counts, steps, weighted, with_k, spark, sf_dir, alpha=ALPHA):
    _, scaler, _, models = _models(spark, sf_dir, name, counts, steps, weighted, alpha)
    return _centroid_frame(spark, name, scaler, models, with_k)


query("fcm_centroids_3iter_traffic", f"WITH {fixture_cte('traffic')}, {gain_ctes('traffic')}, {fcm_ctes('traffic', 3, 3)} {_centroid_rows('traffic', 'v3')}")(partial(_centroids, "traffic", [3], 3, True, False))
query("fcm_centroids_3iter_quality", f"WITH {fixture_cte('quality')}, {gain_ctes('quality')}, {fcm_ctes('quality', 3, 3)} {_centroid_rows('quality', 'v3')}")(partial(_centroids, "quality", [3], 3, True, False))
query("fcm_unweighted_quality", f"WITH {fixture_cte('quality')}, {fcm_ctes('quality', 3, 2, weighted=False)} {_centroid_rows('quality', 'v2')}")(partial(_centroids, "quality", [3], 2, False, False))
query("crisp_centroids_3iter_quality", f"WITH {fixture_cte('quality')}, {gain_ctes('quality')}, {fcm_ctes('quality', 3, 3, crisp=True)} {_centroid_rows('quality', 'v3')}")(partial(_centroids, "quality", [3], 3, True, False, alpha=1.0))
query(
    "fcm_multi_k_traffic",
    f"WITH {fixture_cte('traffic')}, {gain_ctes('traffic')}, {fcm_ctes('traffic', 2, 2)}, {fcm_ctes('traffic', 3, 2, tag='_b')}, {fcm_ctes('traffic', 5, 2, tag='_c')} " + " UNION ALL ".join(_centroid_rows("traffic", t, f"{k} AS k, ") for t, k in (("v2", 2), ("v_b2", 3), ("v_c2", 5))),
)(partial(_centroids, "traffic", [2, 3, 5], 2, True, True))


@query("fcm_objective_trace_traffic", f"WITH {fixture_cte('traffic')}, {gain_ctes('traffic')}, {fcm_ctes('traffic', 3, 3)} " + " UNION ALL ".join(f"SELECT {i} AS iter, round(sum(power(w, {ALPHA}) * d2), 4) AS objective FROM w{i}" for i in range(4)))
def _trace(spark, sf_dir):
    _, _, _, models = _models(spark, sf_dir, "traffic", [3], 4)
    return spark.createDataFrame([(i, round(x, 4)) for i, x in enumerate(models[3].trace)], "iter int, objective double")


def _seeded(spark, sf_dir, name, unknown="both", weighted=True):
    df, scaler, packed, gn, gc = _start(spark, sf_dir, name, weighted)
    return df, scaler, packed, FcmModel(seeds(packed, SEEDED), gn, gc, ALPHA, unknown)


def _distances(name, unknown, spark, sf_dir):
    _, _, packed, model = _seeded(spark, sf_dir, name, unknown)
    return packed.select("row_id", F.posexplode(distance_column(model)).alias("j", "d2")).select("row_id", F.col("j").cast("long").alias("j"), F.round("d2", 6).alias("d2"))


def _distance_sql(name, unknown="both"):
    return f"WITH {fixture_cte(name)}, {gain_ctes(name)}, {fcm_ctes(name, SEEDED, 0, unknown=unknown)} SELECT row_id, j, round(d2, 6) AS d2 FROM d0"


query("mixed_distance_traffic", _distance_sql("traffic"))(partial(_distances, "traffic", "both"))
query("mixed_distance_quality", _distance_sql("quality"))(partial(_distances, "quality", "both"))


query("mixed_distance_unknown_both", _distance_sql("unknowns", "both"))(partial(_distances, "unknowns", "both"))
query("mixed_distance_unknown_either", _distance_sql("unknowns", "either"))(partial(_distances, "unknowns", "either"))
query("fcm_centroids_2iter_unknowns", f"WITH {fixture_cte('unknowns')}, {gain_ctes('unknowns')}, {fcm_ctes('unknowns', 3, 2)} {_centroid_rows('unknowns', 'v2')}")(partial(_centroids, "unknowns", [3], 2, True, False))


@query("fcm_membership_quality", f"WITH {fixture_cte('quality')}, {gain_ctes('quality')}, {fcm_ctes('quality', SEEDED, 0)} SELECT row_id, j, round(w, 5) AS w FROM w0")
def _memberships(spark, sf_dir):
    _, _, packed, model = _seeded(spark, sf_dir, "quality")
    p = membership_column(distance_column(model), ALPHA)
    return packed.select("row_id", F.posexplode(p).alias("j", "w")).select("row_id", F.col("j").cast("long").alias("j"), F.round("w", 5).alias("w"))


@query("sqlfunc_membership", SQL["fcm_membership_quality"])
def _sqlfunc(spark, sf_dir):
    udx.register(spark)
    _, _, packed, model = _seeded(spark, sf_dir, "quality")
    packed.select("row_id", distance_column(model).alias("d")).createOrReplaceTempView("distances_of_rows")
    return spark.sql(f"SELECT row_id, cast(j AS bigint) AS j, round(w, 5) AS w FROM (SELECT row_id, fuzzy_membership(d, {ALPHA}D) AS p FROM distances_of_rows) LATERAL VIEW posexplode(p) AS j, w")


@query("udtf_memberships", SQL["fcm_membership_quality"])
def _udtf(spark, sf_dir):
    udx.register(spark)
    _, _, packed, model = _seeded(spark, sf_dir, "quality")
    packed.select("row_id", membership_column(distance_column(model), ALPHA).alias("p")).createOrReplaceTempView("memberships_of_rows")
    return spark.sql("SELECT row_id, cast(t.j AS bigint) AS j, round(t.w, 5) AS w FROM memberships_of_rows, LATERAL memberships_rows(p) t")


def _augmented(name, T, spark, sf_dir):
    df, scaler, _, model = _seeded(spark, sf_dir, name)
    out = features.augment(df, scaler, model, T)
    extra = [F.round(f"p_{j + 1}", 5).alias(f"p_{j + 1}") for j in range(SEEDED)] if T == 2 else []
    return out.select("row_id", "z", "b", *extra)


def _augmented_sql(name, T):
    rows = ", ".join(f"round(max(CASE WHEN j = {j} THEN w END), 5) AS p_{j + 1}" for j in range(SEEDED))
    return f"WITH {fixture_cte(name)}, {gain_ctes(name)}, {fcm_ctes(name, SEEDED, 0)} SELECT row_id, cast(min(CASE WHEN r = 1 THEN j END) AS int) AS z, max(w6) AS b{', ' + rows if T == 2 else ''} FROM (SELECT *, round(w, 6) AS w6, row_number() OVER (PARTITION BY row_id ORDER BY round(w, 6) DESC, j) AS r FROM w0) q GROUP BY row_id"


query("cluster_features_t1_traffic", _augmented_sql("traffic", 1))(partial(_augmented, "traffic", 1))
query("cluster_features_t2_quality", _augmented_sql("quality", 2))(partial(_augmented, "quality", 2))


def best_subset_sql(name: str, clusters: int) -> str:
    """(subset, merit) of the best of all subsets, by enumeration; clusters: that many of the seeds' memberships, z and b are columns too."""
    spec = list(fixtures.SPECS[name])
    if clusters:
        spec += [Feature("z", "symbolic"), Feature("b", "share"), *(Feature(f"p_{j + 1}", "share") for j in range(clusters))]
    names = sorted(x.name for x in spec)
    inside = " + ".join(f"(mask >> {i}) % 2" for i in range(len(names)))
    chosen = lambda c: "CASE " + " ".join(f"WHEN {c} = '{x}' THEN (mask >> {i}) % 2" for i, x in enumerate(names)) + " ELSE 0 END"
    text = " || ".join(f"CASE WHEN (mask >> {i}) % 2 = 1 THEN '+{x}' ELSE '' END" for i, x in enumerate(names))
    head = f"WITH {fixture_cte(name)}"
    if clusters:
        wide = f"SELECT row_id, cast(min(CASE WHEN r = 1 THEN j END) AS int) AS z, max(w6) AS b, {', '.join(f'max(CASE WHEN j = {j} THEN w6 END) AS p_{j + 1}' for j in range(clusters))} FROM (SELECT *, round(w, 6) AS w6, row_number() OVER (PARTITION BY row_id ORDER BY round(w, 6) DESC, j) AS r FROM w0) q GROUP BY row_id"
        head = f"WITH f0 AS (SELECT * FROM ({fixtures.duckdb_sql(name)}) q WHERE label IS NOT NULL), {gain_ctes(name).replace(' f,', ' f0,').replace(' FROM f ', ' FROM f0 ').replace('FROM f)', 'FROM f0)')}, {fcm_ctes(name, clusters, 0).replace(' FROM f x', ' FROM f0 x').replace('FROM f)', 'FROM f0)')}, f AS (SELECT f0.*, a.* EXCLUDE (row_id) FROM f0 JOIN ({wide}) a ON a.row_id = f0.row_id)"
    pairs = pair_ctes(name, spec=spec)
    return f"""{head}, {pairs}, m AS (SELECT mask, {inside} AS r FROM (SELECT unnest(range(1, {2 ** len(names)})) AS mask) q),
      e AS (SELECT mask, any_value(r) AS r, sum(CASE WHEN f = 'label' THEN su * {chosen('g')} WHEN g = 'label' THEN su * {chosen('f')} ELSE 0 END) AS c, sum(CASE WHEN f <> 'label' AND g <> 'label' THEN su * {chosen('f')} * {chosen('g')} ELSE 0 END) AS ff FROM m, su GROUP BY mask)
      SELECT subset, round(merit, 6) AS merit FROM (SELECT substr({text}, 2) AS subset, c / sqrt(r + 2 * ff) AS merit, r FROM e) q ORDER BY round(merit, 10) DESC, r LIMIT 1"""


query("cfs_best_exhaustive_quality", best_subset_sql("quality", 0))(partial(workloads.best_subset, "quality"))


@query("t3_best_subset_quality", best_subset_sql("quality", SEEDED))
def _t3_best(spark, sf_dir):
    _, scaler, _, model = _seeded(spark, sf_dir, "quality")
    return workloads.best_subset("quality", spark, sf_dir, model, scaler)


@query("cluster_features_t3_quality")
def _t3(spark, sf_dir):
    df, scaler, _, model = _seeded(spark, sf_dir, "quality")
    subset = CfsSelector().choose(*associations(df, fixtures.SPECS["quality"], scaler, {SEEDED: model}, 3, "label")[SEEDED])
    return features.augment(df, scaler, model, 3, subset)


@query("validity_by_k_quality", f"WITH {fixture_cte('quality')}, {gain_ctes('quality')}, {fcm_ctes('quality', 2, 1)}, {fcm_ctes('quality', 3, 1, tag='_b')} " + " UNION ALL ".join(f"SELECT {k} AS k, round((SELECT sum(w * w) / count(DISTINCT row_id) FROM w{t}1), 5) AS pc, round((SELECT sum(CASE WHEN w > 0 THEN -w * ln(w) ELSE 0 END) / count(DISTINCT row_id) FROM w{t}1), 5) AS pe" for k, t in ((2, ""), (3, "_b"))))
def _validity(spark, sf_dir):
    _, _, packed, models = _models(spark, sf_dir, "quality", [2, 3], 1)
    return validity.validity(packed, models).select("k", F.round("pc", 5).alias("pc"), F.round("pe", 5).alias("pe"))


@query("xie_beni_quality")
def _xie_beni(spark, sf_dir):
    _, _, packed, models = _models(spark, sf_dir, "quality", [2, 3, 5], 5)
    return validity.validity(packed, models).select("k", F.round("xb", 5).alias("xb"))


@query("topk_ambiguous_quality", f"WITH {fixture_cte('quality')}, {gain_ctes('quality')}, {fcm_ctes('quality', SEEDED, 0)} SELECT row_id, round(gap, 4) AS gap FROM (SELECT row_id, round(max(CASE WHEN r = 1 THEN w END) - max(CASE WHEN r = 2 THEN w END), 4) AS gap FROM (SELECT *, row_number() OVER (PARTITION BY row_id ORDER BY w DESC, j) AS r FROM w0) q GROUP BY row_id) t ORDER BY gap, row_id LIMIT 20")
def _ambiguous(spark, sf_dir):
    _, _, packed, model = _seeded(spark, sf_dir, "quality")
    p = F.array_sort(membership_column(distance_column(model), ALPHA))
    rows = packed.select("row_id", p.alias("p")).select("row_id", F.round(F.get("p", F.lit(SEEDED - 1)) - F.get("p", F.lit(SEEDED - 2)), 4).alias("gap"))
    return rows.orderBy("gap", "row_id").limit(20)


# --- folds, reduced sets, measures ---------------------------------------------------------------------------------------
def _h(salt: str, column: str = "row_id") -> str:
    return f"cast(('0x' || substr(md5('{salt}' || cast({column} AS varchar)), 1, 8)) AS bigint)"


@query("stratified_folds_traffic", f"WITH {fixture_cte('traffic')} SELECT fold, fine_label, count(*) AS n, min(row_id) AS first_row FROM (SELECT *, cast((row_number() OVER (PARTITION BY fine_label ORDER BY {_h('fold')}, row_id) - 1) % 10 AS int) AS fold FROM f) q GROUP BY fold, fine_label")
def _folds(spark, sf_dir):
    return sampling.stratified_folds(labelled(spark, sf_dir, "traffic")).groupBy("fold", "fine_label").agg(F.count("*").alias("n"), F.min("row_id").alias("first_row"))


def _reduced(part, fraction, spark, sf_dir):
    df = sampling.train_test(labelled(spark, sf_dir, "traffic")).filter(F.col("part") == part)
    return sampling.reduced(df, {"flood": fraction, "benign": fraction}).select("row_id", "label")


def _reduced_sql(part, fraction):
    return f"SELECT row_id, label FROM f WHERE {_h('split')} % 2 = {0 if part == 'train' else 1} AND (label NOT IN ('flood', 'benign') OR {_h('thin')} % 1000 < {1000 * fraction})"


query("reduced_train_traffic", f"WITH {fixture_cte('traffic')} {_reduced_sql('train', 0.05)}")(partial(_reduced, "train", 0.05))
query("reduced_test_traffic", f"WITH {fixture_cte('traffic')} {_reduced_sql('test', 0.5)}")(partial(_reduced, "test", 0.5))


@query("class_distribution_traffic", f"WITH {fixture_cte('traffic')}, s AS (SELECT 'train' AS part, label FROM ({_reduced_sql('train', 0.05)}) a UNION ALL SELECT 'test', label FROM ({_reduced_sql('test', 0.5)}) b) SELECT part, label, count(*) AS n FROM s GROUP BY ROLLUP (part, label)")
def _distribution(spark, sf_dir):
    both = _reduced("train", 0.05, spark, sf_dir).withColumn("part", F.lit("train")).unionByName(_reduced("test", 0.5, spark, sf_dir).withColumn("part", F.lit("test")))
    return metrics.class_distribution(both)


RULE = "CASE WHEN event_type = 'error' AND hour BETWEEN 6 AND 17 THEN 'scan' WHEN (value > 35) <> (k >= 50) THEN 'benign' ELSE 'flood' END"


def _ruled(spark, sf_dir):
    return metrics.confusion(labelled(spark, sf_dir, "traffic").withColumn("prediction", F.expr(RULE)))


_CONF = f"{fixture_cte('traffic')}, conf AS (SELECT label, {RULE} AS prediction, count(*) AS n FROM f GROUP BY 1, 2)"
_RATES = f"{_CONF}, per AS (SELECT label, sum(n) AS n, sum(CASE WHEN label = prediction THEN n ELSE 0 END) AS tp FROM conf GROUP BY label), fps AS (SELECT prediction AS label, sum(CASE WHEN label <> prediction THEN n ELSE 0 END) AS fp FROM conf GROUP BY prediction), r AS (SELECT per.label, tp / n AS tpr, coalesce(fp, 0) / ((SELECT sum(n) FROM per) - n) AS fpr, cast(n AS bigint) AS n FROM per LEFT JOIN fps USING (label))"
query("confusion_traffic", f"WITH {_CONF} SELECT * FROM conf")(_ruled)
query("rates_traffic", f"WITH {_RATES} SELECT label, round(tpr, 6) AS tpr, round(fpr, 6) AS fpr, n FROM r")(lambda s, d: metrics.rates(_ruled(s, d)).select("label", F.round("tpr", 6).alias("tpr"), F.round("fpr", 6).alias("fpr"), "n"))
query("average_rates_traffic", f"WITH {_RATES} SELECT round(sum(n * tpr) / sum(n), 6) AS avg_tpr, round(sum(n * fpr) / sum(n), 6) AS avg_fpr FROM r")(lambda s, d: metrics.average_rates(metrics.rates(_ruled(s, d))).select(F.round("avg_tpr", 6).alias("avg_tpr"), F.round("avg_fpr", 6).alias("avg_fpr")))
query("accuracy_traffic", f"WITH {_CONF} SELECT round(sum(CASE WHEN label = prediction THEN n ELSE 0 END) / sum(n), 6) AS accuracy FROM conf")(lambda s, d: metrics.accuracy(_ruled(s, d)).select(F.round("accuracy", 6).alias("accuracy")))
query("pivot_confusion_traffic", f"WITH {_CONF} SELECT label, cast(sum(CASE WHEN prediction = 'benign' THEN n END) AS bigint) AS benign, cast(sum(CASE WHEN prediction = 'flood' THEN n END) AS bigint) AS flood, cast(sum(CASE WHEN prediction = 'scan' THEN n END) AS bigint) AS scan FROM conf GROUP BY label")(lambda s, d: _ruled(s, d).groupBy("label").pivot("prediction", ["benign", "flood", "scan"]).sum("n"))


# --- relational and window operators ---------------------------------------------------------------------------------------
def events(spark, sf_dir):
    return load(spark, sf_dir, "events").withColumn("ts", F.col("ts").cast("timestamp"))


@query("traffic_counters", "SELECT event_id, count(*) OVER (PARTITION BY user_id ORDER BY epoch(ts) RANGE BETWEEN 21600 PRECEDING AND CURRENT ROW) AS user_recent, cast(epoch(ts) - lag(epoch(ts)) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS bigint) AS user_gap FROM (SELECT event_id, user_id, date_trunc('second', ts) AS ts FROM events) e")
def _counters(spark, sf_dir):
    seconds = F.unix_seconds("ts")
    by_time = Window.partitionBy("user_id").orderBy(seconds).rangeBetween(-21600, 0)
    return events(spark, sf_dir).select("event_id", F.count("*").over(by_time).alias("user_recent"), (seconds - F.lag(seconds).over(Window.partitionBy("user_id").orderBy("ts", "event_id"))).alias("user_gap"))


@query("asof_latest_error", "SELECT event_id, (SELECT max(e2.event_id) FROM events e2 WHERE e2.user_id = e.user_id AND e2.event_type = 'error' AND e2.event_id < e.event_id) AS last_error FROM events e")
def _asof(spark, sf_dir):
    before = Window.partitionBy("user_id").orderBy("event_id").rowsBetween(Window.unboundedPreceding, -1)
    return events(spark, sf_dir).select("event_id", F.last(F.when(F.col("event_type") == "error", F.col("event_id")), ignorenulls=True).over(before).alias("last_error"))


@query("interval_pairs", "SELECT a.event_id AS a, b.event_id AS b FROM events a JOIN events b ON a.user_id = b.user_id AND a.event_id < b.event_id AND b.ts <= a.ts + INTERVAL 2 HOURS")
def _interval(spark, sf_dir):
    a, b = events(spark, sf_dir).select("event_id", "user_id", "ts").alias("a"), events(spark, sf_dir).select("event_id", "user_id", "ts").alias("b")
    return a.join(b, F.expr("a.user_id = b.user_id AND a.event_id < b.event_id AND b.ts <= a.ts + INTERVAL 2 HOURS")).select(F.col("a.event_id").alias("a"), F.col("b.event_id").alias("b"))


@query("range_bin_join", "SELECT bin, count(*) AS n FROM events e JOIN (SELECT * FROM (VALUES (0, 0.0, 20.0), (1, 20.0, 50.0), (2, 50.0, 1e9)) t(bin, lo, hi)) r ON e.value >= lo AND e.value < hi GROUP BY bin")
def _range_join(spark, sf_dir):
    bins = spark.createDataFrame([(0, 0.0, 20.0), (1, 20.0, 50.0), (2, 50.0, 1e9)], "bin int, lo double, hi double")
    e = load(spark, sf_dir, "events", ["value"])
    return e.join(F.broadcast(bins), (e.value >= bins.lo) & (e.value < bins.hi)).groupBy("bin").agg(F.count("*").alias("n"))


query("unlabelled_anti", "SELECT doc_id FROM documents d WHERE NOT EXISTS (SELECT 1 FROM labels l WHERE l.doc_id = d.doc_id)")(lambda s, d: load(s, d, "documents", ["doc_id"]).join(load(s, d, "labels", ["doc_id"]), "doc_id", "left_anti"))
query("labelled_semi", "SELECT doc_id, lang FROM documents d WHERE EXISTS (SELECT 1 FROM labels l WHERE l.doc_id = d.doc_id)")(lambda s, d: load(s, d, "documents", ["doc_id", "lang"]).join(load(s, d, "labels", ["doc_id"]), "doc_id", "left_semi"))
query("star_features_orders", f"SELECT * FROM ({fixtures.duckdb_sql('orders')}) q")(lambda s, d: fixtures.load(s, d, "orders"))


def _split(spark, sf_dir):
    df = sampling.train_test(labelled(spark, sf_dir, "traffic"))
    return df.filter("part = 'train'").select("row_id"), df.filter("part = 'test'").select("row_id"), df.select("row_id")


query("split_union", f"WITH {fixture_cte('traffic')} SELECT row_id FROM f")(lambda s, d: (lambda t: t[0].union(t[1]))(_split(s, d)))
query("split_intersect", f"WITH {fixture_cte('traffic')} SELECT row_id FROM f WHERE {_h('split')} % 2 = 0 INTERSECT SELECT row_id FROM f WHERE {_h('split')} % 2 <> 0")(lambda s, d: (lambda t: t[0].intersect(t[1]))(_split(s, d)))
query("split_except", f"WITH {fixture_cte('traffic')} SELECT row_id FROM f WHERE {_h('split')} % 2 <> 0")(lambda s, d: (lambda t: t[2].exceptAll(t[0]))(_split(s, d)))


@query("rates_cube_orders", f"WITH {fixture_cte('orders')} SELECT c_mktsegment AS segment, label, count(*) AS n, round(avg(CASE WHEN o_orderstatus = 'O' THEN 1.0 ELSE 0.0 END), 6) AS open_share FROM f GROUP BY CUBE (c_mktsegment, label)")
def _cube(spark, sf_dir):
    return labelled(spark, sf_dir, "orders").cube(F.col("c_mktsegment").alias("segment"), "label").agg(F.count("*").alias("n"), F.round(F.avg(F.when(F.col("o_orderstatus") == "O", 1.0).otherwise(0.0)), 6).alias("open_share"))


@query("json_map_array_functions", "SELECT event_id, cast(json_extract_string(props, '$.k') AS int) AS k, cast(list_sum(list_transform(range(1, 4), lambda i: i * cast(json_extract_string(props, '$.k') AS int))) AS bigint) AS total, upper(event_type) AS kind FROM events")
def _functions(spark, sf_dir):
    k = F.get_json_object("props", "$.k").cast("int")
    return load(spark, sf_dir, "events").select("event_id", k.alias("k"), F.aggregate(F.transform(F.sequence(F.lit(1), F.lit(3)), lambda i: i * k), F.lit(0).cast("bigint"), lambda a, x: a + x).alias("total"), F.upper("event_type").alias("kind"))


query("text_features_documents", f"SELECT row_id, n_chars, n_words, n_lines, round(letter_ratio, 6) AS letter_ratio, round(uniq_ratio, 6) AS uniq_ratio FROM ({fixtures.duckdb_sql('quality')}) q")(lambda s, d: fixtures.load(s, d, "quality").select("row_id", "n_chars", "n_words", "n_lines", F.round("letter_ratio", 6).alias("letter_ratio"), F.round("uniq_ratio", 6).alias("uniq_ratio")))
query("date_features_lineitem", "SELECT cast(month(l_shipdate) AS int) AS m, cast(isodow(l_shipdate) - 1 AS int) AS wd, count(*) AS n, round(sum(l_quantity), 2) AS q FROM lineitem GROUP BY 1, 2")(lambda s, d: load(s, d, "lineitem", ["l_shipdate", "l_quantity"]).groupBy(F.month("l_shipdate").alias("m"), F.weekday("l_shipdate").alias("wd")).agg(F.count("*").alias("n"), F.round(F.sum("l_quantity"), 2).alias("q")))


# --- streams -------------------------------------------------------------------------------------------------------------
def _stream(spark, sf_dir):
    return stream_table(spark, sf_dir, "events")


query("stream_tumbling", "SELECT date_trunc('day', ts) AS window_start, event_type, count(*) AS n, round(avg(value), 4) AS mean_value FROM events GROUP BY 1, 2")(lambda s, d: ops.run_once(ops.tumbling(_stream(s, d)), "complete").select(F.col("window_start").cast("timestamp_ntz").alias("window_start"), "event_type", "n", F.round("mean_value", 4).alias("mean_value")))
query("stream_sliding", "SELECT w AS window_start, count(*) AS n, round(avg(CASE WHEN event_type = 'error' THEN 1.0 ELSE 0.0 END), 6) AS alert_rate FROM (SELECT date_trunc('day', ts) AS w, event_type FROM events UNION ALL SELECT date_trunc('day', ts) - INTERVAL 1 DAY, event_type FROM events) q GROUP BY 1")(lambda s, d: ops.run_once(ops.alert_rate(_stream(s, d).withColumn("alert", F.col("event_type") == "error")), "complete").select(F.col("window_start").cast("timestamp_ntz").alias("window_start"), "n", F.round("alert_rate", 6).alias("alert_rate")))
query("stream_session", "SELECT user_id, min(ts) AS session_start, count(*) AS n FROM (SELECT *, sum(new) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS s FROM (SELECT *, CASE WHEN lag(ts) OVER (PARTITION BY user_id ORDER BY ts, event_id) IS NULL OR ts >= lag(ts) OVER (PARTITION BY user_id ORDER BY ts, event_id) + INTERVAL 6 HOURS THEN 1 ELSE 0 END AS new FROM events) e) t GROUP BY user_id, s")(lambda s, d: ops.run_once(ops.sessions(_stream(s, d)), "complete").withColumn("session_start", F.col("session_start").cast("timestamp_ntz")))
query("stream_dedup", "SELECT DISTINCT event_id, user_id FROM events")(lambda s, d: ops.run_once(ops.dedup(_stream(s, d), ["event_id"]).select("event_id", "user_id")))


_LATE = "date_trunc('day', ts)"


@query("stream_late", f"WITH cut AS (SELECT median(event_id) AS m FROM events), newer AS (SELECT e.* FROM events e, cut WHERE event_id >= m) SELECT {_LATE} AS window_start, event_type, count(*) AS n, round(sum(value), 2) AS total FROM newer GROUP BY 1, 2 HAVING {_LATE} + INTERVAL 1 DAY <= (SELECT max(ts) FROM newer) - INTERVAL 2 DAY")
def _late(spark, sf_dir):
    """The newer half of the events comes first, in two batches; the older half is late then, and the watermark leaves it out."""
    df = load(spark, sf_dir, "events")
    middle = df.select(F.median("event_id")).first()[0]
    newer = df.filter(F.col("event_id") >= middle)
    stream = ops.replay([newer.filter("event_id % 2 = 0"), newer.filter("event_id % 2 = 1"), df.filter(F.col("event_id") < middle)])
    out = ops.run_once(ops.tumbling(stream.withColumn("ts", F.col("ts").cast("timestamp"))))
    return out.select(F.col("window_start").cast("timestamp_ntz").alias("window_start"), "event_type", "n", F.round(F.col("n") * F.col("mean_value"), 2).alias("total"))


@query("stream_rolling_rates", SQL["rates_traffic"])
def _rolling(spark, sf_dir):
    """Predictions of a rule, joined with the truth that comes an hour later, and the rates of what met."""
    shaped = lambda: _stream(spark, sf_dir).select("event_id", "ts", "value", F.get_json_object("props", "$.k").cast("int").alias("k"), F.hour("ts").alias("hour"), "event_type")
    truth = fixtures.load(spark, sf_dir, "traffic").select(F.col("row_id").alias("truth_of"), "label")
    predicted = shaped().select("event_id", "ts", F.expr(RULE).alias("prediction"))
    known = shaped().select(F.col("event_id").alias("truth_id"), (F.col("ts") + F.expr("INTERVAL 1 HOUR")).alias("truth_ts")).join(truth, F.col("truth_id") == F.col("truth_of")).drop("truth_of")
    met = ops.run_once(ops.rolling_rates(predicted, known).select("label", "prediction"))
    return metrics.rates(metrics.confusion(met)).select("label", F.round("tpr", 6).alias("tpr"), F.round("fpr", 6).alias("fpr"), "n")


@query("stream_drift", f"SELECT date_trunc('day', ts) AS window_start, z, count(*) AS n, round(avg(b), 5) AS mean_b FROM ({_augmented_sql('traffic', 1)}) a JOIN events ON event_id = row_id GROUP BY 1, 2")
def _drift(spark, sf_dir):
    """Strength and sizes of the clusters by day, on the stream: what training is held against."""
    _, scaler, _, model = _seeded(spark, sf_dir, "traffic")
    shaped = _stream(spark, sf_dir).select(F.col("event_id").alias("row_id"), "ts", F.col("value").cast("double").alias("value"), F.get_json_object("props", "$.k").cast("double").alias("k"), F.hour("ts").cast("double").alias("hour"), "event_type")
    scored = features.augment(shaped, scaler, model, 1)
    return ops.run_once(ops.drift(scored), "complete").select(F.col("window_start").cast("timestamp_ntz").alias("window_start"), "z", "n", F.round("mean_b", 5).alias("mean_b"))


@query("stream_user_state", "SELECT user_id, count(*) AS n, max(ts) AS last_seen, round(max(value), 4) AS top FROM events GROUP BY user_id")
def _user_state(spark, sf_dir):
    out = ops.run_once(ops.user_state(_stream(spark, sf_dir)), "update")
    return out.select("user_id", "n", F.col("last_seen").cast("timestamp_ntz").alias("last_seen"), F.round("top", 4).alias("top"))


@query("stream_refresh_centroids")
def _refresh(spark, sf_dir):
    """Centroids moved by each micro-batch of events, older sums decayed."""
    _, scaler, packed, model = _seeded(spark, sf_dir, "traffic")
    df = load(spark, sf_dir, "events")
    shaped = ops.replay([df.filter(F.col("event_id") % 3 == i) for i in range(3)]).select(F.col("event_id").alias("row_id"), F.col("value").cast("double").alias("value"), F.get_json_object("props", "$.k").cast("double").alias("k"), F.hour("ts").cast("double").alias("hour"), "event_type")
    moved = ops.refresh(scaler.pack(shaped, "row_id"), model, [len(scaler.levels[x.name]) for x in _symbolic("traffic")])
    return _centroid_frame(spark, "traffic", scaler, {SEEDED: moved}, False)


@query("read_formats", "SELECT event_type, count(*) AS n, round(sum(value), 2) AS total FROM events GROUP BY event_type UNION ALL SELECT event_type, count(*), round(sum(value), 2) FROM events GROUP BY event_type UNION ALL SELECT event_type, count(*), round(sum(value), 2) FROM events GROUP BY event_type")
def _formats(spark, sf_dir):
    """Events written as CSV, JSON and ORC and read back with an explicit schema."""
    df = load(spark, sf_dir, "events", ["event_id", "event_type", "value"])
    with_path, folder = [], f"{shared_folder(spark).rstrip('/')}/scratch-{uuid4().hex}"
    for fmt in ("csv", "json", "orc"):
        write_any(df, f"{folder}/{fmt}", fmt)
        with_path.append(read_any(spark, f"{folder}/{fmt}", fmt, df.schema).groupBy("event_type").agg(F.count("*").alias("n"), F.round(F.sum("value"), 2).alias("total")))
    out = materialise(with_path[0].unionByName(with_path[1]).unionByName(with_path[2]))
    remove(spark, folder)
    return out


# --- the method, its baselines and the experiments -------------------------------------------------------------------------
for _learner in ("dt", "psvm", "rsvm"):
    for _t in (1, 2, 3):
        for _fixture in ("traffic", "quality", "role") if _t == 1 else ("traffic", "quality"):
            query(f"cac_{_learner}_t{_t}_{_fixture}")(partial(workloads.per_class, _fixture, _learner, _t, False))
for _fixture in ("orders", "part", "emb", "line"):  # other domains and controls: two counts, three folds
    query(f"cac_dt_t1_{_fixture}")(partial(workloads.per_class, _fixture, "dt", 1, False, K=(2, 5), q=3))
for _learner in ("boost", "bag", "nbtree", "dt", "psvm", "rsvm"):
    query(f"baseline_{_learner}_traffic")(partial(workloads.per_class, "traffic", _learner, 0, False))
for _learner in ("dt", "psvm", "rsvm"):
    query(f"baseline_{_learner}_fs_traffic")(partial(workloads.per_class, "traffic", _learner, 0, True))
for _kind in ("pca", "poly", "rbf"):
    query(f"baseline_{_kind}_dt_traffic")(partial(workloads.lifted, "traffic", "dt", _kind))
for _fixture in ("quality", "traffic"):
    query(f"degree_sweep_{_fixture}")(partial(workloads.sweep, _fixture, "psvm", "degree", [2, 3, 4, 5, 6]))
    query(f"gamma_sweep_{_fixture}")(partial(workloads.sweep, _fixture, "rsvm", "gamma", [round(0.1 * i, 1) for i in range(1, 11)]))
query("average_report_traffic")(partial(workloads.average_report, "traffic"))
query("selection_ablation_traffic")(partial(workloads.selection_ablation, "traffic"))
query("cv_scopes_quality")(partial(workloads.scopes, "quality"))
query("measures_traffic")(partial(workloads.measures, "traffic"))
query("crisp_contrast_traffic")(partial(workloads.crisp_contrast, "traffic"))
query("seeding_traffic")(partial(workloads.seeding, "traffic"))
query("run_cost_traffic")(partial(workloads.costs, "traffic"))
query("cac_dt_t1_unknowns")(partial(workloads.per_class, "unknowns", "dt", 1, False))
query("cac_dt_t1_unknowns_either")(partial(workloads.per_class, "unknowns", "dt", 1, False, unknown="either"))
query("k_curve_full_quality")(partial(workloads.k_curve, "quality", workloads.K_FULL))
query("k_curve_full_traffic")(partial(workloads.k_curve, "traffic", workloads.K_FULL))
query("validity_choice_quality")(partial(workloads.validity_choice, "quality", [2, 3, 5]))
query("xor_case")(workloads.xor_case)
query("ablation_unweighted_traffic")(partial(workloads.per_class, "traffic", "dt", 1, False, weighted=False))
query("score_unlabelled_quality")(workloads.score_unlabelled)
query("stream_score")(workloads.stream_score)
query("subsets_quality")(partial(workloads.subsets, "quality"))
query("adaboost_rounds_quality")(partial(workloads.boosting_rounds, "quality"))
query("border_rows_quality")(partial(workloads.border_rows, "quality"))
query("holdout_choice_traffic")(partial(workloads.per_class, "traffic", "dt", 1, False, evaluator="holdout"))
query("zscore_normalised_quality")(partial(workloads.per_class, "quality", "dt", 1, False, normalise="zscore"))


def _vote_curve_sql(name: str, K: tuple[int, ...] = (2, 3, 5), steps: int = 2, q: int = 3) -> str:
    """Candidates for each k: the class vote of each cluster, by stratified cross validation."""
    tags = ["", *(f"_c{k}" for k in K[1:])]
    rows = " UNION ALL ".join(f"SELECT {k} AS k, row_id, min(CASE WHEN r = 1 THEN j END) AS z FROM (SELECT *, row_number() OVER (PARTITION BY row_id ORDER BY round(w, 6) DESC, j) AS r FROM w{t}{steps}) q GROUP BY row_id" for k, t in zip(K, tags, strict=True))
    said = "row_number() OVER (PARTITION BY {by} ORDER BY n DESC, label)"
    return f"""WITH {fixture_cte(name)}, {gain_ctes(name)}, {', '.join(fcm_ctes(name, k, steps, tag=t) for k, t in zip(K, tags, strict=True))}, zs AS ({rows}),
      folds AS (SELECT row_id, label, cast((row_number() OVER (PARTITION BY fine_label ORDER BY {_h('fold')}, row_id) - 1) % {q} AS int) AS fold FROM f), x AS (SELECT zs.k, zs.z, folds.* FROM zs JOIN folds USING (row_id)), fs AS (SELECT unnest(range(0, {q})) AS test),
      votes AS (SELECT * FROM (SELECT *, {said.format(by='k, test, z')} AS r FROM (SELECT k, test, z, label, count(*) AS n FROM x, fs WHERE fold <> test GROUP BY ALL) c) q WHERE r = 1),
      prior AS (SELECT * FROM (SELECT *, {said.format(by='test')} AS r FROM (SELECT test, label, count(*) AS n FROM folds, fs WHERE fold <> test GROUP BY ALL) c) q WHERE r = 1),
      hit AS (SELECT x.k, x.fold, avg(CASE WHEN x.label = coalesce(votes.label, prior.label) THEN 1.0 ELSE 0.0 END) AS s FROM x JOIN prior ON prior.test = x.fold LEFT JOIN votes ON votes.k = x.k AND votes.test = x.fold AND votes.z = x.z GROUP BY x.k, x.fold),
      score AS (SELECT k, avg(s) AS s FROM hit GROUP BY k)
      SELECT cast(k AS int) AS k, round(s, 6) AS score, row_number() OVER (ORDER BY round(s, 12) DESC, k) = 1 AS chosen FROM score"""


for _name in ("quality", "traffic"):
    query(f"vote_k_curve_{_name}", _vote_curve_sql(_name))(partial(workloads.vote_curve, _name))


def _vote_boosting_sql(name: str, rounds: int = 3) -> str:
    columns = [x.name for x in _symbolic(name)]
    out, arms = [f"{fixture_cte(name)}, n0 AS (SELECT count(*) AS n FROM f), r0 AS (SELECT row_id, label, {', '.join(columns)}, 1.0::double AS w FROM f)"], []
    for i in range(rounds):
        for c in columns:
            out.append(f"t{i}_{c} AS (SELECT {c}, label AS said FROM (SELECT {c}, label, row_number() OVER (PARTITION BY {c} ORDER BY round(sum(w), 9) DESC, label) AS r FROM r{i} GROUP BY {c}, label) q WHERE r = 1)")
        errors = " UNION ALL ".join(f"SELECT {j} AS place, '{c}' AS col, sum(CASE WHEN label <> said THEN w ELSE 0 END) / sum(w) AS e FROM r{i} JOIN t{i}_{c} USING ({c})" for j, c in enumerate(columns))
        out.append(f"b{i} AS (SELECT * FROM ({errors}) q ORDER BY round(e, 9), place LIMIT 1)")
        said = "CASE " + " ".join(f"WHEN b{i}.col = '{c}' THEN t{i}_{c}.said" for c in columns) + " END"
        joins = " ".join(f"JOIN t{i}_{c} ON t{i}_{c}.{c} = r.{c}" for c in columns)
        out.append(f"m{i} AS (SELECT r.*, CASE WHEN {said} <> r.label THEN r.w ELSE r.w * e / (1 - e) END AS w2 FROM r{i} r CROSS JOIN b{i} {joins})")
        out.append(f"r{i + 1} AS (SELECT row_id, label, {', '.join(columns)}, w2 * (SELECT n FROM n0) / sum(w2) OVER () AS w FROM m{i})")
        arms.append(f"SELECT {i + 1} AS round, col AS \"column\", round(e, 6) AS error, round(ln((1 - e) / e), 6) AS vote FROM b{i}")
    return f"WITH {', '.join(out)} " + " UNION ALL ".join(arms)


query("vote_boosting_quality", _vote_boosting_sql("quality"))(partial(workloads.vote_boosting, "quality"))


@query("unlabelled_features_quality", f"WITH {fixture_cte('quality')}, {gain_ctes('quality')}, {fcm_ctes('quality', 3, 3, others='label IS NULL')} SELECT row_id, cast(min(CASE WHEN r = 1 THEN j END) AS int) AS z, round(max(w), 5) AS b FROM (SELECT *, row_number() OVER (PARTITION BY row_id ORDER BY round(w, 6) DESC, j) AS r FROM wo) q GROUP BY row_id")
def _unlabelled(spark, sf_dir):
    _, scaler, _, models = _models(spark, sf_dir, "quality", [3], 3)
    rows = fixtures.load(spark, sf_dir, "quality").filter("label IS NULL")
    return features.with_memberships(rows, scaler, models[3]).select("row_id", features.basic_features("p")[0].alias("z"), F.round(F.array_max("p"), 5).alias("b"))


@query("crisp_clusters_quality", f"WITH {fixture_cte('quality')}, {gain_ctes('quality')}, {fcm_ctes('quality', SEEDED, 0)} SELECT row_id, cast(j AS int) AS z FROM (SELECT row_id, j, row_number() OVER (PARTITION BY row_id ORDER BY round(d2, 9), j) AS r FROM d0) q WHERE r = 1")
def _crisp(spark, sf_dir):
    _, _, packed, model = _seeded(spark, sf_dir, "quality")
    return packed.select("row_id", features.crisp_cluster(distance_column(model)).alias("z"))


def _splits_sql(name: str, bins: int = 10) -> str:
    numeric = ", ".join(f"'{x.name}'" for x in fixtures.SPECS[name] if x.kind == "continuous")
    part = lambda n, a: f"coalesce(sum(CASE WHEN {n} > 0 THEN -{n} / {a} * log2({n} / {a}) END), 0)"
    return f"""WITH {fixture_cte(name)}, {gain_ctes(name, bins)}, s AS (SELECT feature, cut, label, sum(CASE WHEN cast(bin AS int) <= cut THEN n ELSE 0 END) AS l, sum(CASE WHEN cast(bin AS int) > cut THEN n ELSE 0 END) AS r FROM (SELECT * FROM c WHERE bin IS NOT NULL AND feature IN ({numeric})) c, (SELECT unnest(range(0, {bins - 1})) AS cut) k GROUP BY feature, cut, label),
      t AS (SELECT *, l + r AS t, sum(l) OVER (PARTITION BY feature, cut) AS la, sum(r) OVER (PARTITION BY feature, cut) AS ra, sum(l + r) OVER (PARTITION BY feature, cut) AS ta FROM s),
      e AS (SELECT feature, cut, {part('t', 'ta')} AS h, {part('l', 'la')} AS hl, {part('r', 'ra')} AS hr, any_value(la) AS la, any_value(ra) AS ra, any_value(ta) AS ta FROM t GROUP BY feature, cut)
      SELECT feature, cast(cut AS int) AS cut, round(h - (la * hl + ra * hr) / ta, 6) AS gain, round((h - (la * hl + ra * hr) / ta) / -(la / ta * log2(la / ta) + ra / ta * log2(ra / ta)), 6) AS gain_ratio FROM e WHERE la > 0 AND ra > 0"""


for _name in ("traffic", "quality"):
    query(f"tree_root_splits_{_name}", _splits_sql(_name))(lambda spark, sf_dir, n=_name: infogain.binary_splits(labelled(spark, sf_dir, n), fixtures.SPECS[n]).select("feature", "cut", F.round("gain", 6).alias("gain"), F.round("gain_ratio", 6).alias("gain_ratio")))
