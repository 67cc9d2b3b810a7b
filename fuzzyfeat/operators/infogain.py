"""Information gain and its relatives, from one pass of pre-aggregated counts."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from fuzzyfeat.plans.spec import Feature


def bins_of(df: DataFrame, spec: list[Feature], bins: int = 10) -> dict[str, Column]:
    """The bin of each feature: equal widths between the extremes of a continuous one, levels of the others; null if unknown."""
    continuous = [f.name for f in spec if f.kind == "continuous"]
    row = df.agg(*(a for c in continuous for a in (F.min(c), F.max(c)))).first() if continuous else ()
    out = {}
    for f in spec:
        if f.kind == "continuous":
            low, high = row[2 * continuous.index(f.name)], row[2 * continuous.index(f.name) + 1]
            width = (high - low) if low is not None else 0
            out[f.name] = F.when(F.col(f.name).isNotNull(), F.least(F.floor((F.col(f.name) - low) * bins / width), F.lit(bins - 1)).cast("string") if width else F.lit("0"))
        else:
            out[f.name] = F.col(f.name).cast("string")
    return out


def counts_table(df: DataFrame, spec: list[Feature], label: str, bins: int = 10) -> DataFrame:
    """(feature, bin, label, n): every feature of a row in one pass, partially summed before it is dealt out."""
    binned = bins_of(df, spec, bins)
    each = F.explode(F.array(*(F.struct(F.lit(f.name).alias("feature"), binned[f.name].alias("bin")) for f in spec))).alias("e")
    return df.filter(F.col(label).isNotNull()).select(F.col(label).alias("label"), each).groupBy("e.feature", "e.bin", "label").agg(F.count("*").alias("n"))


def _entropy(n: str, total: str) -> Column:
    return F.sum(-F.col(n) / F.col(total) * F.log2(F.col(n) / F.col(total)))


def information_gain(df: DataFrame, spec: list[Feature], label: str = "label", bins: int = 10) -> DataFrame:
    """(feature, gain, gain_ratio, sym_uncert), base 2; unknown values form no bin and the gain is scaled by the known share."""
    counts = counts_table(df, spec, label, bins).withColumn("all", F.sum("n").over(Window.partitionBy("feature")))
    known = counts.filter("bin IS NOT NULL").withColumn("known", F.sum("n").over(Window.partitionBy("feature")))
    by_label = known.groupBy("feature", "label").agg(F.sum("n").alias("n"), F.first("known").alias("known"), F.first("all").alias("all"))
    class_part = by_label.groupBy("feature").agg(_entropy("n", "known").alias("hy"), F.first("known").alias("known"), F.first("all").alias("all"))
    by_bin = known.withColumn("m", F.sum("n").over(Window.partitionBy("feature", "bin"))).groupBy("feature", "bin").agg(_entropy("n", "m").alias("h"), F.first("m").alias("m"), F.first("known").alias("known"))
    bin_part = by_bin.groupBy("feature").agg(F.sum(F.col("m") / F.col("known") * F.col("h")).alias("rest"), _entropy("m", "known").alias("hf"))
    both = class_part.join(bin_part, "feature")
    gain = (F.col("hy") - F.col("rest")) * F.col("known") / F.col("all")
    return both.select("feature", F.greatest(gain, F.lit(0.0)).alias("gain"), F.coalesce(F.try_divide(gain, F.when(F.col("hf") > 1e-12, F.col("hf"))), F.lit(0.0)).alias("gain_ratio"), F.coalesce(F.try_divide(2 * gain, F.when(F.col("hf") + F.col("hy") > 1e-12, F.col("hf") + F.col("hy"))), F.lit(0.0)).alias("sym_uncert"))


def gains(df: DataFrame, spec: list[Feature], label: str = "label", bins: int = 10) -> dict[str, float]:
    return {r["feature"]: r["gain"] for r in information_gain(df, spec, label, bins).collect()}


def pair_uncertainty(df: DataFrame, spec: list[Feature], bins: int = 10, label: str | None = "label") -> DataFrame:
    """(f, g, su): symmetrical uncertainty of every pair of features, and with the label as a feature of that name if given."""
    binned = bins_of(df, spec, bins) | ({label: F.col(label)} if label else {})
    names = sorted(binned)
    pairs = F.explode(F.array(*(F.struct(F.lit(a).alias("f"), F.lit(b).alias("g"), binned[a].cast("string").alias("a"), binned[b].cast("string").alias("b")) for i, a in enumerate(names) for b in names[i + 1 :]))).alias("p")
    rows = (df.filter(F.col(label).isNotNull()) if label else df).select(pairs).select("p.*").filter("a IS NOT NULL AND b IS NOT NULL").groupBy("f", "g", "a", "b").agg(F.count("*").alias("n"))
    return uncertainty(rows, "f", "g")


def uncertainty(rows: DataFrame, *keys: str) -> DataFrame:
    """(keys, su) from counts (keys, a, b, n) of the value pairs of two columns each."""
    rows = rows.withColumn("t", F.sum("n").over(Window.partitionBy(*keys)))
    joint = rows.groupBy(*keys).agg(_entropy("n", "t").alias("hj"))
    one = rows.groupBy(*keys, "a").agg(F.sum("n").alias("n"), F.first("t").alias("t")).groupBy(*keys).agg(_entropy("n", "t").alias("ha"))
    two = rows.groupBy(*keys, "b").agg(F.sum("n").alias("n"), F.first("t").alias("t")).groupBy(*keys).agg(_entropy("n", "t").alias("hb"))
    return joint.join(one, list(keys)).join(two, list(keys)).select(*keys, F.coalesce(F.try_divide(2 * (F.col("ha") + F.col("hb") - F.col("hj")), F.when(F.col("ha") + F.col("hb") > 1e-12, F.col("ha") + F.col("hb"))), F.lit(0.0)).alias("su"))


def binary_splits(df: DataFrame, spec: list[Feature], label: str = "label", bins: int = 10) -> DataFrame:
    """(feature, cut, gain, gain_ratio) of each threshold between bins of the continuous features: the root level of a tree, from one pass of counts."""
    numeric = [f for f in spec if f.kind == "continuous"]
    counts = counts_table(df, numeric, label, bins).filter("bin IS NOT NULL").select("feature", F.col("bin").cast("int").alias("bin"), "label", "n")
    sides = counts.select("feature", "label", "n", F.explode(F.sequence(F.lit(0), F.lit(bins - 2))).alias("cut"), "bin").groupBy("feature", "cut", "label").agg(F.sum(F.when(F.col("bin") <= F.col("cut"), F.col("n")).otherwise(0)).alias("l"), F.sum(F.when(F.col("bin") > F.col("cut"), F.col("n")).otherwise(0)).alias("r"))
    whole = sides.withColumn("t", F.col("l") + F.col("r")).withColumns({f"{c}a": F.sum(c).over(Window.partitionBy("feature", "cut")) for c in ("l", "r", "t")})
    part = lambda n, a: F.coalesce(F.sum(F.when(F.col(n) > 0, -F.col(n) / F.col(a) * F.log2(F.col(n) / F.col(a)))), F.lit(0.0))
    made = whole.groupBy("feature", "cut").agg(part("t", "ta").alias("h"), part("l", "la").alias("hl"), part("r", "ra").alias("hr"), F.first("la").alias("la"), F.first("ra").alias("ra"), F.first("ta").alias("ta")).filter("la > 0 AND ra > 0")
    gain = F.col("h") - (F.col("la") * F.col("hl") + F.col("ra") * F.col("hr")) / F.col("ta")
    split = -(F.col("la") / F.col("ta") * F.log2(F.col("la") / F.col("ta")) + F.col("ra") / F.col("ta") * F.log2(F.col("ra") / F.col("ta")))
    return made.select("feature", "cut", gain.alias("gain"), (gain / split).alias("gain_ratio"))
