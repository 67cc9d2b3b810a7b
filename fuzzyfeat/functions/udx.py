"""The same computations as SQL functions and a table function."""

from __future__ import annotations

from pyspark.sql import SparkSession
from pyspark.sql.functions import udtf


def register(spark: SparkSession) -> None:
    """fuzzy_membership(d, alpha), cluster_id(p) and cluster_strength(p) over arrays, and the table function memberships_rows(p)."""
    # an argument's expression is put wherever the body names it: as an array's only element it is computed once a row
    once = lambda value, name, of: f"get(transform(array({value}), {name} -> {of}), 0)"
    shares = once("aggregate(w, 0D, (s, y) -> s + y)", "t", "transform(w, x -> x / t)")
    powers = "CASE WHEN m <= 0 THEN transform(v, x -> CASE WHEN x <= 0 THEN 1D ELSE 0D END) ELSE transform(v, x -> pow(x / m, -1 / (alpha - 1))) END"
    spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION fuzzy_membership(d ARRAY<DOUBLE>, alpha DOUBLE) RETURNS ARRAY<DOUBLE> RETURN {once('d', 'v', once('array_min(v)', 'm', once(powers, 'w', shares)))}")
    largest = once("transform(p, x -> round(x, 6))", "r", "{}").format
    spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION cluster_id(p ARRAY<DOUBLE>) RETURNS INT RETURN {largest('cast(array_position(r, array_max(r)) - 1 AS INT)')}")
    spark.sql("CREATE OR REPLACE TEMPORARY FUNCTION cluster_strength(p ARRAY<DOUBLE>) RETURNS DOUBLE RETURN array_max(transform(p, x -> round(x, 6)))")

    @udtf(returnType="j int, w double")
    class MembershipRows:
        def eval(self, p):
            for j, w in enumerate(p or []):
                yield j, w

    spark.udtf.register("memberships_rows", MembershipRows)
