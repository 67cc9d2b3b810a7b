"""Connected components of a distributed edge list, by alternating large-star and small-star steps."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from fuzzyfeat.session import materialise, release


def _with_least(edges: DataFrame) -> DataFrame:
    """Edges u -> v beside the least neighbour of u.

    u may be hot: its least is pre-aggregated, and since the key of that side is an expression, both sides are dealt anew
    and adaptive execution may split the hot side.
    """
    least = edges.groupBy("u").agg(F.min("v").alias("m")).select((F.col("u") + F.lit(0)).alias("u"), "m")
    return edges.join(least, "u")


def components(links: DataFrame, most: int = 60) -> DataFrame:
    """(node, component): the least node reachable over the links (u, v), for each node that has a link.

    Each step keeps the edge count linear; the number of steps grows with the logarithm of the longest path.
    """
    edges = materialise(links.select(F.greatest("u", "v").alias("u"), F.least("u", "v").alias("v")).filter("u > v").distinct())
    before = None
    for _ in range(most):
        both = edges.unionByName(edges.select(F.col("v").alias("u"), F.col("u").alias("v")))
        large = _with_least(both).filter("v > u").select(F.col("v").alias("u"), F.least("m", "u").alias("v")).distinct()
        stars = _with_least(large).select(F.explode(F.array(F.struct(F.col("u"), F.col("m").alias("v")), F.struct(F.col("v").alias("u"), F.col("m").alias("v")))).alias("e"))
        older, edges = edges, materialise(stars.select("e.u", "e.v").filter("u > v").distinct())
        release(older)
        state = edges.agg(F.count("*"), F.sum(F.xxhash64("u", "v").cast("decimal(38,0)"))).first()
        if state == before:
            roots = edges.select(F.col("v").alias("node"), F.col("v").alias("component")).distinct()
            return edges.select(F.col("u").alias("node"), F.col("v").alias("component")).unionByName(roots)
        before = state
    raise RuntimeError("components did not settle")
