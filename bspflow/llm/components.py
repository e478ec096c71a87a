"""Connected components of links between 64-bit ids, by alternating star contraction on DataFrames.

Each round links every node's larger neighbours to its smallest one, then its smaller neighbours likewise; the
links shrink to stars in a logarithmic number of rounds.  Each round's links are a written table, so a lost
executor costs one round at most.  Hot nodes meet only aggregations with map-side combine and joins Spark can split.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import materialize


def _lowest(pairs: DataFrame, larger: bool) -> DataFrame:
    """``pairs``(u, v): link v to the smallest of u and its neighbours, for v above (below) u."""
    low = pairs.groupBy("u").agg(F.min("v").alias("m")).withColumn("m", F.least("u", "m"))
    joined = pairs.join(low, "u")
    if larger:
        return joined.where("v > u").select(F.col("v").alias("a"), F.col("m").alias("b"))
    return joined.select(F.col("v").alias("a"), F.col("m").alias("b")).unionByName(low.select(F.col("u").alias("a"), F.col("m").alias("b"))).where("a <> b")


def components(links: DataFrame, most_rounds: int = 60) -> DataFrame:
    """``links``(a, b) of longs in any direction -> (node, component), the component being its smallest node.

    Nodes without links don't appear.  Raises if the links have not settled after ``most_rounds``.
    """
    star = materialize(links.where("a <> b").select(F.greatest("a", "b").alias("a"), F.least("a", "b").alias("b")).distinct(), "links")
    told = None
    for _ in range(most_rounds):
        both = star.select(F.col("a").alias("u"), F.col("b").alias("v")).unionByName(star.select(F.col("b").alias("u"), F.col("a").alias("v")))
        large = _lowest(both, larger=True).distinct()
        small = _lowest(large.select(F.col("a").alias("u"), F.col("b").alias("v")), larger=False).distinct()
        star = materialize(small, "links")
        now = star.agg(F.count("*"), F.sum(F.xxhash64("a", "b").cast("decimal(38,0)"))).first()
        if now == told:
            return star.select(F.col("a").alias("node"), F.col("b").alias("component")).unionByName(star.select(F.col("b").alias("node"), F.col("b").alias("component")).distinct())
        told = now
    raise RuntimeError(f"components did not settle in {most_rounds} rounds")
