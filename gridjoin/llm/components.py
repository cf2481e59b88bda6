"""Connected components of an edge table, by alternating stars; no step sees more than an edge list."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import drop_stored, stored


def connected_components(edges: DataFrame, name: str = "components") -> DataFrame:
    """edges: a, b (of any type with an order). Returns node, comp (the least node of its component) for every node on an edge.

    Each round points every node's larger neighbours at the least neighbour, then its smaller ones. Both are minima with partial
    aggregates and joins that AQE can split. Each round is a written table, so a lost executor repeats its own tasks only.
    """
    edges = stored(edges.select(F.greatest("a", "b").alias("a"), F.least("a", "b").alias("b")).where("a <> b").distinct(), name)
    while True:
        both = edges.unionByName(edges.select(F.col("b").alias("a"), F.col("a").alias("b")))
        least = both.groupBy("a").agg(F.least(F.col("a"), F.min("b")).alias("m"))
        large = both.where("b > a").join(least, "a").select(F.col("b").alias("a"), F.col("m").alias("b")).where("a <> b").distinct()
        low = large.groupBy("a").agg(F.min("b").alias("m"))
        pairs = large.join(low, "a")
        small = pairs.select(F.col("b").alias("a"), F.col("m").alias("b")).unionByName(pairs.select("a", F.col("m").alias("b"))).where("a <> b").distinct()
        new = stored(small, name)
        sign = [F.count("*"), F.sum(F.xxhash64("a", "b").cast("decimal(38,0)"))]
        same = edges.agg(*sign).first() == new.agg(*sign).first()
        drop_stored(edges)
        edges = new
        if same:
            break
    return edges.select(F.col("a").alias("node"), F.col("b").alias("comp")).unionByName(edges.select(F.col("b").alias("node"), F.col("b").alias("comp")).distinct())
