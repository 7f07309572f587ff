"""Connected components by alternating large-star and small-star steps."""

from __future__ import annotations

from pyspark.sql import DataFrame, functions as F

from .shared import join_hot, settle, tidy, unsized


def components(links: DataFrame, a: str = "a", b: str = "b") -> DataFrame:
    """(node, component) for every node of a link between different nodes; the component is its smallest node.

    Each step keeps one row per link at most. A large star hands a node's larger neighbours to its smallest one, a small star
    its smaller neighbours; both end when the links form stars around smallest nodes. Nodes with very many links are joined apart.
    Links with a null end, loops and repeats are ignored.
    """
    ends = links.select(F.greatest(a, b).alias("u"), F.least(a, b).alias("v")).where(F.col(a).isNotNull() & F.col(b).isNotNull() & (F.col("u") != F.col("v")))
    edges = unsized(settle(ends.distinct()))
    while True:
        parents = edges.groupBy("u").agg(F.count(F.lit(1)).alias("n"))
        nested = edges.select(F.col("v").alias("u")).distinct().join(edges.select("u"), "u", "left_semi")
        if parents.where("n > 1").isEmpty() and nested.isEmpty():
            break
        both = settle(edges.unionByName(edges.select(F.col("v").alias("u"), F.col("u").alias("v"))))
        lowest = settle(both.groupBy("u").agg(F.least(F.min("v"), F.col("u")).alias("m"), F.count(F.lit(1)).alias("n")))
        large = join_hot(both, lowest, ["u"], "n").where("v > u").select(F.col("v").alias("u"), F.col("m").alias("v")).distinct()
        large = settle(large.where("u != v"))
        lowest = settle(large.groupBy("u").agg(F.min("v").alias("m"), F.count(F.lit(1)).alias("n")))
        met = join_hot(large, lowest, ["u"], "n")
        small = met.select(F.col("v").alias("u"), F.col("m").alias("v")).where("u != v").unionByName(lowest.select("u", F.col("m").alias("v")))
        edges = unsized(settle(small.distinct()))
        del both, lowest, large, met, small, parents, nested
        tidy(links.sparkSession)
    return edges.select(F.col("u").alias("node"), F.col("v").alias("component")).unionByName(edges.select(F.col("v").alias("node"), F.col("v").alias("component")).distinct())
