"""Connected components of an edge table: alternating large-star and small-star steps over DataFrames.

Each step is a partial-aggregated minimum and an equi-join, whose skewed keys Spark can split, so a node with very many
neighbours needs no task of its own. Each round is written to the shared folder; the rounds grow with the logarithm of
the node count.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from wsig.llm import shared


def _with_least(edges: DataFrame, own: bool) -> DataFrame:
    """Edges with the least neighbour (or the node itself, if ``own``) of their first node."""
    least = edges.groupBy("a").agg(F.min("b").alias("m"))
    if own:
        least = least.select("a", F.least("a", "m").alias("m"))
    return edges.join(least.hint("merge"), "a")  # a broadcast would pass through the driver's memory


def components(edges: DataFrame) -> DataFrame:
    """(node, root) for each node of ``edges`` (a, b: long); the root is the component's smallest node."""
    spark = edges.sparkSession
    now, path = shared.settle(edges.where("a <> b").select(F.greatest("a", "b").alias("a"), F.least("a", "b").alias("b")).distinct(), "edges")
    state = None
    while True:
        both = now.select("a", "b").unionByName(now.select(F.col("b").alias("a"), F.col("a").alias("b")))
        large = _with_least(both, own=True).where("b > a").select(F.col("b").alias("a"), F.col("m").alias("b")).distinct()
        mid, mid_path = shared.settle(large, "large-star")
        small = _with_least(mid, own=False)
        out = small.select("a", F.col("m").alias("b")).unionByName(small.where("b <> m").select(F.col("b").alias("a"), F.col("m").alias("b"))).distinct()
        after, after_path = shared.settle(out, "small-star")
        shared.drop(spark, path, mid_path)
        now, path = after, after_path
        before, state = state, now.agg(F.count("*"), F.sum(F.xxhash64("a", "b") % F.lit(1 << 31))).first()
        if before == state:
            break
    return now.select(F.col("a").alias("node"), F.col("b").alias("root")).unionByName(now.select(F.col("b").alias("node"), F.col("b").alias("root")).distinct())
