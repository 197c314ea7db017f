"""Relational helpers around bags: repeatable samples, filters by key sets, ranks, histograms, purity, trees."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F


def sample_bags(bags: DataFrame, k: int, salt: int = 0) -> DataFrame:
    """Whole bags, one of k by a hash of the id: the same ones in every table and run."""
    return bags.where(F.pmod(F.xxhash64(F.lit(salt), F.col("bag_id").cast("long")), F.lit(k)) == 0)


def restrict_to(bags: DataFrame, keys: DataFrame, on: str = "elem") -> DataFrame:
    """Rows whose key is in a table."""
    return bags.join(keys.select(on).distinct(), on, "left_semi").select(*bags.columns)


def exclude(bags: DataFrame, keys: DataFrame, on: str = "elem") -> DataFrame:
    """Rows whose key isn't in a table, such as stop words."""
    return bags.join(keys.select(on).distinct(), on, "left_anti").select(*bags.columns)


def filter_bags(bags: DataFrame, least: float = 0.0, elements: int = 1) -> DataFrame:
    """Bags of at least so much weight and so many elements."""
    kept = bags.groupBy("bag_id").agg(F.sum("weight").alias("total"), F.count("*").alias("n")).where((F.col("total") >= least) & (F.col("n") >= elements))
    return bags.join(kept.select("bag_id"), "bag_id", "left_semi").select(*bags.columns)


def ranks(bags: DataFrame) -> DataFrame:
    """Every kind of rank of an element by weight within its bag."""
    by = Window.partitionBy("bag_id").orderBy(F.desc("weight"))
    tie = Window.partitionBy("bag_id").orderBy(F.desc("weight"), "elem")
    return bags.select("bag_id", "elem", F.row_number().over(tie).alias("nth"), F.rank().over(by).alias("rank"), F.dense_rank().over(by).alias("dense"), F.ntile(4).over(tie).alias("quarter"), F.percent_rank().over(by).alias("share"))


def histogram(bags: DataFrame, low: float, high: float, bins: int) -> DataFrame:
    """(bin, n) of weights; bin 0 lies under ``low``, bin ``bins`` + 1 at ``high`` and over."""
    return bags.groupBy(F.expr(f"width_bucket(weight, {low!r}D, {high!r}D, {bins})").alias("bin")).agg(F.count("*").alias("n"))


def purity(clusters: DataFrame, labels: DataFrame) -> DataFrame:
    """(clusters, nodes, pure): how many labelled nodes carry the commonest label of their cluster."""
    cells = clusters.join(labels, "node").groupBy("cluster", "label").agg(F.count("*").alias("n"))
    best = cells.groupBy("cluster").agg(F.max("n").alias("best"), F.sum("n").alias("n"))
    return best.agg(F.count("*").alias("clusters"), F.sum("n").alias("nodes"), F.sum("best").alias("pure"))


def tree_bags(nodes: DataFrame, depth: int) -> DataFrame:
    """(bag_id, elem, weight): each tree of (tree, node, parent, label) as the bag of its downward label paths of up to ``depth`` nodes.

    Similar trees, and forests, share many paths. A level of the tree is a join; ``depth`` bounds them.
    """
    paths = nodes.select("tree", "node", F.col("label").cast("string").alias("path"))
    out, level = paths, paths
    for _ in range(depth - 1):
        down = nodes.select("tree", F.col("parent").alias("up"), F.col("node").alias("child"), F.col("label").cast("string").alias("more"))
        level = level.join(down, (level["tree"] == down["tree"]) & (F.col("node") == F.col("up"))).select(level["tree"], F.col("child").alias("node"), F.concat_ws("/", "path", "more").alias("path"))
        out = out.unionByName(level)
    return out.groupBy(F.col("tree").alias("bag_id"), F.xxhash64("path").alias("elem")).agg(F.count("*").cast("double").alias("weight"))


def changes(time: Column, by: str) -> dict[str, Column]:
    """Lag, lead, first, last and second value of a time within its key."""
    order = Window.partitionBy(by).orderBy(time)
    whole = order.rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing)
    return {"before": F.lag(time).over(order), "after": F.lead(time).over(order), "first": F.first(time).over(whole), "last": F.last(time).over(whole), "second": F.nth_value(time, 2).over(whole)}
