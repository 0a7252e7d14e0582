"""Connected components of crossed cells by alternating star contractions."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .tables import drop, kept


def _hook(edges: DataFrame) -> DataFrame:
    """Larger neighbours of a node move to the least node around it."""
    both = edges.union(edges.select("v", "u"))
    least = both.groupBy("u").agg(F.min("v").alias("m")).select("u", F.least("u", "m").alias("m"))
    moved = edges.select(F.col("u").alias("w"), F.col("v").alias("u")).join(least, "u").select(F.col("w").alias("u"), F.col("m").alias("v"))
    return moved.union(least.where("m < u").select("u", "m")).where("u > v").distinct()


def _shorten(edges: DataFrame) -> DataFrame:
    """Smaller neighbours of a node move to the least of them."""
    least = edges.groupBy("u").agg(F.min("v").alias("m"))
    moved = edges.join(least, "u").select(F.col("v").alias("u"), F.col("m").alias("v")).where("u > v")
    return moved.union(least.select("u", "m")).distinct()


def connected(nodes: DataFrame, links: DataFrame) -> DataFrame:
    """(node, component): a component is named by its least node; the number of rounds grows with the logarithm of the diameter."""
    edges = kept(links.select(F.greatest("a", "b").alias("u"), F.least("a", "b").alias("v")).where("u > v").distinct(), "links")
    seen = None
    while True:
        new = kept(_shorten(_hook(edges)), "links")
        drop(edges)
        edges = new
        now = edges.agg(F.count("*"), F.sum(F.xxhash64("u", "v").cast("decimal(38,0)"))).first()
        if now == seen:
            break
        seen = now
    return nodes.select("node").join(edges.withColumnRenamed("u", "node"), "node", "left").select("node", F.coalesce("v", "node").alias("component"))
