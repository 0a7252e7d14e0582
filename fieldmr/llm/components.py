"""Connected components of a large edge table by alternating star contractions."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .runtime import drop_table, materialise


def connected_components(edges: DataFrame, a: str = "a", b: str = "b") -> DataFrame:
    """(node, component) of every node of ``edges``; a component is named by its smallest node.

    Each round sends neighbours to the smallest node of a neighbourhood, first among
    larger nodes, then among smaller ones (published star contraction; the number of
    rounds grows with the logarithm of the diameter).  A hot node is only ever one key of a
    min-aggregate, which combines before its shuffle, and of a join that adaptive
    execution can split; no neighbourhood is collected.  Null nodes, self links and repeated
    links are ignored.
    """
    at = edges.select(F.greatest(a, b).alias("u"), F.least(a, b).alias("v")).where("u > v").distinct()
    at = materialise(at, "stars")
    seen = None
    while True:
        both = at.union(at.select(F.col("v").alias("u"), F.col("u").alias("v")))
        least = both.groupBy("u").agg(F.min("v").alias("m")).select("u", F.least("u", "m").alias("m"))
        large = at.select(F.col("u").alias("w"), F.col("v").alias("u")).join(least, "u").select(F.col("w").alias("u"), F.col("m").alias("v"))
        # the smaller end of each link now points to the least node around it
        large = large.unionByName(least.where("m < u").select("u", F.col("m").alias("v"))).where("u > v").distinct()
        small_least = large.groupBy("u").agg(F.min("v").alias("m"))
        small = large.join(small_least, "u").select(F.col("v").alias("u"), F.col("m").alias("v")).where("u > v")
        new = materialise(small.unionByName(small_least.select("u", F.col("m").alias("v"))).distinct(), "stars")
        now = new.agg(F.count("*"), F.sum(F.xxhash64("u", "v").cast("decimal(38,0)"))).first()
        drop_table(at)
        at = new
        if now == seen:
            break
        seen = now
    roots = at.select(F.col("v").alias("node")).distinct().select("node", F.col("node").alias("component"))
    return at.select(F.col("u").alias("node"), F.col("v").alias("component")).unionByName(roots)
