"""Connected components by alternating star contraction, without the driver holding any link.

Each round replaces every node's links by links to the smallest node it sees, first for larger
neighbours, then for smaller ones. The number of rounds grows with the logarithm of the longest
chain. Groups are only ever reduced by ``min`` (combined before the shuffle), and the joins back
are plain equi-joins that Spark may split where a node is hot."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import discard, materialize


def connected_components(edges: DataFrame, max_rounds: int = 60) -> DataFrame:
    """``edges``: columns u, v of one ordered type. Returns (node, root) for every node that has a
    link to another; root is the smallest node reachable. Links from a node to itself and null ends
    are ignored, links given twice count once. No edges: an empty result."""
    high, low = F.greatest("u", "v"), F.least("u", "v")
    links = materialize(edges.filter(F.col("u") != F.col("v")).select(high.alias("u"), low.alias("v")).distinct())
    for _ in range(max_rounds):
        # done when every node links to one root and no root links on: one small aggregate a node
        ends = links.select(F.col("u").alias("node"), F.lit(1).alias("out"), F.lit(0).alias("root")).unionByName(links.select(F.col("v").alias("node"), F.lit(0).alias("out"), F.lit(1).alias("root")))
        of = ends.groupBy("node").agg(F.sum("out").alias("out"), F.max("root").alias("root"))
        if of.filter("out > 1 or out > 0 and root > 0").isEmpty():
            break
        both = links.unionByName(links.select(F.col("v").alias("u"), F.col("u").alias("v")))
        least = both.groupBy("u").agg(F.min("v").alias("m")).select("u", F.least("u", "m").alias("m"))
        far = both.filter(F.col("v") > F.col("u")).join(least, "u").select(F.col("v").alias("u"), F.col("m").alias("v"))
        far = far.filter(F.col("u") != F.col("v")).distinct()
        near_least = far.groupBy("u").agg(F.min("v").alias("m"))
        pulled = far.join(near_least, "u").filter(F.col("v") != F.col("m")).select(F.col("v").alias("u"), F.col("m").alias("v"))
        new = materialize(pulled.unionByName(near_least.select("u", F.col("m").alias("v"))).distinct())
        discard(links)
        links = new
    else:
        raise RuntimeError(f"components did not settle in {max_rounds} rounds")
    nodes = links.groupBy("u").agg(F.min("v").alias("root")).select(F.col("u").alias("node"), "root")
    return nodes.unionByName(links.select(F.col("v").alias("node"), F.col("v").alias("root")).distinct())
