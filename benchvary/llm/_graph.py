"""Connected components of a table of links, by alternating star contraction; nothing is collected."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from benchvary.session import forget, materialize


def _with_least(edges: DataFrame, least: Column) -> DataFrame:
    """edges(u, v) with m, the least neighbour of u by the aggregate given.

    The join key is u with its bits turned, so the minima are dealt anew and both sides of the join are plain shuffles: adaptive execution
    can then split a hub's links over many tasks.
    """
    low = edges.groupBy("u").agg(least.alias("m")).select(F.bitwise_not("u").alias("w"), "m")
    return edges.withColumn("w", F.bitwise_not("u")).join(low, "w").drop("w")


def _unfinished(edges: DataFrame) -> bool:
    """Whether a node hangs on two others, or on one that hangs itself."""
    zero, one = F.lit(0), F.lit(1)
    ends = edges.select(F.col("u").alias("x"), one.alias("up"), zero.alias("down")).unionByName(edges.select(F.col("v").alias("x"), zero.alias("up"), one.alias("down")))
    per = ends.groupBy("x").agg(F.sum("up").alias("up"), F.max("down").alias("down"))
    return bool(per.agg(F.bool_or((F.col("up") > 1) | ((F.col("up") > 0) & (F.col("down") > 0))).alias("x")).first()["x"])


def components(links: DataFrame, max_rounds: int = 40, whole: bool = True) -> DataFrame:
    """(node, component) for every end of links(a, b); component is the smallest node that can be reached.

    Each round hangs every node and its larger neighbours on its smallest neighbour, then every node's smaller
    neighbours too; links never grow in number and rounds are logarithmic. Minima are pre-aggregated before each
    shuffle, and each round is written to the shared folder, so a lost executor costs no lineage. With whole=False it
    ends after max_rounds, and component is then some node that can be reached. Null ends and self-links are ignored.
    An empty table gives an empty result.
    """
    edges = materialize(links.select(F.greatest("a", "b").alias("u"), F.least("a", "b").alias("v")).where("u > v").distinct(), "edges")
    for k in range(max_rounds):
        both = edges.unionByName(edges.select(F.col("v").alias("u"), F.col("u").alias("v")))
        large = _with_least(both, F.least(F.min("v"), F.first("u"))).where("v > u").select(F.col("v").alias("u"), F.col("m").alias("v"))
        small = _with_least(large, F.min("v"))
        new = small.select("u", F.col("m").alias("v")).unionByName(small.where("v != m").select(F.col("v").alias("u"), F.col("m").alias("v"))).where("u > v").distinct()
        edges, old = materialize(new, "edges"), edges
        forget(old)
        if k + 1 < max_rounds or whole:
            if not _unfinished(edges):
                break
    else:
        if whole:
            raise RuntimeError("components did not converge")
    hung = edges.groupBy("u").agg(F.min("v").alias("v"))
    roots = hung.select(F.col("v").alias("node"), F.col("v").alias("component")).distinct()
    if not whole:  # a node that others hang on may hang itself
        roots = roots.join(hung.select(F.col("u").alias("node")), "node", "left_anti")
    return hung.select(F.col("u").alias("node"), F.col("v").alias("component")).unionByName(roots)
