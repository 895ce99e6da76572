"""Connected components of a distributed edge list, with DataFrame operations alone.

Stars are alternately grown and shrunk: first every node hands its smallest neighbour to its larger ones, then every
node hands it to its smaller ones; a few rounds leave each node joined to the smallest of its component. Neighbours are
only ever reduced to their minimum, so a node with a third of all edges costs a partial aggregate and a join that
Spark can split. Each round is cut off by checkpoint(), which survives lost executors. Rounds go on until the links stay
the same, so that no component is left in parts.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..storage import shared_dir


def _mark(edges: DataFrame) -> tuple:
    return tuple(edges.agg(F.count("*"), F.sum(F.xxhash64("a", "b").cast("decimal(38,0)"))).first())


def components(edges: DataFrame) -> DataFrame:
    """(node, component) for the nodes of edges (a, b), any type with an order; component is the smallest node reachable.

    Self-loops, repeated edges and either direction are allowed; edges with a null are no edges; no edges give no rows;
    other columns aren't read.
    """
    shared_dir(edges.sparkSession)
    real = edges.where("a is not null and b is not null").select("a", "b")
    nodes = real.select(F.col("a").alias("node")).union(real.select("b")).distinct()
    links = real.where("a <> b").select(F.greatest("a", "b").alias("a"), F.least("a", "b").alias("b")).distinct().checkpoint()
    before = _mark(links)
    while before[0]:
        both = links.union(links.select("b", "a"))
        least = both.groupBy("a").agg(F.min("b").alias("m")).select("a", F.least("a", "m").alias("m"))
        large = both.where("b > a").join(least, "a").select(F.col("b").alias("a"), F.col("m").alias("b")).where("a <> b").distinct()
        least = large.groupBy("a").agg(F.min("b").alias("m"))
        small = large.join(least, "a").select("b", "m").where("b <> m").toDF("a", "b").union(least.select("a", "m")).distinct()
        links = small.checkpoint()
        after = _mark(links)
        if after == before:
            break
        before = after
    return nodes.join(links.toDF("node", "component"), "node", "left").select("node", F.coalesce("component", "node").alias("component"))
