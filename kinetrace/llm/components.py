"""Connected components of an edge table by repeated contraction, all on the cluster."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from kinetrace.llm.storage import written


def components(edges: DataFrame) -> DataFrame:
    """(node, root) of every node of `edges` (a, b): nodes of one component share the root, one of them.

    In each round every node moves to the neighbour (or itself) of the least priority, a hash that
    differs by round, so a constant share of the nodes of any graph, chains and stars included, goes
    away in a round. Edges follow the moves; a component is done when it has no edge left.
    """
    hops, turn = [], 0
    edges = written(edges.where("a <> b").select(F.least("a", "b").alias("a"), F.greatest("a", "b").alias("b")).distinct(), "edges")
    while not edges.isEmpty():
        priority = lambda c: F.struct(F.xxhash64(c, F.lit(turn)).alias("p"), F.col(c).alias("n"))
        both = edges.union(edges.select("b", "a")).select("a", priority("b").alias("other"))
        least = both.groupBy("a").agg(F.min("other").alias("other"))
        hop = written(least.select(F.col("a").alias("node"), F.least("other", priority("a"))["n"].alias("to")), "hops")
        hops.append(hop)
        moved = edges.join(hop.select(F.col("node").alias("a"), F.col("to").alias("x")), "a")
        moved = moved.join(hop.select(F.col("node").alias("b"), F.col("to").alias("y")), "b").where("x <> y")
        edges = written(moved.select(F.least("x", "y").alias("a"), F.greatest("x", "y").alias("b")).distinct(), "edges")
        turn += 1
    if not hops:
        return edges.select(F.col("a").alias("node"), F.col("b").alias("root"))
    labels = hops[0].select("node", F.col("to").alias("root"))
    for hop in hops[1:]:
        step = hop.select(F.col("node").alias("root"), "to")
        labels = labels.join(step, "root", "left").select("node", F.coalesce("to", "root").alias("root"))
    return labels
