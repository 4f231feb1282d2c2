"""Connected components of an edge table by alternating large-star and small-star steps.

Each step is one aggregation and one join; a node with a third of all edges is met by partial aggregation and by joins
whose other side has one row a node. Steps are written to the shared folder, so lineage stays short and a lost
executor costs one step at most. No edges, labels or components reach the driver: only two sums that tell whether a
round changed the edges.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from assocmine.plans.materialize import materialize


def _star(edges: DataFrame, large: bool) -> DataFrame:
    """Link every neighbour to the smallest of the neighbourhood: larger neighbours, or smaller ones with the node itself."""
    if large:
        both = edges.select(F.col("a").alias("u"), F.col("b").alias("v")).unionByName(edges.select(F.col("b").alias("u"), F.col("a").alias("v")))
        least = both.groupBy("u").agg(F.least(F.min("v"), F.col("u")).alias("m"))
        out = both.filter("v > u").join(least, "u").select(F.col("m").alias("a"), F.col("v").alias("b"))
    else:
        down = edges.select(F.greatest("a", "b").alias("u"), F.least("a", "b").alias("v"))
        least = down.groupBy("u").agg(F.min("v").alias("m"))
        joined = down.join(least, "u")
        out = joined.select(F.col("m").alias("a"), F.col("v").alias("b")).unionByName(joined.select(F.col("m").alias("a"), F.col("u").alias("b")))
    return out.filter("a <> b").distinct()


def connected(edges: DataFrame, rounds: int = 100) -> DataFrame:
    """``node`` and ``root`` (its component's smallest node) for every node of an edge table with columns a < b."""
    def state(e: DataFrame) -> tuple:
        row = e.agg(F.count("*"), F.expr("bit_xor(xxhash64(a, b))")).first()
        return row[0], row[1]

    before = state(edges)
    for _ in range(rounds):
        if not before[0]:
            break
        edges = materialize(_star(materialize(_star(edges, True), "large-star"), False), "small-star")
        after = state(edges)
        if after == before:
            break
        before = after
    else:
        raise RuntimeError(f"components have not settled after {rounds} rounds")
    stars = edges.select(F.col("b").alias("node"), F.col("a").alias("root"))
    return stars.unionByName(edges.select(F.col("a").alias("node"), F.col("a").alias("root")).distinct())
