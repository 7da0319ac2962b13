"""Connected components of an edge table, smallest member as label.

Large-star and small-star rounds, each written to the shared folder, until one changes nothing. Nothing but
a count per round comes to the driver; every aggregation combines in the map tasks first, and the adaptive
plan splits the join at a node of very many edges.

Defined results: loops and repeated edges change nothing; null ends have no edge; nodes without an edge to
another are not listed; an empty table gives an empty result.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from pantry.session import discard, materialize


def _star(edges: DataFrame, large: bool) -> DataFrame:
    """One round on edges (u, v), v < u: hang each neighbourhood on its least member."""
    if large:
        both = edges.select("u", "v").union(edges.select(F.col("v").alias("u"), F.col("u").alias("v")))
        least = both.groupBy("u").agg(F.min("v").alias("m")).select("u", F.least("u", "m").alias("m"))
        hung = both.where(F.col("v") > F.col("u")).join(least, "u").select(F.col("v").alias("u"), F.col("m").alias("v"))
    else:
        least = edges.groupBy("u").agg(F.min("v").alias("m"))
        hung = edges.join(least, "u").select(F.col("v").alias("u"), F.col("m").alias("v")).union(least.select("u", F.col("m").alias("v")))
    return hung.where(F.col("u") != F.col("v")).distinct()


def components(edges: DataFrame) -> DataFrame:
    """(node, component) of every node with an edge, from edges (a, b)."""
    now = edges.where(F.col("a") != F.col("b")).select(F.greatest("a", "b").alias("u"), F.least("a", "b").alias("v")).distinct()
    now = materialize(now, "cc")
    mark = lambda t: t.agg(F.count("*"), F.sum(F.xxhash64("u", "v").cast("decimal(20,0)"))).first()
    before = mark(now)
    while True:  # each round at least halves the longest way to a component's least node
        old, now = now, materialize(_star(_star(now, True), False), "cc")
        discard(old)
        after = mark(now)
        if tuple(after) == tuple(before):
            break
        before = after
    roots = now.select(F.col("v").alias("node"), F.col("v").alias("component"))
    return now.select(F.col("u").alias("node"), F.col("v").alias("component")).union(roots).distinct()
