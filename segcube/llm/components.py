"""Connected components of a graph given as a table of edges, with DataFrame operations only.

Alternating large-star and small-star steps (each rewires a node's neighbours to its smallest one) until no edge
changes; the number of rounds grows with the logarithm of the graph's size.  A step is one pre-aggregated
``min`` per node and one equi-join back, so a hub with a third of all edges is combined before the shuffle and its
join is split by adaptive execution.  Each round is written to the shared folder, so its lineage is short and no
round is computed twice.  Node ids may be of any orderable type.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from segcube.llm import shared


def _star(edges: DataFrame, large: bool) -> DataFrame:
    """One step over edges (a, b): each node's neighbours on one side are tied to the smallest of its neighbourhood."""
    both = edges.select(F.col("a").alias("u"), F.col("b").alias("v"))
    if large:
        both = both.unionByName(edges.select(F.col("b").alias("u"), F.col("a").alias("v")))
    else:
        both = both.select(F.greatest("u", "v").alias("u"), F.least("u", "v").alias("v"))
    # a plain table, so that a hub can be split in the join
    least = shared.materialised(both.groupBy("u").agg(F.min("v").alias("m")).select("u", F.least("u", "m").alias("m")), "least")
    tied = both.join(least, "u")
    if large:
        out = tied.filter(F.col("v") > F.col("u")).select(F.col("v").alias("a"), F.col("m").alias("b"))
    else:
        out = tied.select(F.col("v").alias("a"), F.col("m").alias("b")).unionByName(least.select(F.col("u").alias("a"), F.col("m").alias("b")))
    return out.filter(F.col("a") != F.col("b")).distinct()


def components(edges: DataFrame, a: str = "a", b: str = "b") -> DataFrame:
    """``node, component``: every node that has an edge, with the smallest node that it can reach."""
    now = edges.select(F.col(a).alias("a"), F.col(b).alias("b")).filter(F.col("a") != F.col("b"))
    now = shared.materialised(now.select(F.greatest("a", "b").alias("a"), F.least("a", "b").alias("b")).distinct(), "edges")
    digest = _digest(now)
    while digest[0]:
        now = shared.materialised(_star(_star(now, large=True), large=False), "edges")
        digest, before = _digest(now), digest
        if digest == before:
            break
    stars = now.select(F.col("a").alias("node"), F.col("b").alias("component"))
    return stars.unionByName(stars.select(F.col("component").alias("node"), "component").distinct())


def _digest(edges: DataFrame) -> tuple:
    row = edges.agg(F.count(F.lit(1)), F.bit_xor(F.xxhash64("a", "b")), F.sum(F.xxhash64("b", "a").cast("decimal(38,0)"))).first()
    return tuple(row)
