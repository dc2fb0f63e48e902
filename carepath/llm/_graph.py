"""Connected components of a graph of links, by alternating stars.

Each round hangs every neighbour above a node onto the node's smallest neighbour, then every neighbour below onto the
smallest one; trees flatten in about log rounds. A round is two aggregations and joins, written to the shared folder, so
that lineage stays short. Links are rows throughout: none are collected.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, Observation
from pyspark.sql import functions as F

from carepath.llm._shared import written


def components(links: DataFrame, known: DataFrame | None = None, most_rounds: int = 60) -> DataFrame:
    """(node, component) for every node in a link (a, b) or in ``known`` components; component: the smallest node reachable."""
    edges = links.select(F.greatest("a", "b").alias("u"), F.least("a", "b").alias("v"))
    if known is not None:
        edges = edges.unionByName(known.select(F.col("node").alias("u"), F.col("component").alias("v")))
    edges = edges.filter("u <> v").distinct()
    before = None
    for _ in range(most_rounds):
        seen = Observation()
        edges = written(_star(_star(edges, True), False).observe(seen, F.count("*").alias("n"), F.sum(F.col("v").cast("decimal(38,0)")).alias("s"), F.sum(F.xxhash64("u", "v").cast("decimal(38,0)")).alias("h")), "edges")
        now = seen.get
        if now == before:
            break
        before = now
    else:
        raise RuntimeError("components did not settle")
    return edges.select(F.col("u").alias("node"), F.col("v").alias("component")).unionByName(edges.select(F.col("v").alias("node"), F.col("v").alias("component")).distinct())


def _star(edges: DataFrame, above: bool) -> DataFrame:
    """``above``: each node's larger neighbours go to its smallest one or itself; else its smaller neighbours and itself do."""
    both = edges.unionByName(edges.select(F.col("v").alias("u"), F.col("u").alias("v"))) if above else edges
    least = both.groupBy("u").agg(F.min("v").alias("m"))
    least = least.withColumn("m", F.least("m", "u"))
    moved = both.join(least, "u").filter(F.col("v") > F.col("u") if above else F.col("v") != F.col("m")).select(F.col("v").alias("u"), F.col("m").alias("v"))
    if not above:
        moved = moved.unionByName(least.select("u", F.col("m").alias("v")))
    return moved.filter("u <> v").distinct()
