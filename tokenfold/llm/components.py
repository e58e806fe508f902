"""Connected components of an edge table, by alternating stars.

Each round rewires every node to the least node of its neighbourhood, first among
its larger neighbours, then among its smaller ones, until all edges are stars. A
round aggregates before it shuffles; nothing is gathered on the driver but counts.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import settle


#: A node with more than one in HUB_SHARE of all edge ends is a hub; there are at most HUB_SHARE of them.
HUB_SHARE = 1000


def _rewired(edges: DataFrame, ends: int, smaller: bool) -> DataFrame:
    """Point neighbours of each u to the least of its neighbourhood, and u too if asked. edges: u, v.

    What a hub's edges are joined with is sent to where they lie, so no task gathers them.
    """
    least = edges.groupBy("u").agg(F.min("v").alias("m"), F.count("*").alias("n")).withColumn("m", F.least("u", "m"))
    hub = F.col("n") * HUB_SHARE >= ends
    hubs, others = least.filter(hub).select("u", "m"), least.filter(~hub).select("u", "m")
    moved = edges if smaller else edges.filter("v > u")
    met = moved.join(F.broadcast(hubs), "u").unionByName(moved.join(F.broadcast(hubs.select("u")), "u", "left_anti").join(others, "u"))
    out = met.select(F.col("v").alias("a"), F.col("m").alias("b"))
    if smaller:
        out = out.union(least.select("u", "m"))
    return out.filter("a <> b").distinct()


def components(edges: DataFrame, a: str = "a", b: str = "b") -> DataFrame:
    """Nodes with a neighbour and the least node of their component: node, root. Loops and nulls are ignored."""
    now = settle(edges.select(F.greatest(a, b).alias("a"), F.least(a, b).alias("b")).filter("a <> b").distinct(), "edges")
    mark, count = None, now.count()
    while True:
        # large star: of each node, the larger neighbours go to the least
        both = now.select(F.col("a").alias("u"), F.col("b").alias("v")).union(now.select("b", "a"))
        large = settle(_rewired(both, 2 * count, False), "large")
        # small star: of each node, the smaller neighbours and itself go to the least
        now = settle(_rewired(large.select(F.col("a").alias("u"), F.col("b").alias("v")), count, True), "small")
        seen = now.agg(F.count("*"), F.sum(F.xxhash64("a", "b").cast("decimal(38,0)"))).first()
        if seen == mark:
            return now.select(F.col("a").alias("node"), F.col("b").alias("root")).union(now.select("b", "b").distinct())
        mark, count = seen, seen[0]
