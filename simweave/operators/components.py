"""Connected components over an edge table, without driver-side graphs."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from simweave.plans.staging import release, stage

#: A node with more edges than this, and than one in HUB_SHARE of all, is a hub. So there are at most HUB_SHARE hubs in a large
#: table and edges / HUB_EDGES in a small one, and their labels are always few enough to broadcast.
HUB_EDGES, HUB_SHARE = 256, 8192


def _with_smallest(edges: DataFrame, low: DataFrame, least: int) -> DataFrame:
    """edges (u, v) with m of low (u, m, n): hubs by broadcast, where their edges are, the others by a shuffle on u."""
    hubs = F.broadcast(low.where(F.col("n") > least).select("u", "m"))
    rest = edges.join(hubs.select("u"), "u", "left_anti").join(low.where(F.col("n") <= least).select("u", "m"), "u")
    return edges.join(hubs, "u").select("u", "v", "m").unionByName(rest.select("u", "v", "m"))


def connected_components(edges: DataFrame, max_rounds: int = 60) -> DataFrame:
    """Smallest reachable node of every node that has an edge.

    edges: columns a, b (long), any direction, duplicates and loops allowed. Returns node, component.
    Alternates two star contractions: every node links its larger neighbours to its smallest one, then
    every node links its smaller neighbours to the smallest. The number of rounds is logarithmic, each
    round is two aggregations and four joins, no neighbour list is ever collected and no hub's edges meet in one task.
    An empty edge table gives an empty result; null ends are ignored. Raises if max_rounds do not suffice.
    """
    given = stage(edges.where("a is not null and b is not null").select(F.greatest("a", "b").alias("u"), F.least("a", "b").alias("v")).distinct(), "edges")
    nodes = given.select(F.explode(F.array("u", "v")).alias("node")).distinct()
    star, done = given.where("u <> v"), []
    for _ in range(max_rounds):
        count = star.count()
        least = max(HUB_EDGES, 2 * count // HUB_SHARE)
        both = star.select("u", "v").union(star.select(F.col("v").alias("u"), F.col("u").alias("v")))
        low = both.groupBy("u").agg(F.least(F.col("u"), F.min("v")).alias("m"), F.count(F.lit(1)).alias("n"))
        up = _with_smallest(both.where("v > u"), low, least)
        large = stage(up.select(F.col("v").alias("u"), F.col("m").alias("v")).where("u <> v").distinct(), "large-star")
        release(*done)
        low = large.groupBy("u").agg(F.min("v").alias("m"), F.count(F.lit(1)).alias("n"))
        linked = _with_smallest(large, low, least)
        small = linked.select(F.col("v").alias("u"), F.col("m").alias("v")).union(low.select("u", F.col("m").alias("v")))
        star = stage(small.where("u <> v").distinct(), "small-star")
        release(large)
        done = [star]
        open_ = star.groupBy("u").agg(F.count(F.lit(1)).alias("n")).where("n > 1").select("u").union(star.join(star.select(F.col("u").alias("v")), "v", "left_semi").select("u"))
        if open_.limit(1).count() == 0:
            break
    else:
        raise RuntimeError(f"components are not complete after {max_rounds} rounds")
    return nodes.join(star.select(F.col("u").alias("node"), F.col("v").alias("c")), "node", "left").select("node", F.coalesce("c", "node").alias("component"))
