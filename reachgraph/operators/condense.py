"""Strongly connected components by joins, for graphs that no task holds."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from reachgraph.operators.partition import vertices
from reachgraph.session import materialise


def _trimmed(edges: DataFrame) -> DataFrame:
    """Edges without those whose source nothing leads to or whose target leads nowhere, until none is left."""
    now, n = edges, edges.count()
    while n:
        after = now.join(now.select(F.col("t").alias("s")).distinct(), "s", "left_semi")
        after = materialise(after.join(after.select(F.col("s").alias("t")).distinct(), "t", "left_semi").select("s", "t"), "trimmed")
        m = after.count()
        if m == n:
            break
        now, n = after, m
    return now


def strong_components(edges: DataFrame) -> DataFrame:
    """(v, scc): the smallest vertex of the strongly connected component of every vertex of edges (s, t).

    Vertices that lie on no cycle are trimmed in layers. In what is left the
    smallest vertex that leads to a vertex is its colour; a colour's own vertex
    and all of that colour that lead back to it are one component, which is
    taken out. Each step is a join and a partial aggregation, so a hub is
    pre-aggregated; the number of rounds grows with the longest shortest path.
    """
    all_edges = materialise(edges.where("s is not null and t is not null").select("s", "t").distinct(), "edges")
    open_, done = _trimmed(all_edges.where("s <> t")), []
    while not open_.isEmpty():
        colour = materialise(vertices(open_).withColumn("c", F.col("v")), "colour")
        while True:
            low = open_.join(colour.select(F.col("v").alias("s"), "c"), "s").groupBy(F.col("t").alias("v")).agg(F.min("c").alias("low"))
            after = materialise(colour.join(low, "v", "left").select("v", F.least("c", F.coalesce("low", "c")).alias("c"), F.col("c").alias("was")), "colour")
            changed = not after.where("c <> was").isEmpty()
            colour = after.select("v", "c")
            if not changed:
                break
        # backwards from each colour's vertex, within the colour
        named = open_.join(colour.select(F.col("v").alias("s"), F.col("c").alias("cs")), "s").join(colour.select(F.col("v").alias("t"), F.col("c").alias("ct")), "t")
        inside = materialise(named.where("cs = ct").select("s", "t"), "inside")
        found = front = materialise(colour.where("v = c").select("v", F.col("c").alias("scc")), "found")
        while not front.isEmpty():
            back = inside.join(front.withColumnRenamed("v", "t"), "t").select(F.col("s").alias("v"), "scc").distinct()
            front = materialise(back.join(found, ["v", "scc"], "left_anti"), "front")
            found = found.union(front)
        found = materialise(found, "found")
        done.append(found)
        left = open_.join(found.select(F.col("v").alias("s")), "s", "left_anti").join(found.select(F.col("v").alias("t")), "t", "left_anti")
        open_ = _trimmed(materialise(left.select("s", "t"), "left"))
    out = vertices(all_edges)
    for k, found in enumerate(done):
        out = out.join(found.withColumnRenamed("scc", f"scc{k}"), "v", "left")
    return out.select("v", F.coalesce(*[f"scc{k}" for k in range(len(done))], F.col("v")).alias("scc"))
