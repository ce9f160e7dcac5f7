"""Assignments of vertices to shards: hash, key range, whole components, locality."""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from reachgraph.session import materialise


def vertices(edges: DataFrame) -> DataFrame:
    """Distinct vertices (v) of edges (s, t)."""
    return edges.select(F.col("s").alias("v")).union(edges.select("t")).distinct()


def both_ways(edges: DataFrame) -> DataFrame:
    """Edges (v, w) in both directions."""
    return edges.select(F.col("s").alias("v"), F.col("t").alias("w")).union(edges.select("t", "s"))


@dataclass(frozen=True)
class HashPartitioner:
    """Vertex modulo number of shards; computed, so nothing is joined."""

    k: int

    def column(self, v: Column) -> Column:
        return F.pmod(v, F.lit(self.k)).cast("int")

    def parts(self, edges: DataFrame) -> DataFrame:
        return vertices(edges).withColumn("part", self.column(F.col("v")))

    def place(self, df: DataFrame, vertex: str, part: str, edges: DataFrame | None = None) -> DataFrame:
        """Add the shard of a vertex column."""
        return df.withColumn(part, self.column(F.col(vertex)))


@dataclass(frozen=True)
class RangePartitioner:
    """Ranges of vertex ids with about as many vertices each."""

    k: int

    def parts(self, edges: DataFrame) -> DataFrame:
        v = vertices(edges)
        cuts = v.agg(F.percentile_approx("v", [i / self.k for i in range(1, self.k)] or [0.5], 10_000).alias("c")).first().c or []
        part = sum((F.when(F.col("v") > F.lit(c), 1).otherwise(0) for c in cuts[: self.k - 1]), F.lit(0))
        return v.withColumn("part", part.cast("int"))


#: Most edges whose components one task works out; 16 bytes each.
TASK_EDGES = 5_000_000


def weak_components(edges: DataFrame, column: str = "label", task_edges: int = TASK_EDGES) -> DataFrame:
    """(v, label): the smallest vertex that v is connected with, directions aside.

    Up to ``task_edges`` distinct edges go to one task. Beyond, labels jump along
    the labels of labels, so the number of rounds grows with the logarithm of
    the diameter; they end when no label changes.
    """
    if edges.limit(task_edges + 1).count() <= task_edges:
        return edges.select("s", "t").repartition(1).mapInArrow(_components, "v long, label long").withColumnRenamed("label", column)
    links = materialise(both_ways(edges), "links")
    labels = materialise(links.groupBy("v").agg(F.least(F.min("w"), F.first("v")).alias("label")), "labels")
    while True:
        near = links.join(labels.select(F.col("v").alias("w"), "label"), "w").groupBy("v").agg(F.min("label").alias("near"))
        stepped = labels.join(near, "v").select("v", F.least("label", "near").alias("label"), F.col("label").alias("old"))
        stepped = materialise(stepped, "labels")
        # a whole component follows where any of its members has found a smaller one
        hook = stepped.groupBy(F.col("old").alias("o")).agg(F.min("label").alias("n"))
        moved = stepped.join(hook, stepped["old"] == hook["o"]).select("v", F.least("label", "n").alias("label"), "old")
        jump = moved.groupBy("v", "label", "old").count().drop("count")
        up = jump.select(F.col("v").alias("u"), F.col("label").alias("up"))
        after = materialise(jump.join(up, jump["label"] == up["u"], "left").select("v", F.coalesce("up", "label").alias("label"), "old"), "labels")
        labels = after.select("v", "label")
        if after.where("label <> old").isEmpty():
            return labels.withColumnRenamed("label", column)


def _components(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Labels spread over whole arrays, each round along all edges and then along labels of labels."""
    got = [(b.column("s").to_numpy(), b.column("t").to_numpy()) for b in batches if b.num_rows]
    if not got:
        return
    s, t = (np.concatenate(side) for side in zip(*got, strict=True))
    names, at = np.unique(np.concatenate([s, t]), return_inverse=True)
    s, t = at[: len(s)], at[len(s) :]
    label = np.arange(len(names))
    while True:
        low = np.minimum(label[s], label[t])
        after = label.copy()
        for end in (label[s], label[t], s, t):
            np.minimum.at(after, end, low)
        while (after != after[after]).any():
            after = after[after]
        if (after == label).all():
            break
        label = after
    yield pa.RecordBatch.from_arrays([pa.array(names), pa.array(names[label])], names=["v", "label"])


@dataclass(frozen=True)
class ComponentPartitioner:
    """Whole weakly connected components, packed by size: the cut is empty."""

    k: int

    def parts(self, edges: DataFrame) -> DataFrame:
        return _packed_components(edges, self.k)


def _packed_components(edges: DataFrame, k: int) -> DataFrame:
    labels = materialise(weak_components(edges), "labels")
    return labels.join(packed(labels, k), "label").select("v", "part")


@dataclass(frozen=True)
class LocalityPartitioner:
    """Label propagation: a vertex joins the label most of its neighbours have, as long as that label has room.

    ``rounds`` rounds are run from singleton labels; labels are then dealt to
    shards by size, the largest first. ``balance`` is how far over the mean a
    label may grow.
    """

    k: int
    rounds: int = 4
    balance: float = 1.2

    def parts(self, edges: DataFrame) -> DataFrame:
        links = materialise(both_ways(edges).where("v <> w"), "links")
        labels = materialise(vertices(edges).select("v", F.col("v").alias("label")), "labels")
        room = max(1, int(labels.count() * self.balance / self.k))
        best = Window.partitionBy("v").orderBy(F.desc("n"), "label")
        for turn in range(self.rounds):
            votes = links.join(labels.select(F.col("v").alias("w"), "label"), "w").groupBy("v", "label").agg(F.count(F.lit(1)).alias("n"))
            chosen = votes.withColumn("r", F.row_number().over(best)).where("r = 1").select("v", F.col("label").alias("wish"))
            asked = labels.join(chosen, "v", "left").withColumn("label", F.when(F.pmod(F.xxhash64("v", F.lit(turn)), F.lit(2)) == 0, F.coalesce("wish", "label")).otherwise(F.col("label")))
            sizes = asked.groupBy("label").agg(F.count(F.lit(1)).alias("size")).where(F.col("size") > room).select(F.col("label").alias("full"))
            kept = asked.join(F.broadcast(sizes), F.col("label") == F.col("full"), "left").join(labels.select("v", F.col("label").alias("was")), "v")
            labels = materialise(kept.select("v", F.when(F.col("full").isNotNull(), F.col("was")).otherwise(F.col("label")).alias("label")), "labels")
        return labels.join(packed(labels, self.k), "label").select("v", "part")


def packed(labels: DataFrame, k: int) -> DataFrame:
    """(label, part): labels dealt to ``k`` shards by size.

    Labels larger than a tenth of a shard, at most ``10 * k`` of them, are dealt
    largest first, each to the shard with the least so far; the small ones are hashed.
    """
    sizes = labels.groupBy("label").agg(F.count(F.lit(1)).alias("size"))
    total = sizes.agg(F.sum("size").alias("n")).first().n or 0
    load, dealt = [0] * k, []
    for r in sizes.where(F.col("size") > max(1, total // (10 * k))).orderBy(F.desc("size"), "label").collect():
        part = min(range(k), key=lambda i: (load[i], i))
        load[part] += r["size"]
        dealt.append((r.label, part))
    given = labels.sparkSession.createDataFrame(dealt, "label long, given int")
    hashed = F.pmod(F.xxhash64("label"), F.lit(k)).cast("int")
    return sizes.join(F.broadcast(given), "label", "left").select("label", F.coalesce("given", hashed).alias("part"))


def check_partition(parts: DataFrame, edges: DataFrame) -> DataFrame:
    """(fault, n): vertices with several shards, and vertices of edges without one; no rows if all is well."""
    twice = parts.groupBy("v").agg(F.countDistinct("part").alias("n")).where("n > 1").select(F.lit("several shards").alias("fault"))
    none = vertices(edges).join(parts, "v", "left_anti").select(F.lit("no shard").alias("fault"))
    return twice.union(none).groupBy("fault").agg(F.count(F.lit(1)).alias("n"))
