"""Connected components and links through buckets, without all pairs in a group.

``components`` labels the nodes of an edge table by alternating two star
operations: every node is joined to the smallest neighbour it knows. Each round
is a partial aggregation and an equi-join; a hub with a third of all edges is
pre-aggregated, and the joins are ones that adaptive execution can split.
"""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from reachgraph.llm.common import drop_stored, stored, sweep


def components(edges: DataFrame) -> DataFrame:
    """(node, label) for every node of ``edges(a, b)``; the label is the smallest node of its component.

    Self-loops, repeated edges and both directions are fine; nulls are left out.
    """
    now = stored(
        edges.where("a is not null and b is not null and a <> b").select(F.greatest("a", "b").alias("a"), F.least("a", "b").alias("b")).distinct(),
        "edges",
    )
    while not _stars(now):
        both = now.unionByName(now.select(F.col("b").alias("a"), F.col("a").alias("b")))
        # large star: every larger neighbour of a node is joined to the smallest of node and neighbours
        low = both.groupBy("a").agg(F.min("b").alias("m")).select("a", F.least("a", "m").alias("m"))
        large = now.withColumnsRenamed({"a": "hi", "b": "a"}).join(low, "a").select(F.col("hi").alias("a"), F.col("m").alias("b"))
        large = large.where("a <> b").distinct()
        # small star: a node and its smaller neighbours are joined to the smallest of them
        low = large.groupBy("a").agg(F.min("b").alias("m"))
        small = large.join(low, "a")
        small = small.select(F.col("b").alias("x"), "m").where("x <> m").unionByName(low.select(F.col("a").alias("x"), "m"))
        after = stored(small.select(F.col("x").alias("a"), F.col("m").alias("b")).distinct(), "edges")
        drop_stored(now)
        now = after
    nodes = now.select(F.col("a").alias("node"), F.col("b").alias("label"))
    return nodes.unionByName(now.select(F.col("b").alias("node"), F.col("b").alias("label")).distinct())


def _stars(edges: DataFrame) -> bool:
    """Whether distinct edges (a, b), a > b, are stars around the smallest node of each component, which ends the rounds."""
    ends = edges.select(F.col("a").alias("v"), F.lit(1).alias("up"), F.lit(0).alias("down")).unionAll(edges.select("b", F.lit(0), F.lit(1)))
    met = ends.groupBy("v").agg(F.sum("up").alias("up"), F.max("down").alias("down"))
    return not met.agg(F.max((F.col("up") + F.col("down") > 1).cast("int")).alias("odd")).first().odd


def bucket_components(
    buckets: DataFrame,
    verifier: Callable[[DataFrame], Callable[[DataFrame], DataFrame]],
    closer: Callable[[DataFrame], DataFrame],
    weigh: Callable[[DataFrame], DataFrame] | None = None,
    large: int = 8,
) -> DataFrame:
    """(node, label) of the nodes in components of several, by verified links among nodes that share a bucket.

    ``buckets(key, node)`` proposes. ``verifier`` gets the members of buckets
    with several nodes and returns a function that takes distinct pairs (a, b),
    a > b, and gives back those that are linked. First every node of a bucket is
    held against the bucket's smallest node, one pair per row, so that a group of
    copies of any size costs as many pairs as it has members. Links inside a
    component add nothing to it. What is left are pairs of one bucket in
    different components, of which one is not in the bucket's main component. In
    buckets of up to ``large`` open nodes all of them are verified. In the others
    they would be as many as the square of the bucket. There the nodes outside
    the main component are held against its heaviest node by ``weigh``, which
    gets nodes and returns (node, weight), else against any one. For what is
    still outside ``closer`` gets the nodes (node, label, outer), where ``outer``
    marks those that are outside a main component, and returns pairs (a, b) of
    different labels, one of them outer, among which is every such pair that is
    linked.
    """
    # most buckets have one node; a count per key is all that travels to find the others
    often = buckets.groupBy("key").agg(F.count(F.lit(1)).alias("n")).where("n > 1").select("key")
    met = stored(buckets.join(often.hint("shuffle_hash"), "key"), "met")
    hubs = met.groupBy("key").agg(F.min("node").alias("hub"), F.max("node").alias("top")).where("hub < top").select("key", "hub")
    members = stored(met.join(hubs, "key"), "members")
    drop_stored(met)
    verify = verifier(members)
    tried = stored(members.where("node <> hub").select(F.col("node").alias("a"), F.col("hub").alias("b")).distinct(), "tried")
    labels = stored(components(stored(verify(tried), "links")), "labels")
    rest = _unsettled(members, labels)
    drop_stored(members)
    crowded = rest.where(F.col("n") > large)
    if not crowded.isEmpty():
        weights = weigh(stored(crowded.select("node").distinct(), "wide")) if weigh else crowded.select("node", F.xxhash64("node").alias("weight")).distinct()
        heads = crowded.where("label = major").join(weights, "node").groupBy("key").agg(F.max_by("node", F.struct("weight", "node")).alias("head"))
        more = crowded.where("label <> major").join(heads, "key").select(F.greatest("node", "head").alias("a"), F.least("node", "head").alias("b")).distinct()
        more = stored(more.join(tried, ["a", "b"], "left_anti"), "tried")
        found = stored(verify(more), "links")
        tried = tried.unionByName(more)
        if not found.isEmpty():
            labels = stored(_merge(labels, found), "labels")
            rest = _unsettled(rest, labels)
    crowded = rest.where(F.col("n") > large)
    wide = stored(crowded.groupBy("node").agg(F.first("label").alias("label"), F.max(F.col("label") != F.col("major")).alias("outer")), "wide")
    pairs = _cross_pairs(rest.where(F.col("n") <= large))
    if not wide.isEmpty():
        pairs = pairs.unionByName(closer(wide))
    pairs = stored(pairs.distinct().join(tried, ["a", "b"], "left_anti"), "tried")
    found = stored(verify(pairs), "links")
    sweep(buckets.sparkSession)
    return labels if found.isEmpty() else stored(_merge(labels, found), "labels")


def _unsettled(members: DataFrame, labels: DataFrame) -> DataFrame:
    """(key, node, hub, label, major, n): nodes, other than hubs, of buckets where these are of several components.

    ``major`` is the label that most of the ``n`` nodes have.
    """
    known = (
        members.where("node <> hub")
        .select("key", "node", "hub")
        .join(labels, "node", "left")
        .select("key", "node", "hub", F.coalesce("label", "node").alias("label"))
        .distinct()
    )
    by_label = known.groupBy("key", "label").agg(F.count(F.lit(1)).alias("m"))
    mixed = by_label.groupBy("key").agg(F.count(F.lit(1)).alias("labels"), F.sum("m").alias("n"), F.max(F.struct("m", "label"))["label"].alias("major"))
    return stored(known.join(mixed.where("labels > 1").select("key", "major", "n"), "key"), "rest")


def _cross_pairs(rest: DataFrame) -> DataFrame:
    """Pairs (a, b), a > b, of one small bucket and of different components, one of them not the main one."""
    left = rest.where("label <> major").select("key", "node", "label")
    right = rest.select("key", "major", F.col("node").alias("o_node"), F.col("label").alias("o_label"))
    # pairs within what is outside the main component come up once, from their larger node
    once = (F.col("o_label") == F.col("major")) | (F.col("node") > F.col("o_node"))
    return (
        left.join(right, "key")
        .where((F.col("label") != F.col("o_label")) & once)
        .select(F.greatest("node", "o_node").alias("a"), F.least("node", "o_node").alias("b"))
    )


def _merge(labels: DataFrame, links: DataFrame) -> DataFrame:
    """Labels after more links; only the labels' own components are worked out anew."""
    ends = links
    for end in ("a", "b"):
        of = labels.select(F.col("node").alias(end), F.col("label").alias(f"l{end}"))
        ends = ends.join(of, end, "left")
    upper = stored(components(ends.select(F.coalesce("la", "a").alias("a"), F.coalesce("lb", "b").alias("b"))), "labels")
    upper = upper.select(F.col("node").alias("label"), F.col("label").alias("top"))
    new = upper.join(labels.select("label").distinct(), "label", "left_anti").select(F.col("label").alias("node"), F.col("top").alias("label"))
    return labels.join(upper, "label", "left").select("node", F.coalesce("top", "label").alias("label")).unionByName(new)
