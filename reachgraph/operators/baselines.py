"""What the index is compared with: traversal, messages, recursion, closures, single pairs, unrolled chains."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from reachgraph.session import materialise


def _ends(pairs: DataFrame, targets: DataFrame | None, plus: str) -> DataFrame:
    if targets is not None:
        pairs = pairs.join(targets.select(F.col("v").alias("y")).distinct(), "y", "left_semi")
    return (pairs.where("x <> y") if plus == "distinct" else pairs).select("x", "y")


def frontier_reach(edges: DataFrame, sources: DataFrame, targets: DataFrame | None = None, *, plus: str = "distinct", counts: list[int] | None = None) -> DataFrame:
    """Pairs (x, y) over one edge or more, by expanding the frontier of all sources hop by hop.

    ``counts`` gets the size of each frontier; its length is the number of rounds.
    """
    hops = edges.select(F.col("s").alias("m"), F.col("t").alias("y")).distinct()
    front = materialise(hops.join(sources.select(F.col("v").alias("m")).distinct(), "m", "left_semi").select(F.col("m").alias("x"), "y"), "front")
    seen = front
    while True:
        n = front.count()
        if counts is not None:
            counts.append(n)
        if not n:
            return _ends(seen, targets, plus)
        ahead = front.withColumnRenamed("y", "m").join(hops, "m").select("x", "y").distinct()
        front = materialise(ahead.join(seen, ["x", "y"], "left_anti"), "front")
        seen = seen.union(front)


def vertex_centric_reach(edges: DataFrame, sources: DataFrame, targets: DataFrame | None = None, *, plus: str = "distinct", counts: list[int] | None = None) -> DataFrame:
    """Pairs (x, y): every vertex keeps the set of its origins and sends what is new along its edges in each superstep."""
    hops = edges.select(F.col("s").alias("v"), F.col("t").alias("to")).distinct()
    state = sources.select("v", F.array("v").alias("fresh"), F.array().cast("array<long>").alias("known")).distinct()
    state = materialise(state, "state")
    while True:
        mail = hops.join(state.where(F.size("fresh") > 0), "v").groupBy(F.col("to").alias("v")).agg(F.array_distinct(F.flatten(F.collect_list("fresh"))).alias("got"))
        # what a vertex starts with is no news of its own: it may come back over a cycle
        both = state.join(mail, "v", "full_outer").select("v", F.coalesce("known", F.array().cast("array<long>")).alias("known"), F.coalesce("got", F.array().cast("array<long>")).alias("got"))
        state = both.select("v", F.array_except("got", "known").alias("fresh"), F.array_union("known", "got").alias("known"))
        state = materialise(state, "state")
        n = state.agg(F.sum(F.size("fresh"))).first()[0] or 0
        if counts is not None:
            counts.append(n)
        if not n:
            return _ends(state.select(F.explode("known").alias("x"), F.col("v").alias("y")), targets, plus)


def recursive_cte_reach(spark: SparkSession, edges: DataFrame, sources: DataFrame, targets: DataFrame | None = None, *, depth: int = 90, plus: str = "distinct") -> DataFrame:
    """Pairs (x, y) by a recursive common table expression; paths of up to ``depth`` edges, for graphs without cycles."""
    text = """
        WITH RECURSIVE walk(x, y, n) MAX RECURSION LEVEL 100 AS (
          SELECT e.s, e.t, 1 FROM {edges} e JOIN {sources} o ON e.s = o.v
          UNION ALL SELECT w.x, e.t, w.n + 1 FROM walk w JOIN {edges} e ON w.y = e.s WHERE w.n < {depth})
        SELECT DISTINCT x, y FROM walk"""
    pairs = spark.sql(text, edges=edges.select("s", "t").distinct(), sources=sources.select("v").distinct(), depth=depth)
    return _ends(pairs, targets, plus)


def closure(edges: DataFrame, method: str = "seminaive", counts: list[int] | None = None) -> DataFrame:
    """All pairs (x, y) over one edge or more; ``doubling`` squares the relation instead of adding a hop."""
    base = materialise(edges.select(F.col("s").alias("x"), F.col("t").alias("y")).distinct(), "closure")
    if method == "seminaive":
        return frontier_reach(edges, edges.select(F.col("s").alias("v")), plus="cycle", counts=counts)
    n = base.count()
    while True:
        if counts is not None:
            counts.append(n)
        twice = base.select("x", F.col("y").alias("m")).join(base.select(F.col("x").alias("m"), "y"), "m").select("x", "y")
        base = materialise(base.union(twice).distinct(), "closure")
        after = base.count()
        if after == n:
            return base
        n = after


def closure_reach(edges: DataFrame, sources: DataFrame, targets: DataFrame, *, method: str = "seminaive", plus: str = "distinct") -> DataFrame:
    """Pairs (x, y) looked up in the whole closure."""
    pairs = closure(edges, method).join(sources.select(F.col("v").alias("x")).distinct(), "x", "left_semi")
    return _ends(pairs, targets, plus)


def pairwise_reach(index: object, sources: list[int], targets: list[int], *, plus: str = "distinct") -> DataFrame:
    """Pairs (x, y) by one query per pair; for a handful of each."""
    spark = index.edges.sparkSession
    one = lambda v: spark.createDataFrame([(v,)], "v long")
    found = [(s, t) for s in sources for t in targets if not index.set_reach(one(s), one(t), "+", plus=plus).isEmpty()]
    return spark.createDataFrame(found, "x long, y long")


def unrolled_reach(edges: DataFrame, sources: DataFrame, targets: DataFrame, *, most: int | None, plus: str = "distinct", unroll: int = 16) -> DataFrame:
    """Pairs (x, y) over paths of 1 to ``most`` edges, each length a chain of joins written out.

    Without ``most`` the chain is written ``unroll`` joins at a time, from the
    pairs that the last join found new, until there are none.
    """
    hops = edges.select(F.col("s").alias("m"), F.col("t").alias("y")).distinct()
    pairs = hops.join(sources.select(F.col("v").alias("m")).distinct(), "m", "left_semi").select(F.col("m").alias("x"), "y")
    if most is not None:
        return _ends(_chain(pairs, hops, most - 1).select("x", "y").distinct(), targets, plus)
    hops = materialise(hops, "hops")
    front = seen = materialise(pairs, "front")
    while not front.isEmpty():
        found = materialise(_chain(front, hops, unroll).select("x", "y").distinct(), "found")
        front = materialise(found.join(seen, ["x", "y"], "left_anti"), "front")
        seen = seen.union(front)
    return _ends(seen, targets, plus)


def _chain(pairs: DataFrame, hops: DataFrame, joins: int) -> DataFrame:
    """Pairs, and those that up to ``joins`` further edges make of them."""
    every = pairs
    for _ in range(joins):
        pairs = pairs.withColumnRenamed("y", "m").join(hops, "m").select("x", "y").distinct()
        every = every.union(pairs)
    return every


def bounded_reach(edges: DataFrame, sources: DataFrame, targets: DataFrame, low: int, high: int) -> DataFrame:
    """Pairs (x, y) joined by a path of ``low`` to ``high`` edges, vertices repeating or not."""
    hops = edges.select(F.col("s").alias("m"), F.col("t").alias("y")).distinct()
    pairs = sources.select(F.col("v").alias("x"), F.col("v").alias("y")).distinct()
    every = pairs if low == 0 else None
    for n in range(1, high + 1):
        pairs = pairs.withColumnRenamed("y", "m").join(hops, "m").select("x", "y").distinct()
        if n >= low:
            every = pairs if every is None else every.union(pairs)
    return _ends(every.distinct(), targets, "cycle")


def shortest_lengths(edges: DataFrame, sources: DataFrame) -> DataFrame:
    """(x, y, n): number of edges of a shortest path of one edge or more."""
    hops = edges.select(F.col("s").alias("m"), F.col("t").alias("y")).distinct()
    front = hops.join(sources.select(F.col("v").alias("m")).distinct(), "m", "left_semi").select(F.col("m").alias("x"), "y", F.lit(1).alias("n"))
    seen = front = materialise(front, "front")
    n = 1
    while not front.isEmpty():
        n += 1
        ahead = front.drop("n").withColumnRenamed("y", "m").join(hops, "m").select("x", "y").distinct()
        front = materialise(ahead.join(seen, ["x", "y"], "left_anti").withColumn("n", F.lit(n)), "front")
        seen = seen.union(front)
    return seen
