"""Statistics of triples (s, p, o) and of properties, for the planner."""

from __future__ import annotations

import json
import math
from dataclasses import dataclass, field

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F


def key_counts(triples: DataFrame) -> DataFrame:
    """(slot, k, n): how many triples have each subject, property and object; one pass."""
    sets = triples.select(F.explode(F.array(*[F.struct(F.lit(c).alias("slot"), F.col(c).cast("long").alias("k")) for c in "spo"])).alias("e"))
    return sets.groupBy("e.slot", "e.k").agg(F.count(F.lit(1)).alias("n"))


def pair_counts(triples: DataFrame) -> DataFrame:
    """(slots, k1, k2, n): how many triples have each pair of (s, o), (p, s) and (p, o); one pass."""
    pairs = [F.struct(F.lit(a + b).alias("slots"), F.col(a).cast("long").alias("k1"), F.col(b).cast("long").alias("k2")) for a, b in ("so", "ps", "po")]
    return triples.select(F.explode(F.array(*pairs)).alias("e")).groupBy("e.slots", "e.k1", "e.k2").agg(F.count(F.lit(1)).alias("n"))


def property_sizes(triples: DataFrame) -> DataFrame:
    """(p, n_edges, n_vertices) of each property."""
    ends = triples.select("p", F.explode(F.array("s", "o")).alias("v")).distinct().groupBy("p").agg(F.count(F.lit(1)).alias("n_vertices"))
    return triples.groupBy("p").agg(F.count(F.lit(1)).alias("n_edges")).join(ends, "p")


def join_sizes(triples: DataFrame) -> DataFrame:
    """(p, q, position, n): rows that triples of p and of q give when joined on s-s, s-o, o-s or o-o.

    Degrees are multiplied vertex by vertex; the join itself is never built.
    """
    degree = {c: triples.groupBy("p", F.col(c).alias("v")).agg(F.count(F.lit(1)).alias("d")) for c in "so"}
    out = None
    for a in "so":
        for b in "so":
            x, y = degree[a].select("v", "p", "d"), degree[b].select("v", F.col("p").alias("q"), F.col("d").alias("e"))
            one = x.join(y, "v").groupBy("p", "q").agg(F.sum(F.col("d") * F.col("e")).alias("n")).withColumn("position", F.lit((a + b).upper()))
            out = one if out is None else out.union(one)
    return out.select("p", "q", "position", "n")


def join_selectivity(triples: DataFrame) -> DataFrame:
    """(p, q, position, sel): share of all pairs of triples of p and q that join."""
    size = triples.groupBy("p").agg(F.count(F.lit(1)).alias("m"))
    sizes = join_sizes(triples).join(size.withColumnRenamed("m", "mp"), "p").join(size.select(F.col("p").alias("q"), F.col("m").alias("mq")), "q")
    return sizes.select("p", "q", "position", (F.col("n") / (F.col("mp") * F.col("mq"))).alias("sel"))


def wilson(hits: int, n: int, z: float = 1.96) -> tuple[float, float]:
    """Interval of a share from a sample."""
    if not n:
        return 0.0, 1.0
    p, d = hits / n, 1 + z * z / n
    mid, half = (p + z * z / (2 * n)) / d, z * math.sqrt(p * (1 - p) / n + z * z / (4 * n * n)) / d
    return max(0.0, mid - half), min(1.0, mid + half)


@dataclass(frozen=True)
class ReachStat:
    """Sampled reachability selectivity of a property. ``sel`` is never 0."""

    samples: int
    hits: int
    sel: float
    low: float
    high: float


#: Pairs of a sample under which its share says little.
_FEW_HITS = 10


def reach_selectivity(index: object, side: int = 100, seed: int = 7, sources: DataFrame | None = None, targets: DataFrame | None = None) -> ReachStat:
    """Share of reachable pairs among ``side`` random sources times ``side`` random targets, asked as one set query.

    Ends are picked from ``sources(v)`` and ``targets(v)``, else from all
    vertices of the property. Where few pairs are met, the sources are held
    against all targets.
    """
    v = index.edges.select(F.col("s").alias("v")).union(index.edges.select("t")).distinct()
    pick = lambda df, salt: df.select("v").distinct().orderBy(F.xxhash64("v", F.lit(salt)), "v").limit(side)
    sources, every = pick(v if sources is None else sources, seed), v if targets is None else targets.select("v").distinct()
    targets = pick(every, seed + 1)
    ask = lambda to: (sources.count() * to.count(), index.set_reach(sources, to, "+", plus="cycle").count())
    n, hits = ask(targets)
    if n and hits < _FEW_HITS:
        n, hits = ask(every)
    low, high = wilson(hits, n)
    return ReachStat(n, hits, max(hits / n if n else 0.0, 1 / (2 * max(1, n))), low, high)


def reach_selectivity_exact(closure: DataFrame, edges: DataFrame) -> float:
    """Share of reachable pairs among all pairs of vertices, from the whole closure (x, y)."""
    n = edges.select(F.col("s").alias("v")).union(edges.select("t")).distinct().count()
    return closure.count() / (n * n) if n else 0.0


def sizes(edges: DataFrame) -> tuple[int, int, int, int]:
    """(edges, subjects, objects, vertices) of one property in one pass; all but the first are sketched."""
    ends = [F.hll_sketch_agg(c) for c in ("s", "o")]
    row = edges.agg(F.count(F.lit(1)), *map(F.hll_sketch_estimate, ends), F.hll_sketch_estimate(F.hll_union(*ends))).first()
    return tuple(int(x or 0) for x in row)


def pair_selectivity(left: DataFrame, right: DataFrame, position: str) -> float:
    """Share of all pairs of edges of two properties that meet in one end each, from products of degrees."""
    a, b = position.lower()
    x = left.groupBy(F.col(a).alias("v")).agg(F.count(F.lit(1)).alias("d"))
    y = right.groupBy(F.col(b).alias("v")).agg(F.count(F.lit(1)).alias("e"))
    met = x.join(y, "v", "full").agg(F.sum(F.coalesce(F.col("d") * F.col("e"), F.lit(0))), F.sum("d"), F.sum("e")).first()
    return (met[0] or 0) / max(1, (met[1] or 0) * (met[2] or 0))


@dataclass
class Catalog:
    """What the planner knows. Values that are missing fall back to guesses from the sizes."""

    k: int = 8
    n_edges: dict[str, int] = field(default_factory=dict)
    n_vertices: dict[str, int] = field(default_factory=dict)
    n_subjects: dict[str, int] = field(default_factory=dict)
    n_objects: dict[str, int] = field(default_factory=dict)
    join_sel: dict[tuple[str, str, str], float] = field(default_factory=dict)
    reach_sel: dict[str | tuple[str, str, str], float] = field(default_factory=dict)  # property, or property and what its ends are bound to
    key_rows: dict[tuple[str, str, str], int] = field(default_factory=dict)  # property, end, constant

    def edges(self, p: str) -> int:
        return self.n_edges.get(p, 1000)

    def vertices(self, p: str) -> int:
        return self.n_vertices.get(p, 2 * self.edges(p))

    def joined(self, p: str, q: str, position: str) -> float:
        if (sel := self.join_sel.get((p, q, position))) is not None:
            return max(sel, 1e-12)
        return 1 / max(1, min(self.vertices(p), self.vertices(q)))

    def reach(self, p: str, ends: tuple[str, str] = ("", "")) -> float:
        return self.reach_sel.get((p, *ends), self.reach_sel.get(p, 0.05))

    def save(self, spark: SparkSession, path: str) -> None:
        """Write the catalog to a folder that all sessions share."""
        facts = {name: [[key, value] for key, value in getattr(self, name).items()] for name in _KNOWN}
        spark.createDataFrame([(json.dumps({"k": self.k} | facts),)], "value string").coalesce(1).write.mode("overwrite").text(path)

    @classmethod
    def load(cls, spark: SparkSession, path: str) -> Catalog:
        """The catalog that ``save`` wrote."""
        facts = json.loads(spark.read.text(path).first().value)
        out = cls(facts["k"])
        for name in _KNOWN:
            getattr(out, name).update({tuple(key) if isinstance(key, list) else key: value for key, value in facts[name]})
        return out


_KNOWN = ("n_edges", "n_vertices", "n_subjects", "n_objects", "join_sel", "reach_sel", "key_rows")


def q_error(estimate: float, actual: float) -> float:
    """How many times an estimate is off, in either direction."""
    a, b = max(estimate, 1e-9), max(actual, 1e-9)
    return max(a / b, b / a)
