"""Reachability over a graph whose cycles are tied up first.

Vertices of one strongly connected component reach the same, so the smallest
stands for all of them. The largest component, the hub, is taken out: what leads
into it reaches all that it leads to. What is left has few and short paths. It
is sent to the tasks whole, which share the sources; where it is large, or where
options say how an index is laid out, it gets a ``ReachIndex``. A pair holds
over the hub or in what is left, and is found in one of the two only.
"""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass
from functools import cached_property

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from reachgraph.functions.kernels import Dag, components
from reachgraph.operators.partition import TASK_EDGES
from reachgraph.operators.reach_index import ReachIndex, one_step, same
from reachgraph.session import materialise

#: Ends of a question that are sent to all executors; more are joined by shuffle.
SENT_ROWS = 500_000
#: Edges of what is left that are sent to all executors; more are laid out in shards.
SENT_EDGES = 2_000_000

_KNOTS = pa.schema([("v", pa.int64()), ("scc", pa.int64()), ("hub", pa.bool_()), ("into", pa.bool_()), ("out", pa.bool_())])


def flooded(n: int, src: np.ndarray, dst: np.ndarray, start: np.ndarray) -> np.ndarray:
    """Which of the vertices 0..n-1 the edges lead to from ``start``, themselves included."""
    by = np.argsort(src, kind="stable")
    to, offsets = dst[by], np.searchsorted(src[by], np.arange(n + 1))
    seen = np.zeros(n, dtype=bool)
    seen[start], front = True, start
    while len(front):
        count = offsets[front + 1] - offsets[front]
        step = np.arange(count.sum()) - np.repeat(np.cumsum(count) - count, count)
        met = to[np.repeat(offsets[front], count) + step]
        front = np.unique(met[~seen[met]])
        seen[front] = True
    return seen


def _knots(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Vertices that share a cycle with others, and those that lead to the hub or come after it."""
    got = [(b.column("s").to_numpy(), b.column("t").to_numpy()) for b in batches if b.num_rows]
    if not got:
        return
    s, t = (np.concatenate(side) for side in zip(*got, strict=True))
    names, at = np.unique(np.concatenate([s, t]), return_inverse=True)
    s, t, n = at[: len(s)], at[len(s) :], len(names)
    comp = components(n, s, t)
    size, (_, first) = np.bincount(comp), np.unique(comp, return_index=True)
    hub = comp == size.argmax() if size.max() > 1 else np.zeros(n, dtype=bool)
    into, out = flooded(n, t, s, np.flatnonzero(hub)), flooded(n, s, t, np.flatnonzero(hub))
    told = np.flatnonzero((size[comp] > 1) | into | out)
    columns = [names[told], names[first[comp[told]]], hub[told], into[told], out[told]]
    for lo in range(0, len(told), 1 << 16):
        yield pa.RecordBatch.from_arrays([pa.array(c[lo : lo + (1 << 16)]) for c in columns], schema=_KNOTS)


@dataclass
class CondensedIndex:
    """Index over edges (s, t) without their cycles; asked as a ``ReachIndex`` is."""

    edges: DataFrame
    knots: DataFrame
    options: dict[str, object]

    @classmethod
    def build(cls, edges: DataFrame, *, task_edges: int = TASK_EDGES, **options: object) -> CondensedIndex | ReachIndex:
        """Cycles are found in one task; a graph of more than ``task_edges`` edges, or without cycles, gets a plain index."""
        edges = materialise(edges.where("s is not null and t is not null").select("s", "t").distinct(), "edges")
        if edges.count() > task_edges:
            return ReachIndex.build(edges, **options)
        knots = materialise(edges.repartition(1).mapInArrow(_knots, "v long, scc long, hub boolean, into boolean, out boolean"), "knots")
        if knots.isEmpty():
            return ReachIndex.build(edges, **options)
        return cls(edges, knots, options)

    @cached_property
    def left(self) -> DataFrame:
        """Edges (s, t) of what is left: knots by their smallest vertex, the hub taken out."""
        left = self.edges
        for end in ("s", "t"):
            of = self.knots.select(F.col("v").alias(end), "scc", "hub")
            left = left.join(of, end, "left").where("not coalesce(hub, false)").withColumn(end, F.coalesce("scc", end)).drop("scc", "hub")
        return materialise(left.select("s", "t").distinct(), "left")

    @cached_property
    def inner(self) -> ReachIndex:
        """Index of what is left; built when first asked for."""
        return ReachIndex.build(self.left, **self.options)

    @cached_property
    def whole(self) -> object:
        """Broadcast of what is left as one DAG; None where it is large or options ask for an index."""
        if self.options or self.left.count() > SENT_EDGES:
            return None
        got = self.left.toArrow()
        return self.edges.sparkSession.sparkContext.broadcast(Dag.of(*(got[c].to_numpy().astype(np.int64) for c in ("s", "t"))))

    @property
    def cut(self) -> DataFrame:
        return self.inner.cut

    def _named(self, ends: DataFrame, name: str) -> DataFrame:
        """(name, scc, hub, into, out) of vertices (v)."""
        known = ends.select("v").where("v is not null").distinct().join(self.knots, "v", "left")
        flags = [F.coalesce(c, F.lit(False)).alias(f"{name}_{c}") for c in ("hub", "into", "out")]
        return materialise(known.select(F.col("v").alias(name), F.coalesce("scc", "v").alias(f"{name}_scc"), *flags), "ends")

    def _rest(self, sources: DataFrame, targets: DataFrame, direction: str = "forward") -> DataFrame:
        """(x_scc, y_scc): what named ends reach, cycles included, without the hub."""
        x, y = (ends.where(f"not {n}_hub").select(F.col(f"{n}_scc").alias("v")).distinct() for ends, n in ((sources, "x"), (targets, "y")))
        if self.whole is not None and (sent := y.limit(SENT_ROWS + 1).toArrow()).num_rows <= SENT_ROWS:
            known = self.left.select(F.col("s").alias("v")).distinct()  # where no edge begins, nothing is reached
            tasks = 4 * x.sparkSession.sparkContext.defaultParallelism
            return x.join(known, "v", "left_semi").repartition(tasks).mapInArrow(_walked(self.whole, sent["v"].to_numpy().astype(np.int64)), "x_scc long, y_scc long")
        return self.inner.set_reach(x, y, "+", plus="cycle", direction=direction).toDF("x_scc", "y_scc")

    def set_reach(self, sources: DataFrame, targets: DataFrame, kind: str = "+", *, plus: str = "distinct", zero_scope: str = "domain", direction: str = "forward") -> DataFrame:
        """Distinct pairs (x, y), as ``ReachIndex.set_reach`` gives them."""
        if kind == "?":
            return one_step(self.edges, sources, targets, zero_scope)
        x, y = self._named(sources, "x"), self._named(targets, "y")
        pairs = self._rest(x, y, direction)
        for ends, name in ((x, "x"), (y, "y")):
            pairs = pairs.join(_sent(ends.drop(f"{name}_hub")), f"{name}_scc")
        pairs = pairs.where("not (x_into and y_out)").select("x", "y").unionByName(_product(x.where("x_into").select("x"), y.where("y_out").select("y")))
        if kind == "*":
            return pairs.where("x <> y").unionByName(same(self.edges, sources, targets, zero_scope))
        return pairs.where("x <> y") if plus == "distinct" else pairs

    def meets(self, df: DataFrame, x: str, y: str, kind: str = "+", *, plus: str = "distinct") -> DataFrame:
        """Rows of ``df`` whose column ``x`` reaches their column ``y``; pairs of members are never made."""
        df = materialise(df.where(F.col(x).isNotNull() & F.col(y).isNotNull()), "rows")
        a, b = (self._named(df.select(F.col(c).alias("v")), n) for c, n in ((x, "x"), (y, "y")))
        rows = df
        for ends, c, n in ((a, x, "x"), (b, y, "y")):
            rows = rows.join(_sent(ends.withColumnRenamed(n, f"_{n}")), F.col(c) == F.col(f"_{n}"))
        equal = F.col(x) == F.col(y)
        if kind == "*" or plus == "distinct":
            rows = rows.where(~equal)
        over = F.col("x_into") & F.col("y_out")
        rest = rows.where(~over & ~F.col("x_hub") & ~F.col("y_hub"))
        out = rows.where(over).select(*df.columns).unionByName(rest.join(self._rest(a, b), ["x_scc", "y_scc"], "left_semi").select(*df.columns))
        return out.unionByName(df.where(equal)) if kind == "*" else out

    def on_cycles(self, vertices: DataFrame) -> DataFrame:
        """(v): those of ``vertices(v)`` that reach themselves over an edge or more: members of components of several, and loops."""
        shared = self.knots.join(self.knots.groupBy("scc").agg(F.count(F.lit(1)).alias("n")).where("n > 1"), "scc").select("v")
        loops = self.edges.where("s = t").select(F.col("s").alias("v"))
        return vertices.select("v").where("v is not null").distinct().join(shared.union(loops), "v", "left_semi")


def layered(edges: DataFrame, middle: DataFrame) -> DataFrame:
    """Edges (s, t) of two copies of a graph, v as 2v and as 2v + 1; each vertex of ``middle(v)`` leads from the first copy to the second.

    So 2x reaches 2y + 1 where x reaches, in no edge or more, a vertex of ``middle`` and that reaches y.
    """
    one, two = (edges.select(*[(F.col(c) * 2 + k).alias(c) for c in ("s", "t")]) for k in (0, 1))
    over = middle.where("v is not null").distinct().select((F.col("v") * 2).alias("s"), (F.col("v") * 2 + 1).alias("t"))
    return one.union(two).union(over)


def reach_over(index: CondensedIndex | ReachIndex, sources: DataFrame, targets: DataFrame) -> DataFrame:
    """Distinct pairs (x, y) that an index over ``layered`` edges connects."""
    x, y = (ends.select((F.col("v") * 2 + k).alias("v")) for k, ends in enumerate((sources, targets)))
    return index.set_reach(x, y, "+").select(*[F.shiftright(c, 1).alias(c) for c in ("x", "y")])


def _walked(whole: object, targets: np.ndarray):
    schema = pa.schema([("x_scc", pa.int64()), ("y_scc", pa.int64())])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        got = [b.column("v").to_numpy() for b in batches if b.num_rows]
        if not got:
            return
        sources = np.concatenate(got)
        for x, y in whole.value.reach_by_blocks(sources, sources, targets, empty_path=False):
            for lo in range(0, len(x), 1 << 18):
                yield pa.RecordBatch.from_arrays([pa.array(c[lo : lo + (1 << 18)]) for c in (x, y)], schema=schema)

    return run


def _sent(ends: DataFrame) -> DataFrame:
    return F.broadcast(ends) if ends.count() <= SENT_ROWS else ends


def _product(x: DataFrame, y: DataFrame) -> DataFrame:
    """All pairs of two sets; the smaller is sent to the tasks of the larger, or both are dealt out."""
    n, m = x.count(), y.count()
    tasks = 4 * x.sparkSession.sparkContext.defaultParallelism
    if min(n, m) > SENT_ROWS:
        return x.repartition(tasks).crossJoin(y.repartition(8))
    large, small = (x, y) if n >= m else (y, x)
    return large.repartition(tasks).crossJoin(F.broadcast(small)).select("x", "y")
