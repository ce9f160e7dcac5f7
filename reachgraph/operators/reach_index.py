"""Reachability index of one property, and set reachability in one exchange.

Vertices lie in shards. Each shard holds the DAG of its own edges; what leads
from shard to shard is one boundary graph, shared by all: cut edges, and for
each shard which of its exits its entries reach. Entries that reach the same
exits, and exits that the same entries reach, are classes with one virtual
vertex each.

A query goes from the sources to the exits of their shard, through the boundary
graph to entries, all in one task; the pairs (source, entry) are exchanged once
and finished in the shards of the entries.

Sources of one component, and sources that reach the same entries, go as one
class, named by its smallest member. Entries of a shard that lie in one
component of the boundary graph are likewise named by the smallest. Pairs of
classes and targets become pairs of members by a join in the end, so that no
task holds an answer.
"""

from __future__ import annotations

import json
import uuid
from collections.abc import Callable, Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from reachgraph.functions.kernels import WALK, WALK_PAIRS, Dag, equal_columns, joined, set_bits
from reachgraph.operators.partition import HashPartitioner, packed, weak_components
from reachgraph.session import materialise

_ARRAYS = ("verts", "comp", "cyclic", "src", "dst", "level", "entries", "exits")
_SHARD = "part int, " + ", ".join(f"{a} array<long>" for a in _ARRAYS)
_ROLES = pa.schema([("role", pa.int32()), ("a", pa.int64()), ("b", pa.int64())])

# roles of what departs: a member of a class and the class, a class and what it reaches in its shard, and both again for what is mailed
_NEAR_MEMBER, _NEAR, _FAR_MEMBER, _FAR = range(4)


def _np(column: pa.ChunkedArray) -> np.ndarray:
    return column.to_numpy(zero_copy_only=False).astype(np.int64)


def _rows(table: pa.Table | pa.RecordBatch) -> Iterator[dict[str, np.ndarray]]:
    """The shards of a table, each array as a view and not as Python numbers."""
    for batch in table.to_batches() if isinstance(table, pa.Table) else [table]:
        for i in range(batch.num_rows):
            yield {a: batch.column(a)[i].values.to_numpy(zero_copy_only=False) for a in _ARRAYS} | {"part": batch.column("part")[i].as_py()}


def _dag(row: dict[str, np.ndarray]) -> Dag:
    return Dag(row["verts"], row["comp"], row["cyclic"].astype(bool), row["src"], row["dst"], row["level"])


# ids within the boundary and compound graphs
def _local(v):
    return v * 4


def _entry(v):
    return v * 4 + 1


def _exit(v):
    return v * 4 + 2


def _build(compound: tuple[np.ndarray, np.ndarray] | None):
    schema = pa.schema([("part", pa.int32())] + [(a, pa.list_(pa.int64())) for a in _ARRAYS])

    def run(key: tuple, rows: pa.Table) -> pa.Table:
        kind, a, b = (_np(rows[c]) for c in ("kind", "a", "b"))
        src, dst = a[kind == 0], b[kind == 0]
        entries, exits = np.unique(a[kind == 1]), np.unique(a[kind == 2])
        extra = np.concatenate([entries, exits])
        if compound:
            src = np.concatenate([_local(src), _local(exits), _entry(entries), compound[0]])
            dst = np.concatenate([_local(dst), _exit(exits), _local(entries), compound[1]])
            extra = _local(extra)
        dag = Dag.of(src, dst, extra)
        values = [dag.verts, dag.comp, dag.cyclic.astype(np.int64), dag.src, dag.dst, dag.level, entries, exits]
        return pa.table([pa.array([key[0].as_py()], type=pa.int32())] + [pa.ListArray.from_arrays(pa.array([0, len(v)], type=pa.int32()), pa.array(v, type=pa.int64())) for v in values], schema=schema)

    return run


def _crossings(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    schema = pa.schema([("part", pa.int32()), ("entry", pa.int64()), ("exit", pa.int64())])
    for batch in batches:
        for row in _rows(batch):
            for s, t in _dag(row).reach_by_blocks(row["entries"], row["entries"], row["exits"]):
                yield pa.RecordBatch.from_arrays([pa.array(np.full(len(s), row["part"]), type=pa.int32()), pa.array(s), pa.array(t)], schema=schema)


@dataclass
class ReachIndex:
    """Index over edges (s, t). ``build`` makes one; ``set_reach`` asks it."""

    edges: DataFrame
    partitioner: object
    parts: DataFrame | None
    cut: DataFrame
    shards: DataFrame
    crossings: DataFrame
    boundary: DataFrame
    layout: str
    shared: object  # broadcast of (boundary DAG, entries, the entries that stand for them), or None if it is too large
    max_boundary: int
    steps: int = 0  # exchanges of the last question that crossed the boundary by joins

    @classmethod
    def build(
        cls,
        edges: DataFrame,
        k: int | None = None,
        partitioner: object = None,
        *,
        compress: bool = True,
        layout: str = "shared",
        max_boundary: int = 2_000_000,
        shard_edges: int = 1_000_000,
    ) -> ReachIndex:
        """Index the distinct, non-null edges over ``k`` shards.

        Without ``k`` there is a shard for every ``shard_edges`` edges, 8 at
        least. Without a partitioner one is chosen by ``choose_partitioner``. A
        boundary graph of more than ``max_boundary`` edges is not broadcast:
        queries then cross it by joins, with one exchange per step, and say how
        many in ``steps``.
        """
        spark = edges.sparkSession
        edges = materialise(edges.where("s is not null and t is not null").select("s", "t").distinct(), "edges")
        if k is None:
            k = max(8, -(-edges.count() // shard_edges))
            partitioner = partitioner or choose_partitioner(edges, k)
        partitioner = partitioner or HashPartitioner(k)
        parts = None if isinstance(partitioner, HashPartitioner) else materialise(partitioner.parts(edges), "parts")
        placed = _place(_place(edges, "s", "ps", partitioner, parts), "t", "pt", partitioner, parts)
        placed = materialise(placed, "placed")
        cut = placed.where("ps <> pt")
        rows = _shard_rows(placed.where("ps = pt"), cut)
        rows = _apart(rows, k)
        shards = materialise(rows.groupBy("part").applyInArrow(_build(None), _SHARD), "shards")
        crossings = materialise(_apart(shards, k).mapInArrow(_crossings, "part int, entry long, exit long"), "crossings")
        boundary = _boundary(crossings, cut, compress)
        shared = _shared(boundary, cut, max_boundary)
        if layout == "compound":
            if shared is None:
                raise ValueError("the boundary is too large for a copy per shard")
            got = boundary.toArrow()
            shards = materialise(rows.groupBy("part").applyInArrow(_build((_np(got["src"]), _np(got["dst"]))), _SHARD), "shards")
        return cls(edges, partitioner, parts, cut, shards, crossings, boundary, layout, shared, max_boundary)

    # -- storage -----------------------------------------------------------

    _TABLES = ("edges", "parts", "cut", "shards", "crossings", "boundary")

    def save(self, path: str) -> str:
        """Write the index under a new version of a folder that executors share; returns the version's path."""
        spark = self.edges.sparkSession
        version = f"{path.rstrip('/')}/v-{uuid.uuid4().hex}"
        for name in self._TABLES:
            if (df := getattr(self, name)) is not None:
                df.write.parquet(f"{version}/{name}")
        # the description comes last: a version without one is not complete
        facts = {"k": getattr(self.partitioner, "k", 1), "parts": self.parts is not None, "layout": self.layout, "max_boundary": self.max_boundary}
        spark.createDataFrame([(json.dumps(facts),)], "value string").coalesce(1).write.text(f"{version}/about")
        return version

    @classmethod
    def load(cls, spark: SparkSession, version: str) -> ReachIndex:
        """The index that ``save`` wrote, in any session that can read the folder."""
        facts = json.loads(spark.read.text(f"{version}/about").first().value)
        got = {name: spark.read.parquet(f"{version}/{name}") for name in cls._TABLES if name != "parts" or facts["parts"]}
        shared = _shared(got["boundary"], got["cut"], facts["max_boundary"])
        return cls(**({"parts": None} | got), partitioner=HashPartitioner(facts["k"]), layout=facts["layout"], shared=shared, max_boundary=facts["max_boundary"])

    def with_edges(self, more: DataFrame) -> ReachIndex:
        """This index with further edges (s, t): only shards that a new edge touches are built again, then the boundary."""
        if self.layout != "shared":
            raise ValueError("an index with a copy of the boundary per shard is built anew")
        fresh = materialise(more.where("s is not null and t is not null").select("s", "t").distinct().join(self.edges, ["s", "t"], "left_anti"), "edges")
        edges, k = self.edges.unionByName(fresh), getattr(self.partitioner, "k", None) or int(self.parts.agg(F.max("part")).first()[0]) + 1
        parts = self.parts
        if parts is not None:
            unknown = fresh.select(F.col("s").alias("v")).union(fresh.select("t")).distinct().join(parts, "v", "left_anti")
            parts = materialise(parts.unionByName(unknown.withColumn("part", F.pmod("v", F.lit(k)).cast("int"))), "parts")
        place = lambda df: _place(_place(df, "s", "ps", self.partitioner, parts), "t", "pt", self.partitioner, parts)
        placed = materialise(place(fresh), "placed")
        touched = placed.select(F.col("ps").alias("part")).union(placed.select("pt")).distinct()
        held = F.broadcast(touched)  # at most one row per shard
        cut = self.cut.unionByName(placed.where("ps <> pt").select(*self.cut.columns))
        rows = _shard_rows(place(edges).where("ps = pt"), cut).join(held, "part", "left_semi")
        new = materialise(rows.groupBy("part").applyInArrow(_build(None), _SHARD), "shards")
        crossed = new.mapInArrow(_crossings, "part int, entry long, exit long")
        shards = self.shards.join(held, "part", "left_anti").unionByName(new)
        crossings = materialise(self.crossings.join(held, "part", "left_anti").unionByName(crossed), "crossings")
        boundary = _boundary(crossings, cut)
        return ReachIndex(edges, self.partitioner, parts, cut, shards, crossings, boundary, "shared", _shared(boundary, cut, self.max_boundary), self.max_boundary)

    def backward(self) -> ReachIndex:
        """The index of the reversed edges, over the same shards; built when first asked for."""
        if not hasattr(self, "_backward"):
            turned = self.edges.select(F.col("t").alias("s"), F.col("s").alias("t"))
            again = self.partitioner if self.parts is None else _Given(self.parts)
            self._backward = ReachIndex.build(turned, getattr(self.partitioner, "k", 8), again, layout=self.layout, max_boundary=self.max_boundary)
        return self._backward

    # -- questions ---------------------------------------------------------

    def place(self, df: DataFrame, vertex: str, part: str) -> DataFrame:
        """Add the shard of a vertex column; vertices without edges drop out."""
        return _place(df, vertex, part, self.partitioner, self.parts)

    def mail(self, sources: DataFrame) -> DataFrame:
        """(s, entry): which entries of which shards the sources reach over the boundary, those that others stand for left out."""
        out = self._depart(sources, None)
        return self._letters(out).withColumnRenamed("s", "cls").join(_members(out, _FAR_MEMBER, "s"), "cls").select("s", "e")

    def _letters(self, departed: DataFrame) -> DataFrame:
        """(s, e): classes of sources and the entries that they reach."""
        far = _role(departed, _FAR)
        return self._cross_by_joins(far.toDF("x", "y")) if self.shared is None else far.toDF("s", "e")

    def set_reach(self, sources: DataFrame, targets: DataFrame, kind: str = "+", *, plus: str = "distinct", zero_scope: str = "domain", direction: str = "forward") -> DataFrame:
        """Distinct pairs (x, y), x from ``sources(v)`` and y from ``targets(v)``, such that y is reachable from x.

        ``kind`` is ``*``, ``+`` or ``?``. For ``+`` the ends differ, unless
        ``plus="cycle"`` lets x reach itself over a cycle. For ``*`` and ``?``
        every x that is a target reaches itself; with ``zero_scope="vertices"``
        only vertices of this property do. ``direction="backward"`` goes from the
        targets over reversed edges, ``"auto"`` does so where they are fewer by far.
        """
        if direction == "auto":
            direction = "backward" if 10 * targets.count() < sources.count() else "forward"
        if direction == "backward" and kind != "?":
            pairs = self.backward().set_reach(targets, sources, kind, plus=plus, zero_scope=zero_scope)
            return pairs.select(F.col("y").alias("x"), F.col("x").alias("y"))
        sources, targets = sources.select("v").where("v is not null").distinct(), targets.select("v").where("v is not null").distinct()
        if kind == "?":
            return one_step(self.edges, sources, targets, zero_scope)
        out = self._depart(sources, targets)
        pairs = _spelled(_role(out, _NEAR).toDF("cls", "y"), _members(out, _NEAR_MEMBER, "x"))
        crossed = not self.cut.isEmpty()
        if crossed:
            pairs = pairs.union(_spelled(self._arrive(self._letters(out), targets).toDF("cls", "y"), _members(out, _FAR_MEMBER, "x")))
        if kind == "*":
            pairs = pairs.union(same(self.edges, sources, targets, zero_scope))
        elif plus == "distinct":
            pairs = pairs.where("x <> y")
        return pairs.distinct() if crossed or kind == "*" else pairs  # within one shard a pair is found once

    def on_cycles(self, vertices: DataFrame) -> DataFrame:
        """(v): those of ``vertices(v)`` that reach themselves over an edge or more; each is followed home in its own shard's task."""
        ends = self.place(vertices.select("v").where("v is not null").distinct(), "v", "part").select("part", F.lit(0).alias("kind"), F.col("v").alias("a"), F.col("v").alias("b"))
        if self.shared is None:
            pairs = self.set_reach(vertices, vertices, "+", plus="cycle")
            return pairs.where("x = y").select(F.col("x").alias("v"))
        shared, compound = self.shared, self.layout == "compound"

        def run(row: dict[str, np.ndarray], kind: np.ndarray, a: np.ndarray, b: np.ndarray) -> Iterator[pa.RecordBatch]:
            dag, (boundary, entries, _) = _dag(row), shared.value
            a = np.unique(a)
            at, comp = dag.place(_local(a) if compound else a)
            a, own = a[at], dag.cyclic[comp]
            yield _out(0, a[own], a[own])
            if compound or not len(row["exits"]) or not len(row["entries"]):
                return
            a, comp = a[~own], comp[~own]
            yield from (_out(0, found, found) for found in _homeward(dag, boundary, row, a, comp))

        return self._by_shard(ends, run).select(F.col("a").alias("v"))

    def _by_shard(self, ends: DataFrame, run: Callable[..., Iterator[pa.RecordBatch]]) -> DataFrame:
        """(role, a, b): what ``run`` makes of each shard and the rows (part, kind, a, b) that belong to it."""

        def both(left: pa.Table, right: pa.Table) -> pa.Table:
            made = run(next(_rows(right)), *(_np(left[c]) for c in ("kind", "a", "b"))) if left.num_rows and right.num_rows else ()
            return pa.Table.from_batches(list(made), schema=_ROLES)

        k = getattr(self.partitioner, "k", 8)
        return _apart(ends, k).groupBy("part").cogroup(_apart(self.shards, k).groupBy("part")).applyInArrow(both, "role int, a long, b long")

    def _depart(self, sources: DataFrame, targets: DataFrame | None) -> DataFrame:
        """(role, a, b): classes of the sources, what they reach in their shard, and the entries that they reach elsewhere.

        Where the boundary is not shared, exits stand in place of entries.
        """
        ends = self.place(sources, "v", "part").select("part", F.lit(0).alias("kind"), F.col("v").alias("a"), F.col("v").alias("b"))
        if targets is not None:
            ends = ends.union(self.place(targets, "v", "part").select("part", F.lit(1), "v", "v"))
        shared, compound = self.shared, self.layout == "compound"

        def run(row: dict[str, np.ndarray], kind: np.ndarray, a: np.ndarray, b: np.ndarray) -> Iterator[pa.RecordBatch]:
            if not (kind == 0).any():
                return
            dag = _dag(row)
            here, back = (_local, lambda v: v // 4) if compound else ((lambda v: v),) * 2
            members, heads = dag.heads(here(a[kind == 0]))
            names, number = np.unique(heads, return_inverse=True)
            if (kind == 1).any():
                yield _out(_NEAR_MEMBER, back(members), back(heads))
                for x, y in dag.reach_by_blocks(names, names, here(a[kind == 1]), empty_path=False):
                    yield _out(_NEAR, back(x), back(y))
            boundary, entries, reps = shared.value if shared is not None else (None, row["exits"], row["exits"])
            reps = np.unique(reps)
            if not len(reps) or not len(row["exits"]) and not compound:
                return
            if compound:
                at, end = dag.place(_entry(reps))
                over, reps, more = dag, reps[at], 0
            elif boundary is None:
                at, end = dag.place(reps)
                over, reps, more = dag, reps[at], 0
            else:
                _, end = boundary.place(_entry(reps))
                at, gate = boundary.place(_exit(row["exits"]))
                _, leave = dag.place(row["exits"][at])
                over, more = boundary, len(boundary.cyclic)
            _, start = dag.place(names)
            cls = np.empty(len(names), dtype=np.int64)

            def lead(lo: int, size: int) -> tuple[np.ndarray, np.ndarray] | None:
                walked = dag.walk(np.arange(size), start[lo : lo + size], WALK_PAIRS)
                if walked is not None and over is boundary:
                    walked = boundary.walk(*joined(*walked, leave, gate), WALK_PAIRS)
                return None if walked is None else joined(*walked, end, reps)

            lo, wide, block, sparse = 0, WALK, dag.block(more), True
            while lo < len(names):
                size = min(wide, len(names) - lo)
                led = lead(lo, size) if sparse else None
                if led is None and size > block:
                    wide = max(block, size // 4)
                    continue
                sparse = led is not None
                if sparse:
                    first, who, met = _equal_sets(*led, size)
                    yield _out(_FAR, back(names[lo + who]), met)
                else:
                    rows = np.zeros((len(dag.cyclic), (size + 63) // 64), dtype=np.uint64)
                    set_bits(rows, start[lo : lo + size], np.arange(size))
                    rows = dag.spread(rows)
                    if over is boundary:
                        inner, rows = rows, np.zeros((len(boundary.cyclic), rows.shape[1]), dtype=np.uint64)
                        np.bitwise_or.at(rows, gate, inner[leave])
                        rows = boundary.spread(rows)
                    first = equal_columns(rows[end], size)
                    for bit in np.flatnonzero(first == np.arange(size)):
                        met = reps[(rows[end, bit // 64] >> np.uint64(bit % 64)) & np.uint64(1) == 1]
                        yield _out(_FAR, np.full(len(met), back(names[lo + bit])), met)
                cls[lo : lo + size] = np.where(first >= 0, lo + first, -1)
                lo += size
            far = cls[number]
            yield _out(_FAR_MEMBER, back(members[far >= 0]), back(names[far[far >= 0]]))

        return materialise(self._by_shard(ends, run), "departed")

    def _arrive(self, mail: DataFrame, targets: DataFrame) -> DataFrame:
        """(s, y): targets that classes of sources reach from the entries that the mail names."""
        homes = self.place(targets, "v", "part")
        held = F.broadcast(homes.select("part").distinct())  # at most one row per shard
        letters = self.place(mail, "e", "part").join(held, "part", "left_semi")
        rows = letters.select("part", F.lit(0).alias("kind"), F.col("s").alias("a"), F.col("e").alias("b")).union(homes.select("part", F.lit(1), "v", "v"))
        shared, compound = self.shared, self.layout == "compound"

        def run(row: dict[str, np.ndarray], kind: np.ndarray, a: np.ndarray, b: np.ndarray) -> Iterator[pa.RecordBatch]:
            if not (kind == 0).any() or not (kind == 1).any():
                return
            dag, enc = _dag(row), _local if compound else (lambda v: v)
            targets, s, e = enc(a[kind == 1]), a[kind == 0], b[kind == 0]
            mine = stand = np.unique(e)
            if shared is not None:
                _, entries, reps = shared.value
                mine = row["entries"]
                stand = reps[np.searchsorted(entries, mine)]
            # entries by the one that stands for them
            by = np.argsort(stand, kind="stable")
            mine, stand = mine[by], stand[by]
            order = np.argsort(s, kind="stable")
            s, e = s[order], e[order]
            low, high = np.searchsorted(stand, e, "left"), np.searchsorted(stand, e, "right")
            total = np.concatenate([[0], np.cumsum(high - low)])
            lo = 0
            while lo < len(s):
                # whole sources, of some two million starts together
                hi = int(np.searchsorted(total, total[lo] + (2 << 20), "right")) - 1
                hi = int(np.searchsorted(s, s[min(max(hi, lo + 1), len(s)) - 1], "right"))
                count = high[lo:hi] - low[lo:hi]
                at = np.repeat(low[lo:hi] - (total[lo:hi] - total[lo]), count) + np.arange(count.sum())
                for x, y in dag.reach_by_blocks(np.repeat(s[lo:hi], count), enc(mine[at]), targets):
                    yield _out(0, x, y // 4 if compound else y)
                lo = hi

        return self._by_shard(rows, run).select(F.col("a").alias("s"), F.col("b").alias("y"))

    def _cross_by_joins(self, departed: DataFrame) -> DataFrame:
        """(s, e): entries behind the exits (x, y) reached, one join per step of the boundary graph."""
        steps, self.steps = self.boundary, 0
        front = departed.select(F.col("x").alias("s"), (F.col("y") * 4 + 2).alias("n")).distinct()
        seen = front = materialise(front, "front")
        while not front.isEmpty():
            after = front.join(steps, front["n"] == steps["src"]).select("s", F.col("dst").alias("n")).distinct()
            front = materialise(after.join(seen, ["s", "n"], "left_anti"), "front")
            seen = seen.union(front)
            self.steps += 1
        return seen.where("pmod(n, 4) = 1").select("s", F.shiftright("n", 2).alias("e"))


def same(edges: DataFrame, sources: DataFrame, targets: DataFrame, zero_scope: str) -> DataFrame:
    """(x, y): sources that are targets, with themselves; with ``zero_scope="vertices"`` only vertices of the edges."""
    both = sources.select("v").where("v is not null").distinct().join(targets, "v", "left_semi")
    if zero_scope == "vertices":
        known = edges.select(F.col("s").alias("v")).union(edges.select("t")).distinct()
        both = both.join(known, "v", "left_semi")
    return both.select(F.col("v").alias("x"), F.col("v").alias("y"))


def one_step(edges: DataFrame, sources: DataFrame, targets: DataFrame, zero_scope: str) -> DataFrame:
    """(x, y): pairs over one edge or none."""
    near = edges.join(sources.withColumnRenamed("v", "s"), "s", "left_semi").join(targets.withColumnRenamed("v", "t"), "t", "left_semi")
    return near.select(F.col("s").alias("x"), F.col("t").alias("y")).union(same(edges, sources, targets, zero_scope)).distinct()


def _apart(df: DataFrame, k: int) -> DataFrame:
    """Rows by shard, in so many tasks that few shards share one: they are few bytes and much work, which adaptive plans put together."""
    return df.repartition(3 * max(8, k), "part")


def _out(role: int, a: np.ndarray, b: np.ndarray) -> pa.RecordBatch:
    return pa.RecordBatch.from_arrays([pa.array(np.full(len(a), role, dtype=np.int32)), pa.array(a, type=pa.int64()), pa.array(b, type=pa.int64())], schema=_ROLES)


def _equal_sets(who: np.ndarray, met: np.ndarray, size: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(first, who, met): for each of ``size`` sources the first that meets the same, -1 where it meets none; the pairs of those that are first."""
    by = np.lexsort((met, who))
    who, met = who[by], met[by]
    first, known = np.full(size, -1, dtype=np.int64), {}
    ends = np.searchsorted(who, np.arange(size + 1))
    for i in np.flatnonzero(np.diff(ends)):
        first[i] = known.setdefault(met[ends[i] : ends[i + 1]].tobytes(), i)
    mine = first[who] == who
    return first, who[mine], met[mine]


def _homeward(dag: Dag, boundary: Dag, row: dict[str, np.ndarray], a: np.ndarray, comp: np.ndarray) -> Iterator[np.ndarray]:
    """Those of the vertices, one per component of a shard, that come back to themselves over the boundary."""
    at, gate = boundary.place(_exit(row["exits"]))
    _, leave = dag.place(row["exits"][at])
    at, door = boundary.place(_entry(row["entries"]))
    _, enter = dag.place(row["entries"][at])
    lo, wide, block, sparse = 0, WALK, dag.block(len(boundary.cyclic)), True
    while lo < len(a):
        size = min(wide, len(a) - lo)
        mine = comp[lo : lo + size]
        walked = dag.walk(np.arange(size), mine, WALK_PAIRS) if sparse else None
        walked = walked and boundary.walk(*joined(*walked, leave, gate), WALK_PAIRS)
        walked = walked and dag.walk(*joined(*walked, door, enter), WALK_PAIRS)
        if walked is None and size > block:
            wide = max(block, size // 4)
            continue
        lo, sparse = lo + size, walked is not None
        if sparse:
            who, there = walked
            yield a[lo - size : lo][who[there == mine[who]]]
            continue
        rows = np.zeros((len(dag.cyclic), (size + 63) // 64), dtype=np.uint64)
        set_bits(rows, mine, np.arange(size))
        inner, rows = dag.spread(rows), np.zeros((len(boundary.cyclic), rows.shape[1]), dtype=np.uint64)
        np.bitwise_or.at(rows, gate, inner[leave])
        outer, rows = boundary.spread(rows), np.zeros_like(inner)
        np.bitwise_or.at(rows, enter, outer[door])
        rows = dag.spread(rows)
        bit = np.arange(size)
        yield a[lo - size : lo][(rows[mine, bit // 64] >> (bit % 64).astype(np.uint64)) & np.uint64(1) == 1]


def _role(departed: DataFrame, role: int) -> DataFrame:
    return departed.where(F.col("role") == role).select("a", "b")


def _members(departed: DataFrame, role: int, name: str) -> DataFrame:
    return _role(departed, role).toDF(name, "cls")


def _spelled(found: DataFrame, members: DataFrame) -> DataFrame:
    """(x, y): what classes reach (cls, y), for each member (x, cls)."""
    n = 4 * found.sparkSession.sparkContext.defaultParallelism  # few rows may become very many, so none are put together
    return found.repartition(n, "cls").join(members.repartition(n, "cls"), "cls").select("x", "y")


@dataclass(frozen=True)
class _Given:
    """Shards that another index has."""

    table: DataFrame

    def parts(self, edges: DataFrame) -> DataFrame:
        return self.table


def _shard_rows(inner: DataFrame, cut: DataFrame) -> DataFrame:
    """(part, kind, a, b): edges of each shard, its entries and its exits."""
    none = F.lit(0).cast("long")
    return (
        inner.select(F.col("ps").alias("part"), F.lit(0).alias("kind"), F.col("s").alias("a"), F.col("t").alias("b"))
        .union(cut.select("pt", F.lit(1), "t", none).distinct())
        .union(cut.select("ps", F.lit(2), "s", none).distinct())
    )


def _shared(boundary: DataFrame, cut: DataFrame, max_boundary: int) -> object:
    """Broadcast of the boundary's DAG, its entries and those that stand for them; None where it has too many edges.

    The smallest entry stands for all of its shard that lie in one component of the boundary.
    """
    if boundary.limit(max_boundary + 1).count() > max_boundary:
        return None
    got = boundary.toArrow()
    homes = cut.select("t", "pt").distinct().toArrow()
    entries, part = _np(homes["t"]), _np(homes["pt"])
    by = np.argsort(entries)
    entries, part = entries[by], part[by]
    dag = Dag.of(_np(got["src"]), _np(got["dst"]), _entry(entries))
    _, comp = dag.place(_entry(entries))
    _, first, which = np.unique(np.stack([comp, part], axis=1), axis=0, return_index=True, return_inverse=True)
    return boundary.sparkSession.sparkContext.broadcast((dag, entries, entries[first[which.ravel()]]))


def choose_partitioner(edges: DataFrame, k: int, most_cut: float = 0.3, room: float = 1.5) -> object:
    """Whole components, if hashing would cut many edges and no component is much larger than a shard; else hashing.

    Chains and other small components then lie in one shard each, nothing is
    cut, and no binding is mailed.
    """
    placed = edges.agg(F.count(F.lit(1)).alias("n"), F.sum((F.pmod("s", F.lit(k)) != F.pmod("t", F.lit(k))).cast("long")).alias("cut")).first()
    if not placed.n or placed.cut < most_cut * placed.n:
        return HashPartitioner(k)
    parts = materialise(weak_components(edges), "labels")
    largest = parts.groupBy("label").agg(F.count(F.lit(1)).alias("n")).agg(F.max("n").alias("most"), F.sum("n").alias("all")).first()
    if largest.most > room * largest["all"] / k:
        return HashPartitioner(k)
    return _Given(materialise(parts.join(packed(parts, k), "label").select("v", "part"), "parts"))


def _place(df: DataFrame, vertex: str, part: str, partitioner: object, parts: DataFrame | None) -> DataFrame:
    if parts is None:
        return partitioner.place(df, vertex, part)
    return df.join(parts.select(F.col("v").alias(vertex), F.col("part").alias(part)), vertex)


def _cut_steps(cut: DataFrame) -> DataFrame:
    return cut.select((F.col("s") * 4 + 2).alias("src"), (F.col("t") * 4 + 1).alias("dst"))


def _plain(crossings: DataFrame, cut: DataFrame) -> DataFrame:
    """Boundary graph without classes."""
    return crossings.select((F.col("entry") * 4 + 1).alias("src"), (F.col("exit") * 4 + 2).alias("dst")).union(_cut_steps(cut)).distinct()


def _boundary(crossings: DataFrame, cut: DataFrame, compress: bool = True) -> DataFrame:
    """Boundary graph over classes where that has fewer edges, else the plain one."""
    plain = materialise(_plain(crossings, cut), "boundary")
    if not compress:
        return plain
    small = materialise(_compressed(crossings, cut), "boundary")
    return small if small.count() < plain.count() else plain


def classes(crossings: DataFrame) -> tuple[DataFrame, DataFrame]:
    """((part, entry, cls), (part, exit, cls)): members with equal partner sets share a class."""
    ins = crossings.groupBy("part", "entry").agg(F.sort_array(F.collect_set("exit")).alias("to"))
    ins = ins.join(ins.groupBy("part", "to").agg(F.min("entry").alias("cls")), ["part", "to"]).select("part", "entry", "cls")
    outs = crossings.groupBy("part", "exit").agg(F.sort_array(F.collect_set("entry")).alias("by"))
    outs = outs.join(outs.groupBy("part", "by").agg(F.min("exit").alias("cls")), ["part", "by"]).select("part", "exit", "cls")
    return ins, outs


def _compressed(crossings: DataFrame, cut: DataFrame) -> DataFrame:
    """Boundary graph over classes: entry, its class, the classes of exits, the entries that their members lead to.

    Departures still start at real exits, and arrivals end at real entries.
    """
    ins, outs = (materialise(c, "classes") for c in classes(crossings))
    # a class is named by its smallest member, with the two upper kinds of id told apart by sign
    icls, ocls = (F.col("icls") * 4 + 3), -(F.col("ocls") * 4 + 3)
    a = ins.select((F.col("entry") * 4 + 1).alias("src"), (F.col("cls") * 4 + 3).alias("dst"))
    named = crossings.join(ins.withColumnRenamed("cls", "icls"), ["part", "entry"]).join(outs.withColumnRenamed("cls", "ocls"), ["part", "exit"])
    b = named.select(icls.alias("src"), ocls.alias("dst"))
    c = cut.join(outs.select(F.col("exit").alias("s"), F.col("cls").alias("ocls")), "s").select(ocls.alias("src"), (F.col("t") * 4 + 1).alias("dst"))
    return a.union(b).union(c).union(_cut_steps(cut)).distinct()
