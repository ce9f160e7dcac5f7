"""Graphs to ask: properties as edge tables, indexes on demand, plans run as DataFrames."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from reachgraph.operators.condensed import CondensedIndex, layered, reach_over
from reachgraph.operators.permutations import PropertyStore
from reachgraph.operators.reach_index import ReachIndex
from reachgraph.plans.optimizer import Optimizer, Plan, bound_to, choose_permutation, solid_ends
from reachgraph.plans.query import Const, Dashed, Query, QueryGraph, Solid, Var, column, normalise, parse
from reachgraph.plans.statistics import Catalog, pair_selectivity, reach_selectivity, sizes
from reachgraph.session import materialise


#: Rows that equal columns may join into before a predicate's pairs are looked at instead.
CROWD = 1_000_000
#: Ids from here on have no room for the bit that tells the copies of a layered graph apart.
WIDE = 1 << 61


class Graph:
    """Properties by name, each as edges (s, o).

    Edges are written to a ``PropertyStore``, indexes for paths are built and
    statistics gathered when a query first asks for them. With ``measured=False``
    plans are made from guesses. Names such as ``(p|q)`` and ``(p/q|r)`` stand
    for the edges of alternatives of sequences of properties.
    """

    def __init__(
        self,
        spark: SparkSession,
        properties: dict[str, Callable[[], DataFrame]],
        constant: Callable[[Const], int | None],
        *,
        k: int | None = None,
        plus: str = "distinct",
        catalog: Catalog | None = None,
        measured: bool = True,
        **index_options: object,
    ) -> None:
        self.spark, self.properties, self.constant = spark, properties, constant
        self.k, self.plus, self.catalog, self.measured = k, plus, catalog or Catalog(k or 8), measured
        self.index_options = index_options
        self.store = PropertyStore(spark, k or 8)
        self._indexes: dict[str, CondensedIndex | ReachIndex] = {}

    def rows(self, prop: str) -> DataFrame:
        """Edges of a property as its source gives them, or of a group of them."""
        if prop in self.properties:
            return self.properties[prop]()
        if not prop.startswith("("):
            raise KeyError(f"unknown property {prop!r}")
        out = None
        for way in prop.strip("()").split("|"):
            steps = way.split("/")
            one = self.edges(steps[0]).toDF("s", "o")
            for step in steps[1:]:
                one = one.withColumnRenamed("o", "m").join(self.edges(step, "s").toDF("m", "o"), "m").select("s", "o")
            out = one if out is None else out.union(one)
        return out

    def edges(self, prop: str, by: str = "s") -> DataFrame:
        """Distinct edges (s, o) of a property, placed and sorted by subject (PSO) or by object (POS)."""
        return self.store.table(prop, by, lambda: self.rows(prop))

    def index(self, prop: str) -> CondensedIndex | ReachIndex:
        """Reachability index of a property, its cycles tied up unless shards are given."""
        if prop not in self._indexes:
            edges = self.edges(prop).withColumnRenamed("o", "t")
            given = self.k is not None or self.index_options.get("partitioner") is not None
            self._indexes[prop] = ReachIndex.build(edges, self.k, **self.index_options) if given else CondensedIndex.build(edges, **self.index_options)
        return self._indexes[prop]

    def index_over(self, prop: str, middle: DataFrame, name: str) -> CondensedIndex | ReachIndex:
        """Index of a property's paths that come over a vertex of ``middle(v)``, kept under the property and a name."""
        key = f"{prop} over {name}"
        if key not in self._indexes:
            self._indexes[key] = CondensedIndex.build(layered(self.index(prop).edges, middle), **self.index_options)
        return self._indexes[key]

    def measure(self, graph: QueryGraph) -> Catalog:
        """Fill the catalog with what a query's plan depends on and is not known yet.

        Sizes of properties, rows of constants, join selectivities of the pairs
        of properties that are joined, selectivities of paths, sampled among the
        vertices that the constants at their ends leave.
        """
        known = self.catalog
        plain = [v.pattern for v in graph.vertices if v.kind == "plain" and isinstance(v.pattern.path[0].prop, str)]
        for p in {q.path[0].prop for q in plain} | {c.prop for c in graph.dashed}:
            if p not in known.n_edges:
                known.n_edges[p], known.n_subjects[p], known.n_objects[p], known.n_vertices[p] = sizes(self.edges(p))
        for q in plain:
            for slot, term in (("s", q.s), ("o", q.o)):
                key = (q.path[0].prop, slot, str(term))
                if isinstance(term, Const) and key not in known.key_rows:
                    value = self.constant(term)
                    known.key_rows[key] = 0 if value is None else self.edges(key[0], slot).where(F.col(slot) == F.lit(value)).count()
        for key in filter(None, (solid_ends(c, graph) for c in graph.solid)):
            if key not in known.join_sel:
                p, q, position = key
                known.join_sel[key] = pair_selectivity(self.edges(p, position[0].lower()), self.edges(q, position[1].lower()), position)
        for c in graph.dashed:
            (x, xs), (y, ys) = bound_to(c.x, graph), bound_to(c.y, graph)
            key = (c.prop, x, y) if x or y else c.prop
            if key not in known.reach_sel:
                known.reach_sel[key] = reach_selectivity(self.index(c.prop), sources=self.bound(xs), targets=self.bound(ys)).sel
        return known

    def bound(self, patterns: list[tuple[str, str, Const]]) -> DataFrame | None:
        """(v): what meets all of these patterns (property, slot of the vertex, constant); None without patterns."""
        out = None
        for prop, slot, term in patterns:
            other, value = "o" if slot == "s" else "s", self.constant(term)
            one = self.edges(prop, other).where(F.lit(False) if value is None else F.col(other) == F.lit(value)).select(F.col(slot).alias("v"))
            out = one if out is None else out.join(one, "v", "left_semi")
        return out

    def prepare(self, query: Query | str, choice: bool = False) -> QueryGraph:
        """The query's graph, with its statistics gathered; with ``choice`` only where a plan depends on them."""
        graph = QueryGraph.of(normalise(parse(query) if isinstance(query, str) else query))
        if self.measured and not (choice and _one_way(graph)):
            self.measure(graph)
        return graph

    # -- asking ------------------------------------------------------------

    def plan(self, query: Query | str, optimizer: str = "unified", cardinality: str = "chain") -> Plan:
        return Optimizer(self.prepare(query), self.catalog, optimizer, cardinality).best()

    def match(self, query: Query | str, optimizer: str = "unified") -> DataFrame:
        """Bindings of a query, one long column per selected variable."""
        query = normalise(parse(query) if isinstance(query, str) else query)
        graph = self.prepare(query, choice=True)
        run = _Run(self, graph)
        plan = Optimizer(graph, self.catalog, optimizer).best()
        out = run.chained(plan, query)
        out = run.of(plan) if out is None else out
        for c in graph.dashed:  # both ends on one relation
            if c.number not in run.settled:
                out = run.reach(out, c)
        out = out.select(*[F.col(f"`{c}`") for c in query.select])
        return out.distinct() if query.distinct and not run.unique else out

    def explain(self, query: Query | str, optimizer: str = "unified", analyze: bool = False) -> DataFrame:
        """(step, what, estimated, cost, actual) of the plan, leaves last; ``analyze`` counts the rows of every step."""
        graph = self.prepare(query)
        rows: list[tuple] = []

        def walk(p: Plan) -> None:
            actual = _Run(self, graph).of(p).count() if analyze else None
            rows.append((len(rows), p.show()[0].split(" [")[0], float(p.rows), float(p.cost), actual))
            for side in (p.left, p.right):
                if side:
                    walk(side)

        walk(Optimizer(graph, self.catalog, optimizer).best())
        return self.spark.createDataFrame(rows, "step int, what string, estimated double, cost double, actual long")

    def sql_view(self, name: str, query: Query | str) -> None:
        """Register the bindings of a query as a view."""
        self.match(query).createOrReplaceTempView(name)


def _one_way(graph: QueryGraph) -> bool:
    """Whether there is one plan only: at most two vertices, and no more than one condition between them."""
    return len(graph.vertices) <= 2 and len(graph.solid) + len(graph.dashed) <= 1


def _chain(plan: Plan, query: Query, graph: QueryGraph) -> tuple[Dashed, Dashed, Plan, Plan, Plan] | None:
    """(first, second, left, middle, right) of a plan that ends in two predicates of one property in a row, whose middle no one asks for."""
    if not query.distinct or plan.op != "reach" or len(plan.conditions) != 1:
        return None
    for inner, outer in ((plan.left, plan.right), (plan.right, plan.left)):
        if inner.op != "reach" or len(inner.conditions) != 1:
            continue
        both, parts = (plan.conditions[0], inner.conditions[0]), (inner.left, inner.right, outer)
        names = [frozenset().union(*(graph.vertices[i].variables() for i in p.members)) for p in parts]
        for first, second in (both, both[::-1]):
            if first.prop != second.prop or first.y != second.x or "?" in (first.mark, second.mark):
                continue
            at = [[k for k, n in enumerate(names) if end in n] for end in (first.x, first.y, second.y)]
            if any(len(k) != 1 for k in at) or len({k[0] for k in at}) != 3:
                continue
            used = {end for c in graph.dashed if c.number not in (first.number, second.number) for end in (c.x, c.y)}
            if not names[at[1][0]] & (used | set(query.select)):
                return first, second, *(parts[k[0]] for k in at)
    return None


class _Run:
    """A plan as a DataFrame."""

    def __init__(self, graph: Graph, query: QueryGraph) -> None:
        self.graph, self.query = graph, query
        self.settled: set[int] = set()
        self.unique = False  # whether the rows are known to be distinct

    def of(self, plan: Plan, key: str | None = None) -> DataFrame:
        """The rows of a plan; a scan takes the permutation that is placed by ``key``, if it can."""
        if plan.op == "scan":
            return self.scan(plan.vertex, key)
        equal = [c.var for c in plan.conditions if isinstance(c, Solid)]
        reach = [c for c in plan.conditions if isinstance(c, Dashed)]
        left, right = (self.of(side, equal[0] if equal else None) for side in (plan.left, plan.right))
        if plan.op == "merge":
            return left.join(right.hint("merge"), equal)
        if plan.op == "hash":
            return left.join(right, equal)  # Spark picks the side to build, and broadcasts it if it is small
        if plan.op == "cross":
            return left.crossJoin(right)
        return reach_join(left, right, equal, reach, self)

    def scan(self, i: int, key: str | None = None) -> DataFrame:
        v = self.query.vertices[i]
        if v.kind == "constant":
            value = self.graph.constant(v.term)
            return self.graph.spark.createDataFrame([] if value is None else [(value,)], f"`{column(v.term)}` long")
        if v.kind == "unbound":
            out = None
            for p in v.props:
                e = self.graph.edges(p)
                one = e.select(F.col("s").alias(v.term.name)).union(e.select("o")).distinct()
                out = one if out is None else out.intersect(one)
            return out
        s, prop, o = v.pattern.s, v.pattern.path[0].prop, v.pattern.o
        if isinstance(prop, Var):
            names = sorted(self.graph.properties)
            df = None
            for k, name in enumerate(names):
                one = self.graph.edges(name).withColumn("p", F.lit(k).cast("long"))
                df = one if df is None else df.union(one)
        else:
            # constants first, then the column that the rows are joined on
            first = choose_permutation("p" + "".join(c for c, t in (("s", s), ("o", o)) if not isinstance(t, Var)), "o" if o == Var(key or "") else "s")
            df = self.graph.edges(prop, "o" if first.index("O") < first.index("S") else "s")
        keep = {}
        for c, t in (("s", s), ("p", prop), ("o", o)):
            if c == "p" and not isinstance(prop, Var):
                continue
            if isinstance(t, Var):
                if t.name in keep:
                    df = df.where(F.col(c) == F.col(keep[t.name]))
                else:
                    keep[t.name] = c
            else:
                value = self.graph.constant(t)
                df = df.where(F.col(c) == F.lit(value)) if value is not None else df.where(F.lit(False))
        return df.select(*[F.col(c).alias(name) for name, c in keep.items()]) if keep else df.limit(1).select(F.lit(1).cast("long").alias("_"))

    def pairs(self, x: DataFrame, y: DataFrame, c: Dashed) -> DataFrame:
        """(x, y) of a predicate between two sets of vertices (v)."""
        self.settled.add(c.number)
        return self.graph.index(c.prop).set_reach(x, y, c.mark, plus=self.graph.plus)

    def chained(self, plan: Plan, query: Query) -> DataFrame | None:
        """Rows of a plan that ends in a ``_chain`` without those of its middle; None for other plans.

        The pairs of both predicates, joined on a middle that nobody asks for,
        would be many times the pairs of their outer ends. These come from one
        index whose paths lead over the middle. Where ``+`` leaves from or ends
        in the middle itself, such a path could stay where it is; these few ends
        take the pairs of both predicates.
        """
        if (chain := _chain(plan, query, self.query)) is None:
            return None
        first, second, *sides = chain
        rows = [p.rows for p in sides]
        sel = [self.graph.catalog.reach(c.prop, (bound_to(c.x, self.query)[0], bound_to(c.y, self.query)[0])) for c in (first, second)]
        index = self.graph.index(first.prop)
        if rows[0] * rows[1] * rows[2] * sel[0] * sel[1] <= CROWD or not isinstance(index, CondensedIndex):
            return None
        l, m, r = (self.of(p) for p in sides)
        ends = lambda df, name: materialise(df.select(F.col(f"`{name}`").alias("v")).distinct(), "ends")
        x, middle, y = ends(l, first.x), ends(m, first.y), ends(r, second.y)
        every = index.edges.select(F.col("s").alias("v")).union(index.edges.select("t")).union(x).union(middle).union(y)
        if not every.where((F.col("v") >= WIDE) | (F.col("v") <= -WIDE)).isEmpty():
            return None
        self.settled |= {first.number, second.number}
        name = " ".join(str(self.query.vertices[i].pattern or self.query.vertices[i].term) for i in sorted(sides[1].members))
        over = self.graph.index_over(first.prop, middle, f"{first.y}: {name}")
        x_in, y_in = (df.join(middle, "v", "left_semi") if c.mark == "+" else df.limit(0) for df, c in ((x, first), (y, second)))
        x_out, y_out = x.join(x_in, "v", "left_anti"), y.join(y_in, "v", "left_anti")
        pairs, self.unique = reach_over(over, x_out, y_out), True
        for a, b, some in ((x_in, y, x_in), (x_out, y_in, y_in)):
            if not some.isEmpty():
                pairs = pairs.union(self.pairs(a, middle, first).toDF("x", "m").join(self.pairs(middle, b, second).toDF("m", "y"), "m").select("x", "y"))
                self.unique = False
        out = pairs.toDF(first.x, second.y)
        for df, end in ((l, first.x), (r, second.y)):
            if df.columns != [end]:  # else its rows are the ends that were asked for
                out, self.unique = out.join(df, end), False
        self.unique = self.unique and set(query.select) == {first.x, second.y}
        return out

    def crowded(self, left: DataFrame, right: DataFrame, equal: list[str], c: Dashed) -> bool:
        """Whether equal columns alone would join into many more rows than the predicate has pairs."""
        count = lambda df, n: df.groupBy(*[F.col(f"`{e}`") for e in equal]).agg(F.count(F.lit(1)).alias(n))
        met = count(left, "_l").join(count(right, "_r"), equal, "full").agg(F.sum(F.col("_l").cast("double") * F.col("_r")), F.sum("_l"), F.sum("_r")).first()
        ends = tuple(bound_to(end, self.query)[0] for end in (c.x, c.y))
        return (met[0] or 0) > max(CROWD, self.graph.catalog.reach(c.prop, ends) * (met[1] or 0) * (met[2] or 0))

    def reach(self, df: DataFrame, c: Dashed) -> DataFrame:
        """Rows whose two columns meet the predicate."""
        ends = lambda name: df.select(F.col(f"`{name}`").alias("v")).distinct()
        if c.x == c.y:
            same = self.pairs(ends(c.x), ends(c.y), c).where("x = y").select(F.col("x").alias(c.x))
            return df.join(same, c.x, "left_semi")
        if c.mark != "?" and isinstance(index := self.graph.index(c.prop), CondensedIndex):
            self.settled.add(c.number)
            return index.meets(df, c.x, c.y, c.mark, plus=self.graph.plus)
        pairs = self.pairs(ends(c.x), ends(c.y), c).select(F.col("x").alias(c.x), F.col("y").alias(c.y))
        return df.join(pairs, [c.x, c.y], "left_semi")


def reach_join(left: DataFrame, right: DataFrame, equal: list[str], reach: list[Dashed], run: _Run) -> DataFrame:
    """Rows of both sides with equal shared columns that meet every reachability predicate.

    With shared columns the sides are joined on them first and each predicate is
    a semi-join. Without, or where they would join into very many rows, the
    pairs of the first predicate connect the sides.
    """
    apart = bool(reach) and all((reach[0].x in df.columns) != (reach[0].y in df.columns) for df in (left, right))
    if equal and not (apart and run.crowded(left, right, equal, reach[0])):
        out = left.join(right, equal)
    else:
        c, reach = reach[0], reach[1:]
        l, r = (left, right) if c.x in left.columns else (right, left)
        ends = lambda df, name: df.select(F.col(f"`{name}`").alias("v")).distinct()
        pairs = run.pairs(ends(l, c.x), ends(r, c.y), c).select(F.col("x").alias(c.x), F.col("y").alias(c.y))
        out = l.join(pairs, c.x).join(r, [c.y, *equal])
    for c in reach:
        out = run.reach(out, c)
    return out
