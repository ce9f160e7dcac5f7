"""Every method and experiment as a query over a directory of tables, with the SQL that tells the same.

Results carry table keys, not tagged ids. The SQL closes the edge rule with a
recursive UNION, seeded from the sources where they are few.
"""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from reachgraph.functions.ids import BASE, KINDS, literal_number, term_key
from reachgraph.operators import baselines
from reachgraph.operators.condensed import CondensedIndex
from reachgraph.operators.partition import HashPartitioner, LocalityPartitioner, RangePartitioner, weak_components
from reachgraph.operators.permutations import shard_triples
from reachgraph.operators.reach_index import ReachIndex, classes
from reachgraph.plans import statistics
from reachgraph.plans.engine import Graph
from reachgraph.plans.query import Const
from reachgraph.sources.graphs import NEAR_SQL, RULES, duck_sql, edges, spark_sql
from reachgraph.sources.triples import dictionary, properties, property_ids, sound_dictionary, to_triples

Query = Callable[[SparkSession, str], DataFrame]

QUERIES: dict[str, Query] = {}
ORACLE: dict[str, str] = {}

_graphs: dict[tuple, object] = {}


def query(sql: str | None = None, name: str | None = None) -> Callable[[Query], Query]:
    """Register a query and its SQL."""

    def add(f: Query) -> Query:
        QUERIES[name or f.__name__] = f
        if sql:
            ORACLE[name or f.__name__] = duck_sql(sql)
        return f

    return add


def _kept(spark: SparkSession, *key: object, make: Callable[[], object]) -> object:
    """One of a kind per Spark application: indexes and graphs serve all queries of a session."""
    key = (spark.sparkContext.applicationId, *key)
    if key not in _graphs:
        _graphs[key] = make()
    return _graphs[key]


def constant(c: Const) -> int | None:
    """Id of a constant: ``kind/key``, or a literal by the hash that ``literal_id`` takes of its text."""
    if not c.literal:
        kind, _, key = c.text.partition("/")
        return KINDS[kind] * BASE + int(key) if kind in KINDS and key.isdigit() else None
    return literal_number(c.text)


def graph(spark: SparkSession, sf_dir: str, **options: object) -> Graph:
    """The property graph of a directory."""
    return _kept(spark, sf_dir, "graph", *sorted(options.items()), make=lambda: Graph(spark, properties(spark, sf_dir), constant, **options))


def index(spark: SparkSession, sf_dir: str, name: str, **options: object) -> ReachIndex:
    """Reachability index of a graph under test, on untagged keys."""
    return _kept(spark, sf_dir, name, *map(str, sorted(options.items(), key=str)), make=lambda: ReachIndex.build(edges(spark, sf_dir, name), options.pop("k", None), **options))


def tied(spark: SparkSession, sf_dir: str, name: str, **options: object) -> CondensedIndex | ReachIndex:
    """The same with the graph's cycles tied up first, unless shards are given."""
    if {"k", "partitioner"} & options.keys():
        return index(spark, sf_dir, name, **options)
    return _kept(spark, sf_dir, name, "tied", *map(str, sorted(options.items(), key=str)), make=lambda: CondensedIndex.build(edges(spark, sf_dir, name), **options))


def match(spark: SparkSession, sf_dir: str, text: str, keep: str = "") -> DataFrame:
    """Run a query text and strip the kinds off its bindings."""
    df = graph(spark, sf_dir).match(text)
    names = keep.split() or df.columns
    return df.select(*[term_key(F.col(f"`{c}`")).alias(c) for c in names])


def walk(rule: str, seed: str = "SELECT a, b FROM e", more: str = "") -> str:
    """WITH clause: edges e(a, b) of a rule and r(x, y), the pairs over one edge or more from a seed."""
    text = RULES.get(rule, rule)
    return f"WITH RECURSIVE e(a, b) AS ({text}), r(x, y) AS ({seed} UNION SELECT r.x, e.b FROM r JOIN e ON r.y = e.a){more} "


# -- workloads ---------------------------------------------------------------

#: The query texts of the workloads.
TEXTS = {
    "wl1": 'SELECT ?x ?y WHERE { ?x type "ECONOMY" . ?x hands_to+ ?y . ?y type "PROMO" }',
    "wl2": 'SELECT ?a ?b WHERE { ?a status "F" . ?a placed_by ?c . ?c segment "BUILDING" . ?c in_nation nation/3 . ?a next_order+ ?b . ?b priority "1-URGENT" }',
    "wl3": 'SELECT DISTINCT ?x ?y WHERE { ?x type "ECONOMY" . ?x hands_to48+ ?y . ?s supplies ?x . ?t supplies ?y . ?s relays_thin+ ?t }',
    "wf1": 'SELECT ?a ?b WHERE { ?a event_kind "signup" . ?a next_event+ ?b . ?b event_kind "purchase" }',
    "wf2": 'SELECT ?a ?b WHERE { ?a done_by user/7 . ?a event_kind "error" . ?a next_event+ ?b . ?b event_kind "purchase" . ?b done_by user/7 }',
    "wf3": 'SELECT DISTINCT ?a ?c WHERE { ?a event_kind "error" . ?a next_event+ ?b . ?b event_kind "signup" . ?b next_event+ ?c . ?c event_kind "purchase" }',
    "wd1": 'SELECT ?a ?b ?p ?q ?l ?m WHERE { ?a quality "1" . ?a copy_of+ ?b . ?a from_source ?p . ?b from_source ?q . ?a in_lang ?l . ?b in_lang ?m }',
    "wd2": 'SELECT ?a ?b WHERE { ?a spoken_by "user" . ?a next_turn+ ?b . ?b spoken_by "assistant" }',
    "wd3": 'SELECT DISTINCT ?a ?c WHERE { ?a in_class "1" . ?a near+ ?b . ?b in_class "2" . ?b near* ?c . ?c in_class "3" }',
    "intro_path": 'SELECT DISTINCT ?a WHERE { ?a priority "1-URGENT" . ?a placed_by/within*/named "ASIA" }',
}


@query(
    walk("hands_to", "SELECT a, b FROM e JOIN part ON p_partkey = a AND p_type = 'ECONOMY'")
    + "SELECT x, y FROM r JOIN part ON p_partkey = y AND p_type = 'PROMO' WHERE x <> y"
)
def wl1(spark: SparkSession, sf_dir: str) -> DataFrame:
    """One reachability join of two large scans."""
    return match(spark, sf_dir, TEXTS["wl1"])


@query(
    walk("next_order", "SELECT a, b FROM e JOIN orders ON o_orderkey = a AND o_orderstatus = 'F' JOIN customer ON o_custkey = c_custkey AND c_mktsegment = 'BUILDING' AND c_nationkey = 3")
    + "SELECT x AS a, y AS b FROM r JOIN orders ON o_orderkey = y AND o_orderpriority = '1-URGENT' WHERE x <> y"
)
def wl2(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Selective: two joins and one reachability join."""
    return match(spark, sf_dir, TEXTS["wl2"])


@query(
    f"WITH RECURSIVE e(a, b) AS ({RULES['hands_to48']}), f(a, b) AS ({RULES['relays_thin']}),"
    " r(x, y) AS (SELECT a, b FROM e JOIN part ON p_partkey = a AND p_type = 'ECONOMY' UNION SELECT r.x, e.b FROM r JOIN e ON r.y = e.a),"
    " q(s, t) AS (SELECT a, b FROM f UNION SELECT q.s, f.b FROM q JOIN f ON q.t = f.a), u AS (SELECT DISTINCT l_suppkey AS s, l_partkey AS p FROM lineitem)"
    " SELECT DISTINCT x, y FROM r JOIN u c ON c.p = x JOIN q ON q.s = c.s AND q.s <> q.t JOIN u d ON d.s = q.t AND d.p = y WHERE x <> y"
)
def wl3(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Two reachability joins and two joins."""
    return match(spark, sf_dir, TEXTS["wl3"])


@query(
    walk("next_event", "SELECT a, b FROM e JOIN events ON event_id = a AND event_type = 'signup'") + "SELECT x AS a, y AS b FROM r JOIN events ON event_id = y AND event_type = 'purchase' WHERE x <> y"
)
def wf1(spark: SparkSession, sf_dir: str) -> DataFrame:
    """A single large reachability join along chains."""
    return match(spark, sf_dir, TEXTS["wf1"])


@query(
    walk("next_event", "SELECT a, b FROM e JOIN events ON event_id = a AND event_type = 'error' AND user_id = 7")
    + "SELECT x AS a, y AS b FROM r JOIN events ON event_id = y AND event_type = 'purchase' AND user_id = 7 WHERE x <> y"
)
def wf2(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Selective joins and one reachability join."""
    return match(spark, sf_dir, TEXTS["wf2"])


@query(
    f"WITH RECURSIVE e(a, b) AS ({RULES['next_event']}), r(x, y) AS (SELECT a, b FROM e JOIN events ON event_id = a AND event_type = 'error' UNION SELECT r.x, e.b FROM r JOIN e ON r.y = e.a),"
    " q(x, y) AS (SELECT a, b FROM e JOIN events ON event_id = a AND event_type = 'signup' UNION SELECT q.x, e.b FROM q JOIN e ON q.y = e.a)"
    " SELECT DISTINCT r.x AS a, q.y AS c FROM r JOIN q ON r.y = q.x JOIN events ON event_id = q.y AND event_type = 'purchase'"
)
def wf3(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Two reachability joins in a row."""
    return match(spark, sf_dir, TEXTS["wf3"])


@query(
    walk("copy_of", "SELECT a, b FROM e JOIN labels ON labels.doc_id = a AND quality = 1")
    + "SELECT x AS a, y AS b FROM r JOIN documents i ON i.doc_id = x JOIN documents j ON j.doc_id = y WHERE i.source <> j.source OR i.lang <> j.lang"
)
def wd1(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Copies of good documents in another source or language."""
    out = graph(spark, sf_dir).match(TEXTS["wd1"])
    return out.where("p <> q or l <> m").select(term_key("a").alias("a"), term_key("b").alias("b"))


@query(
    walk("next_turn", "SELECT a, b FROM e JOIN conversations ON conv_id * 100000 + turn = a AND role = 'user'")
    + "SELECT x AS a, y AS b FROM r JOIN conversations ON conv_id * 100000 + turn = y AND role = 'assistant' WHERE x <> y"
)
def wd2(spark: SparkSession, sf_dir: str) -> DataFrame:
    """User turns and later assistant turns."""
    return match(spark, sf_dir, TEXTS["wd2"])


@query(
    f"WITH RECURSIVE e(a, b) AS ({NEAR_SQL}), v AS (SELECT vec_id, label FROM embeddings WHERE label IN (1, 2, 3)), r(x, y) AS (SELECT a, b FROM e JOIN v ON vec_id = a UNION SELECT r.x, e.b FROM r JOIN e ON r.y = e.a)"
    " SELECT DISTINCT p.x AS a, q.y AS c FROM r p JOIN v i ON i.vec_id = p.x AND i.label = 1 JOIN v j ON j.vec_id = p.y AND j.label = 2 JOIN r q ON q.x = p.y JOIN v k ON k.vec_id = q.y AND k.label = 3"
)
def wd3(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Neighbour chains over three classes; for small tables, as the neighbours come from all pairs."""
    return match(spark, sf_dir, TEXTS["wd3"])


_CHAIN = "SELECT DISTINCT o_orderkey AS a FROM orders JOIN customer ON o_custkey = c_custkey JOIN nation ON c_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey WHERE r_name = 'ASIA' AND o_orderpriority = '1-URGENT'"


@query(_CHAIN)
def intro_chain(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Urgent orders from a region, every hop written out."""
    return match(spark, sf_dir, 'SELECT DISTINCT ?a WHERE { ?a priority "1-URGENT" . ?a placed_by ?c . ?c in_nation ?n . ?n in_region ?r . ?r named "ASIA" }')


@query(_CHAIN)
def intro_path(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The same as one path with a starred step."""
    return match(spark, sf_dir, TEXTS["intro_path"])


WORKED_SIX = 'SELECT ?x ?n ?x1 ?n1 WHERE { ?x relays_thin* ?x1 . ?x supplies part/5 . ?n trades* ?n1 . ?n within* region/2 . ?x1 in_nation ?n1 . ?x in_nation ?n }'


@query(
    f"WITH RECURSIVE e(a, b) AS ({RULES['relays_thin']}), f(a, b) AS ({RULES['trades']}),"
    " r(x, y) AS (SELECT s_suppkey, s_suppkey FROM supplier UNION SELECT r.x, e.b FROM r JOIN e ON r.y = e.a),"
    " q(x, y) AS (SELECT CAST(n_nationkey AS BIGINT), CAST(n_nationkey AS BIGINT) FROM nation UNION SELECT q.x, f.b FROM q JOIN f ON q.y = f.a)"
    " SELECT s.s_suppkey AS x, CAST(s.s_nationkey AS BIGINT) AS n, t.s_suppkey AS x1, CAST(t.s_nationkey AS BIGINT) AS n1 FROM supplier s JOIN nation ON s.s_nationkey = n_nationkey AND n_regionkey = 2"
    " JOIN r ON r.x = s.s_suppkey JOIN supplier t ON t.s_suppkey = r.y JOIN q ON q.x = s.s_nationkey AND q.y = t.s_nationkey"
    " WHERE s.s_suppkey IN (SELECT l_suppkey FROM lineitem WHERE l_partkey = 5)"
)
def worked_six(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Three plain and three starred patterns, a constant end, a variable on two relations."""
    g = graph(spark, sf_dir)
    g.properties.setdefault("supplier_nation", lambda: g.edges("in_nation").where(F.shiftright("s", 48) == KINDS["supplier"]))
    return match(spark, sf_dir, WORKED_SIX.replace("in_nation", "supplier_nation"))


_S = "SELECT p_partkey AS v FROM part WHERE p_type = 'ECONOMY'"


def _ends(spark: SparkSession, sf_dir: str) -> tuple[DataFrame, DataFrame]:
    part = spark.read.parquet(f"{sf_dir}/part.parquet")
    of = lambda kind: part.where(F.col("p_type") == kind).select(F.col("p_partkey").alias("v"))
    return of("ECONOMY"), of("PROMO")


def _ladder(name: str) -> None:
    if name == "relays":
        sql = walk(name) + "SELECT x, y FROM r WHERE x <> y"
    else:
        sql = walk(name, "SELECT a, b FROM e JOIN part ON p_partkey = a AND p_type = 'ECONOMY'") + "SELECT x, y FROM r JOIN part ON p_partkey = y AND p_type = 'PROMO' WHERE x <> y"

    @query(sql, f"ladder_{name}")
    def ladder(spark: SparkSession, sf_dir: str) -> DataFrame:
        if name == "relays":
            v = spark.read.parquet(f"{sf_dir}/supplier.parquet").select(F.col("s_suppkey").alias("v"))
            ends = v, v
        else:
            ends = _ends(spark, sf_dir)
        return tied(spark, sf_dir, name).set_reach(*ends, "+")


for _name in ("hands_to49", "hands_to48", "hands_to", "relays"):
    _ladder(_name)


# -- encoding, partitions, permutations ----------------------------------------

#: Properties between rows of tables; their ids can be told in SQL, those of literals are hashes.
_LINKS = {
    "done_by": [("events", "event", "event_id", "user", "user_id")],
    "filled_by": [("lineitem", "order", "l_orderkey", "supplier", "l_suppkey")],
    "has_part": [("lineitem", "order", "l_orderkey", "part", "l_partkey")],
    "in_nation": [("customer", "customer", "c_custkey", "nation", "c_nationkey"), ("supplier", "supplier", "s_suppkey", "nation", "s_nationkey")],
    "in_region": [("nation", "nation", "n_nationkey", "region", "n_regionkey")],
    "placed_by": [("orders", "order", "o_orderkey", "customer", "o_custkey")],
    "supplies": [("lineitem", "supplier", "l_suppkey", "part", "l_partkey")],
    "turn_of": [("conversations", "turn", "conv_id * 100000 + turn", "conversation", "conv_id")],
}
_IDS = property_ids(list(_LINKS))
_TRIPLES = " UNION ".join(
    f"SELECT {KINDS[a] * BASE} + {x} AS s, {_IDS[name]} AS p, {KINDS[b] * BASE} + {y} AS o FROM {table} WHERE {x} IS NOT NULL AND {y} IS NOT NULL" for name, ways in _LINKS.items() for table, a, x, b, y in ways
)
_T = f"WITH t AS (SELECT CAST(s AS BIGINT) AS s, p, CAST(o AS BIGINT) AS o FROM ({_TRIPLES}) u) "


def _triples(spark: SparkSession, sf_dir: str) -> DataFrame:
    return to_triples(spark, sf_dir, list(_LINKS))


@query(_T + "SELECT p, count(*) AS n FROM t GROUP BY p")
def triples_count(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Triples per property."""
    return _triples(spark, sf_dir).groupBy("p").agg(F.count(F.lit(1)).alias("n"))


@query("SELECT p_partkey AS k, p_type AS lex FROM part UNION SELECT p_partkey, p_brand FROM part UNION SELECT o_orderkey, o_orderstatus FROM orders UNION SELECT o_orderkey, o_orderpriority FROM orders UNION SELECT c_custkey, c_mktsegment FROM customer UNION SELECT event_id, event_type FROM events")
def encode(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Literals of six properties, encoded and decoded again, after a look at collisions."""
    names = ["type", "brand", "status", "priority", "segment", "event_kind"]
    terms, g = sound_dictionary(spark, sf_dir, names), graph(spark, sf_dir)
    out = None
    for name in names:
        one = g.edges(name).join(terms, F.col("o") == F.col("id")).select(term_key("s").alias("k"), "lex")
        out = one if out is None else out.union(one)
    return out.distinct()


@query(_T + "SELECT CAST(s % 4 AS INTEGER) AS part, count(*) AS n FROM (SELECT s FROM t UNION ALL SELECT o FROM t WHERE s % 4 <> o % 4) u GROUP BY s % 4")
def shards(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Triples per shard; each is there once or twice."""
    return shard_triples(_triples(spark, sf_dir), 4).groupBy("part").agg(F.count(F.lit(1)).alias("n"))


def _permutation(perm: str, where: str) -> None:
    @query(_T + f"SELECT s, p, o FROM t WHERE {where}", f"perm_{perm.lower()}")
    def scan(spark: SparkSession, sf_dir: str) -> DataFrame:
        from reachgraph.operators.permutations import IndexStore
        from reachgraph.session import shared_folder

        # each permutation is written when first asked for, with all triples
        store = _kept(
            spark, sf_dir, "store", perm, make=lambda: IndexStore(spark, f"{shared_folder(spark)}/perms-{abs(hash((sf_dir, spark.sparkContext.applicationId)))}", 4).write(_triples(spark, sf_dir), (perm,))
        )
        given = dict(part.split(" = ") for part in where.split(" AND "))
        return store.scan(perm, **{k: int(v) for k, v in given.items()})


_SUP, _NAT, _PART = KINDS["supplier"] * BASE + 3, KINDS["nation"] * BASE + 3, KINDS["part"] * BASE + 5
for _perm, _where in {
    "SPO": f"s = {_SUP} AND p = {_IDS['supplies']}", "SOP": f"s = {_SUP} AND o = {_NAT}", "PSO": f"p = {_IDS['supplies']} AND s = {_SUP}",
    "OSP": f"o = {_PART} AND s = {_SUP}", "OPS": f"o = {_PART} AND p = {_IDS['supplies']}", "POS": f"p = {_IDS['in_nation']} AND o = {_NAT}",
}.items():
    _permutation(_perm, _where)

_CUT = f"WITH e(a, b) AS ({RULES['hands_to49']}), c AS (SELECT a AS u, b AS v, CAST(a % 4 AS INTEGER) AS pu, CAST(b % 4 AS INTEGER) AS pv FROM e WHERE a % 4 <> b % 4) "


@query(_CUT + "SELECT u, v, pu, pv FROM c")
def cut(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Edges between shards."""
    return index(spark, sf_dir, "hands_to49", k=4).cut.select(F.col("s").alias("u"), F.col("t").alias("v"), F.col("ps").alias("pu"), F.col("pt").alias("pv"))


@query(_CUT + "SELECT DISTINCT pv AS part, v FROM c")
def entries(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Vertices where the cut leads into a shard."""
    return index(spark, sf_dir, "hands_to49", k=4).cut.select(F.col("pt").alias("part"), F.col("t").alias("v")).distinct()


@query(_CUT + "SELECT DISTINCT pu AS part, u AS v FROM c")
def exits(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Vertices where the cut leads out of a shard."""
    return index(spark, sf_dir, "hands_to49", k=4).cut.select(F.col("ps").alias("part"), F.col("s").alias("v")).distinct()


_CROSS = (
    f"WITH RECURSIVE e(a, b) AS ({RULES['hands_to49']}), i AS (SELECT DISTINCT b AS v FROM e WHERE a % 4 <> b % 4), o AS (SELECT DISTINCT a AS v FROM e WHERE a % 4 <> b % 4),"
    " r(x, y) AS (SELECT v, v FROM i UNION SELECT r.x, e.b FROM r JOIN e ON r.y = e.a WHERE e.a % 4 = e.b % 4), x AS (SELECT CAST(r.x % 4 AS INTEGER) AS part, r.x AS entry, r.y AS exit FROM r JOIN o ON o.v = r.y) "
)


@query(_CROSS + "SELECT part, entry, exit FROM x")
def crossings(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Exits that the entries of each shard reach inside it."""
    return index(spark, sf_dir, "hands_to49", k=4).crossings.select("part", "entry", "exit")


@query(_CROSS + ", g AS (SELECT part, entry, list_sort(list(exit)) AS l FROM x GROUP BY part, entry) SELECT part, entry, min(entry) OVER (PARTITION BY part, l) AS cls FROM g", "classes")
def entry_classes(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Entries with equal sets of exits."""
    return classes(index(spark, sf_dir, "hands_to49", k=4).crossings)[0]


@query(_CROSS + ", g AS (SELECT part, exit, list_sort(list(entry)) AS l FROM x GROUP BY part, exit) SELECT part, exit, min(exit) OVER (PARTITION BY part, l) AS cls FROM g")
def exit_classes(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Exits with equal sets of entries."""
    return classes(index(spark, sf_dir, "hands_to49", k=4).crossings)[1]


@query(_CROSS + "SELECT entry * 4 + 1 AS src, exit * 4 + 2 AS dst FROM x UNION SELECT a * 4 + 2, b * 4 + 1 FROM e WHERE a % 4 <> b % 4")
def boundary_pairs(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Boundary graph without classes: crossings and cut."""
    return index(spark, sf_dir, "hands_to49", k=4, compress=False).boundary


_SCC = walk("hands_to", "SELECT a, b FROM e")


@query(_SCC + "SELECT p.x AS v, min(p.y) AS scc FROM (SELECT x, y FROM r UNION SELECT a, a FROM e UNION SELECT b, b FROM e) p WHERE p.x = p.y OR EXISTS (SELECT 1 FROM r q WHERE q.x = p.y AND q.y = p.x) GROUP BY p.x")
def scc(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Smallest vertex of each strongly connected component, over one condensed shard."""
    ix = index(spark, sf_dir, "hands_to", k=1)
    rows = ix.shards.select(F.explode(F.arrays_zip("verts", "comp")).alias("z")).select(F.col("z.verts").alias("v"), F.col("z.comp").alias("c"))
    return rows.join(rows.groupBy("c").agg(F.min("v").alias("scc")), "c").select("v", "scc")


@query(_SCC + "SELECT x AS v FROM r WHERE x = y")
def on_cycle(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Vertices that reach themselves over an edge or more."""
    ix = tied(spark, sf_dir, "hands_to")
    v = ix.edges.select(F.col("s").alias("v")).distinct()
    return ix.on_cycles(v)


@query(f"WITH RECURSIVE e(a, b) AS ({RULES['hands_to49']}), u AS (SELECT a, b FROM e UNION SELECT b, a FROM e), r(x, y) AS (SELECT a, b FROM u UNION SELECT r.x, u.b FROM r JOIN u ON r.y = u.a) SELECT x AS v, least(x, min(y)) AS label FROM r GROUP BY x")
def weak_component(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Smallest vertex of each weakly connected component."""
    return weak_components(edges(spark, sf_dir, "hands_to49"))


# -- set reachability ------------------------------------------------------------

_FROM = "SELECT a, b FROM e JOIN part ON p_partkey = a AND p_type = 'ECONOMY'"
_TO = " JOIN part ON p_partkey = y AND p_type = 'PROMO'"
_PLUS = walk("hands_to48", _FROM) + "SELECT x, y FROM r" + _TO + " WHERE x <> y"


def _reach_variant(name: str, **options: object) -> None:
    @query(_PLUS, name)
    def reach(spark: SparkSession, sf_dir: str) -> DataFrame:
        made = {k: v() if callable(v) else v for k, v in options.items()}
        return tied(spark, sf_dir, "hands_to48", **made).set_reach(*_ends(spark, sf_dir), "+")


for _key, _options in {
    "reach_plus": {}, "reach_uncompressed": {"compress": False}, "reach_compound": {"layout": "compound"}, "reach_central": {"k": 1}, "reach_many_shards": {"k": 16},
    "reach_large_boundary": {"max_boundary": 0}, "reach_by_range": {"partitioner": lambda: RangePartitioner(4)}, "reach_by_locality": {"partitioner": lambda: LocalityPartitioner(4, 2)},
}.items():
    _reach_variant(_key, **_options)


@query(walk("hands_to48", f"SELECT v AS a, v AS b FROM ({_S}) s") + "SELECT x, y FROM r JOIN part ON p_partkey = y AND p_type = 'ECONOMY'")
def reach_star(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Zero or more edges, from a set to itself."""
    s, _ = _ends(spark, sf_dir)
    return tied(spark, sf_dir, "hands_to48").set_reach(s, s, "*")


@query(walk("relays", "SELECT a, b FROM e") + "SELECT x, y FROM r")
def reach_plus_cycle(spark: SparkSession, sf_dir: str) -> DataFrame:
    """One edge or more, cycles included."""
    ix = tied(spark, sf_dir, "relays")
    v = ix.edges.select(F.col("s").alias("v")).union(ix.edges.select("t")).distinct()
    return ix.set_reach(v, v, "+", plus="cycle")


@query(f"WITH e(a, b) AS ({RULES['hands_to48']}) SELECT a AS x, b AS y FROM e JOIN part p ON p.p_partkey = a AND p.p_type = 'ECONOMY' JOIN part q ON q.p_partkey = b AND q.p_type = 'ECONOMY' UNION SELECT v, v FROM ({_S}) s")
def reach_opt(spark: SparkSession, sf_dir: str) -> DataFrame:
    """No edge or one."""
    s, _ = _ends(spark, sf_dir)
    return tied(spark, sf_dir, "hands_to48").set_reach(s, s, "?")


@query(walk("hands_to48", _FROM) + "SELECT y AS x, x AS y FROM r" + _TO + " WHERE x <> y")
def reach_inverse(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The inverse path."""
    return match(spark, sf_dir, 'SELECT ?x ?y WHERE { ?x type "PROMO" . ?x ^hands_to48+ ?y . ?y type "ECONOMY" }')


@query(
    f"WITH RECURSIVE e(a, b) AS ({RULES['hands_to49']}), r(x, y) AS (SELECT a, b FROM e UNION SELECT r.x, e.b FROM r JOIN e ON r.y = e.a)"
    " SELECT DISTINCT p_brand AS brand, r.y AS y FROM r JOIN part ON p_partkey = r.x WHERE x <> y"
)
def reach_concat(spark: SparkSession, sf_dir: str) -> DataFrame:
    """A path of three steps: brand of, parts behind it."""
    out = graph(spark, sf_dir).match("SELECT DISTINCT ?b ?y WHERE { ?b ^brand/hands_to49+ ?y }")
    return out.join(dictionary(spark, sf_dir, ["brand"]), F.col("b") == F.col("id")).select(F.col("lex").alias("brand"), term_key("y").alias("y"))


@query(walk("relays", "SELECT a, b FROM e WHERE a = 3") + "SELECT count(*) > 0 AS reached FROM r WHERE y = 5")
def reach_single(spark: SparkSession, sf_dir: str) -> DataFrame:
    """One source, one target."""
    one = lambda v: spark.createDataFrame([(v,)], "v long")
    pairs = index(spark, sf_dir, "relays").set_reach(one(3), one(5), "+")
    return pairs.agg((F.count(F.lit(1)) > 0).alias("reached"))


@query(walk("relays", "SELECT a, b FROM e WHERE a = 3") + "SELECT y FROM r WHERE y <> 3")
def reach_from(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Everything behind a constant; the other end is unbound."""
    return match(spark, sf_dir, "SELECT ?y WHERE { supplier/3 relays+ ?y }")


@query(walk("relays") + "SELECT x FROM r WHERE y = 3 AND x <> 3")
def reach_to(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Everything before a constant."""
    return match(spark, sf_dir, "SELECT ?x WHERE { ?x relays+ supplier/3 }")


@query(walk("hands_to49") + "SELECT x, y FROM r WHERE x <> y")
def reach_unbound(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Both ends unbound: all pairs of the property's vertices."""
    return match(spark, sf_dir, "SELECT ?x ?y WHERE { ?x hands_to49+ ?y }")


# -- reachability joins -----------------------------------------------------------


@query(_PLUS)
def drj_pure(spark: SparkSession, sf_dir: str) -> DataFrame:
    """No shared variable."""
    return match(spark, sf_dir, 'SELECT ?x ?y WHERE { ?x type "ECONOMY" . ?y type "PROMO" . ?x hands_to48+ ?y }')


@query(walk("hands_to48", _FROM) + "SELECT x, y FROM r JOIN part p ON p.p_partkey = x JOIN part q ON q.p_partkey = y AND p.p_brand = q.p_brand WHERE x <> y")
def drj_shared(spark: SparkSession, sf_dir: str) -> DataFrame:
    """A shared variable beside the predicate."""
    return match(spark, sf_dir, 'SELECT ?x ?y WHERE { ?x type "ECONOMY" . ?x brand ?b . ?y brand ?b . ?x hands_to48+ ?y }')


@query(
    f"WITH RECURSIVE e(a, b) AS ({RULES['hands_to']}), f(a, b) AS ({RULES['hands_to48']}), r(x, y) AS ({_FROM} UNION SELECT r.x, e.b FROM r JOIN e ON r.y = e.a),"
    f" q(x, y) AS ({_FROM.replace('FROM e', 'FROM f')} UNION SELECT q.x, f.b FROM q JOIN f ON q.y = f.a) SELECT r.x, r.y FROM r JOIN q ON r.x = q.x AND r.y = q.y{_TO.replace('= y', '= r.y')} WHERE r.x <> r.y"
)
def drj_two_preds(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Two predicates between the same relations."""
    return match(spark, sf_dir, 'SELECT ?x ?y WHERE { ?x type "ECONOMY" . ?y type "PROMO" . ?x hands_to48+ ?y . ?x hands_to+ ?y }')


@query(walk("hands_to48", "SELECT a, b FROM e WHERE a IN (SELECT p_partkey FROM part WHERE p_type = 'ECONOMY')") + "SELECT x FROM r WHERE y = (SELECT min(b) FROM e) AND x <> y")
def drj_constant(spark: SparkSession, sf_dir: str) -> DataFrame:
    """A constant target, the smallest that has an edge into it."""
    least = graph(spark, sf_dir).edges("hands_to48").agg(term_key(F.min("o"))).first()[0]
    return match(spark, sf_dir, f'SELECT ?x WHERE {{ ?x type "ECONOMY" . ?x hands_to48+ part/{least} }}')


@query(
    walk("relays")
    + "SELECT DISTINCT i.l_partkey AS p, x, y FROM part JOIN lineitem i ON i.l_partkey = p_partkey AND p_brand = 'Brand#11' JOIN lineitem j ON i.l_partkey = j.l_partkey JOIN r ON x = i.l_suppkey AND y = j.l_suppkey WHERE x <> y"
)
def drj_same_side(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Both ends bound by relations that are joined already."""
    return match(spark, sf_dir, 'SELECT ?p ?x ?y WHERE { ?p brand "Brand#11" . ?x supplies ?p . ?y supplies ?p . ?x relays+ ?y }')


@query(walk("hands_to49", "SELECT a, b FROM e JOIN part ON p_partkey = a AND p_brand = 'Brand#11'") + "SELECT x, y FROM r JOIN part ON p_partkey = y AND p_brand = 'Brand#12' WHERE x <> y")
def drj_naive(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The definition itself, as a baseline: all pairs of two brands' parts that are in the closure."""
    part = spark.read.parquet(f"{sf_dir}/part.parquet")
    of = lambda brand, name: part.where(F.col("p_brand") == brand).select(F.col("p_partkey").alias(name))
    pairs = of("Brand#11", "x").crossJoin(of("Brand#12", "y")).where("x <> y")
    return pairs.join(baselines.frontier_reach(edges(spark, sf_dir, "hands_to49"), of("Brand#11", "v")), ["x", "y"], "left_semi")


# -- statistics --------------------------------------------------------------------

for _slot in "spo":

    @query(_T + f"SELECT CAST({_slot} AS BIGINT) AS k, count(*) AS n FROM t GROUP BY {_slot}", f"card_{_slot}")
    def card(spark: SparkSession, sf_dir: str, slot: str = _slot) -> DataFrame:
        return statistics.key_counts(_triples(spark, sf_dir)).where(F.col("slot") == slot).select("k", "n")


for _slots in ("so", "ps", "po"):

    @query(_T + f"SELECT CAST({_slots[0]} AS BIGINT) AS k1, CAST({_slots[1]} AS BIGINT) AS k2, count(*) AS n FROM t GROUP BY {_slots[0]}, {_slots[1]}", f"card_{_slots}")
    def card_pair(spark: SparkSession, sf_dir: str, slots: str = _slots) -> DataFrame:
        return statistics.pair_counts(_triples(spark, sf_dir)).where(F.col("slots") == slots).select("k1", "k2", "n")


@query(_T + ", v AS (SELECT p, s AS v FROM t UNION SELECT p, o FROM t) SELECT t.p, t.n AS n_edges, w.n AS n_vertices FROM (SELECT p, count(*) AS n FROM t GROUP BY p) t JOIN (SELECT p, count(*) AS n FROM v GROUP BY p) w ON t.p = w.p")
def property_size(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Edges and vertices per property."""
    return statistics.property_sizes(_triples(spark, sf_dir)).select("p", "n_edges", "n_vertices")


@query(_T + " UNION ALL ".join(f"SELECT x.p, y.p AS q, '{(a + b).upper()}' AS position, count(*) AS n FROM t x JOIN t y ON x.{a} = y.{b} GROUP BY x.p, y.p" for a in "so" for b in "so"))
def sel_join(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Sizes of the joins of all property pairs."""
    return statistics.join_sizes(_triples(spark, sf_dir))


@query(walk("relays") + ", v AS (SELECT a FROM e UNION SELECT b FROM e) SELECT round((SELECT count(*) FROM r) / ((SELECT count(*) FROM v) * (SELECT count(*) FROM v)), 9) AS sel")
def sel_reach_exact(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Reachability selectivity of one property, exactly."""
    ix = tied(spark, sf_dir, "relays")
    v = ix.edges.select(F.col("s").alias("v")).union(ix.edges.select("t")).distinct()
    sel = statistics.reach_selectivity_exact(ix.set_reach(v, v, "+", plus="cycle"), ix.edges)
    return spark.createDataFrame([(round(sel, 9),)], "sel double")


@query()
def sel_reach_sampled(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Reachability selectivities from samples, with their intervals."""
    rows = [(n, s.samples, s.hits, s.sel, s.low, s.high) for n in ("hands_to49", "hands_to", "relays") for s in (statistics.reach_selectivity(tied(spark, sf_dir, n)),)]
    return spark.createDataFrame(rows, "graph string, samples long, hits long, sel double, low double, high double")


# -- baselines ----------------------------------------------------------------------

_B = walk("hands_to49", _FROM) + "SELECT x, y FROM r" + _TO + " WHERE x <> y"
_BASELINES: dict[str, Callable] = {
    "frontier": lambda spark, e, s, t: baselines.frontier_reach(e, s, t),
    "vertex": lambda spark, e, s, t: baselines.vertex_centric_reach(e, s, t),
    "cte": lambda spark, e, s, t: baselines.recursive_cte_reach(spark, e, s, t),
    "closure": lambda spark, e, s, t: baselines.closure_reach(e, s, t),
    "doubling": lambda spark, e, s, t: baselines.closure_reach(e, s, t, method="doubling"),
    "unrolled": lambda spark, e, s, t: baselines.unrolled_reach(e, s, t, most=None),
}
for _base in _BASELINES:

    @query(_B, f"baseline_{_base}")
    def baseline(spark: SparkSession, sf_dir: str, base: str = _base) -> DataFrame:
        return _BASELINES[base](spark, edges(spark, sf_dir, "hands_to49"), *_ends(spark, sf_dir))


@query(walk("trades") + "SELECT x, y FROM r JOIN nation i ON i.n_nationkey = x AND i.n_regionkey = 0 JOIN nation j ON j.n_nationkey = y AND j.n_regionkey = 1 WHERE x <> y")
def baseline_pairwise(spark: SparkSession, sf_dir: str) -> DataFrame:
    """One query per pair of nations of two regions."""
    nation = spark.read.parquet(f"{sf_dir}/nation.parquet")
    of = lambda region: [r.n_nationkey for r in nation.where(F.col("n_regionkey") == region).orderBy("n_nationkey").collect()]
    return baselines.pairwise_reach(index(spark, sf_dir, "trades", k=2), of(0), of(1))


@query(f"WITH e(a, b) AS ({RULES['hands_to49']}) SELECT e.a AS x, g.b AS y FROM e JOIN e f ON e.b = f.a JOIN e g ON f.b = g.a UNION SELECT e.a, f.b FROM e JOIN e f ON e.b = f.a")
def bounded_path(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Two or three edges."""
    e = edges(spark, sf_dir, "hands_to49")
    v = e.select(F.col("s").alias("v")).union(e.select("t")).distinct()
    return baselines.bounded_reach(e, v, v, 2, 3)


@query(
    f"WITH RECURSIVE e(a, b) AS ({RULES['hands_to49']}), w(x, y, n) AS (SELECT a, b, 1 FROM e JOIN part ON p_partkey = a AND p_type = 'ECONOMY' UNION SELECT w.x, e.b, w.n + 1 FROM w JOIN e ON w.y = e.a WHERE w.n < 60) SELECT x, y, CAST(min(n) AS INTEGER) AS n FROM w GROUP BY x, y"
)
def shortest_path(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Edges of a shortest path."""
    return baselines.shortest_lengths(edges(spark, sf_dir, "hands_to49"), _ends(spark, sf_dir)[0])
