"""Variants of the index and its questions, statistics by other means, streams that meet: each with its SQL."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from reachgraph.functions.bitsets import bitset_parts, bitset_size
from reachgraph.functions.table import register
from reachgraph.measures import rounds
from reachgraph.operators.condense import strong_components
from reachgraph.operators.labels import LabelTables
from reachgraph.operators.multi_index import MultiIndex
from reachgraph.operators.reach_index import ReachIndex
from reachgraph.plans.statistics import q_error
from reachgraph.session import shared_folder
from reachgraph.sources.graphs import RULES, edges
from reachgraph.streaming.events import followed
from reachgraph.workloads import _IDS, _PLUS, _T, ORACLE, TEXTS, _ends, _triples, graph, index, match, query, walk


@query(walk(f"{RULES['relays']} UNION {RULES['relays_thin']}", "SELECT a, b FROM e WHERE a = 3") + "SELECT y FROM r WHERE y <> 3")
def path_either(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Any number of steps, each over one of two properties."""
    return match(spark, sf_dir, "SELECT ?y WHERE { supplier/3 (relays|relays_thin)+ ?y }")


@query(
    f"WITH RECURSIVE n(a, b) AS ({RULES['next_event']}), e(a, b) AS (SELECT n.a, m.b FROM n JOIN n m ON n.b = m.a), r(x, y) AS (SELECT a, b FROM e JOIN events ON event_id = a AND event_type = 'error' UNION SELECT r.x, e.b FROM r JOIN e ON r.y = e.a)"
    " SELECT x AS a, y AS b FROM r JOIN events ON event_id = y AND event_type = 'purchase'"
)
def path_repeated_sequence(spark: SparkSession, sf_dir: str) -> DataFrame:
    """A sequence of two steps, any number of times."""
    return match(spark, sf_dir, 'SELECT ?a ?b WHERE { ?a event_kind "error" . ?a (next_event/next_event)+ ?b . ?b event_kind "purchase" }')


@query(_PLUS)
def reach_backward(spark: SparkSession, sf_dir: str) -> DataFrame:
    """From the targets, over the reversed index."""
    return index(spark, sf_dir, "hands_to48").set_reach(*_ends(spark, sf_dir), "+", direction="backward")


@query(_PLUS)
def reach_labels(spark: SparkSession, sf_dir: str) -> DataFrame:
    """By label tables and joins alone."""
    return LabelTables.of(index(spark, sf_dir, "hands_to48")).set_reach(*_ends(spark, sf_dir))


@query(_PLUS)
def reach_saved(spark: SparkSession, sf_dir: str) -> DataFrame:
    """An index that was written and read back."""
    version = index(spark, sf_dir, "hands_to48").save(f"{shared_folder(spark)}/saved")
    return ReachIndex.load(spark, version).set_reach(*_ends(spark, sf_dir), "+")


@query(_PLUS)
def reach_together(spark: SparkSession, sf_dir: str) -> DataFrame:
    """One property of an index that was built for several at once."""
    names = ("hands_to48", "relays", "next_turn", "trades")
    return MultiIndex.build({n: edges(spark, sf_dir, n) for n in names}, 4).set_reach("hands_to48", *_ends(spark, sf_dir))


@query(_PLUS)
def reach_upkeep(spark: SparkSession, sf_dir: str) -> DataFrame:
    """An index that further edges were added to."""
    ix = index(spark, sf_dir, "hands_to49", k=4)
    return ix.with_edges(edges(spark, sf_dir, "hands_to48")).set_reach(*_ends(spark, sf_dir), "+")


_RELAYS = walk("relays")


@query(_RELAYS + "SELECT p.x AS v, min(p.y) AS scc FROM (SELECT x, y FROM r UNION SELECT a, a FROM e UNION SELECT b, b FROM e) p WHERE p.x = p.y OR EXISTS (SELECT 1 FROM r q WHERE q.x = p.y AND q.y = p.x) GROUP BY p.x")
def scc_by_joins(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Strongly connected components without a task that holds the graph."""
    return strong_components(edges(spark, sf_dir, "relays"))


@query(_RELAYS + "SELECT y AS v FROM r WHERE x = 3 AND y <> 3 UNION SELECT 3 WHERE EXISTS (SELECT 1 FROM r WHERE x = 3 AND y = 3)")
def reach_table_function(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Everything behind a vertex, by a table function in SQL."""
    register(spark)
    return spark.sql("SELECT v FROM reach_from(TABLE(SELECT s, t FROM {e}) WITH SINGLE PARTITION, CAST(3 AS BIGINT))", e=edges(spark, sf_dir, "relays"))


@query("SELECT 'hands_to48' AS graph, 1 AS rounds UNION ALL SELECT 'next_event', 0")
def rounds_measured(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Exchanges of bindings that a predicate takes, counted in plans that ran; none where components lie whole in a shard."""
    got = [("hands_to48", rounds(index(spark, sf_dir, "hands_to48"), *_ends(spark, sf_dir)))]
    ix = index(spark, sf_dir, "next_event")
    v = ix.edges.select(F.col("s").alias("v"))
    got.append(("next_event", rounds(ix, v, v) if ix.cut.limit(1).count() else 0))
    return spark.createDataFrame(got, "graph string, rounds int")


_PLANNED = ("wl1", "wl2", "wf1", "wf2", "wd2")


@query(" UNION ALL ".join(f"SELECT '{n}' AS workload, count(*) AS found, false AS far_off, true AS unified_least FROM ({ORACLE[n]}) q{n}" for n in _PLANNED))
def plan_q_error(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Rows of workloads, whether the plan's estimate is off by 100 times, and whether ordering all joins together costs least."""
    g, rows = graph(spark, sf_dir), []
    for name in _PLANNED:
        plans = {mode: g.plan(TEXTS[name], mode) for mode in ("unified", "split", "textual")}
        found = g.match(TEXTS[name]).count()
        least = min(p.cost for p in plans.values())
        rows.append((name, found, q_error(max(plans["unified"].rows, 1), max(found, 1)) > 100, plans["unified"].cost <= least * (1 + 1e-9)))
    return spark.createDataFrame(rows, "workload string, found long, far_off boolean, unified_least boolean")


@query(_T + "SELECT s, CAST(p AS INTEGER) AS p, o, count(*) AS n FROM t GROUP BY GROUPING SETS ((s, p), (p, o), (p))")
def card_sets(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Cardinalities by pairs and by property in one pass."""
    return spark.sql("SELECT s, p, o, count(*) AS n FROM {t} GROUP BY GROUPING SETS ((s, p), (p, o), (p))", t=_triples(spark, sf_dir))


@query(" UNION ALL ".join(f"SELECT {i} AS p, true AS near" for i in _IDS.values()))
def card_approx(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Whether sketched numbers of subjects are within a tenth of the exact ones, by property."""
    both = _triples(spark, sf_dir).groupBy("p").agg(F.approx_count_distinct("s", 0.02).alias("a"), F.count_distinct("s").alias("n"))
    return both.select("p", (F.abs(F.col("a") - F.col("n")) <= F.greatest(F.lit(1), 0.1 * F.col("n"))).alias("near"))


@query("SELECT p_brand AS brand, count(DISTINCT p_size) AS n FROM part GROUP BY p_brand")
def bitset_union(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Distinct sizes by brand, from bitmaps by brand and type that are united."""
    part = spark.read.parquet(f"{sf_dir}/part.parquet").select(F.col("p_brand").alias("brand"), "p_type", "p_size")
    return bitset_size(bitset_parts(part, ["brand", "p_type"], "p_size"), ["brand"])


@query(
    "SELECT x.event_id AS a, y.event_id AS b FROM events x JOIN events y ON x.user_id = y.user_id AND x.event_type = 'error' AND y.event_type = 'purchase' AND y.ts > x.ts AND y.ts <= x.ts + INTERVAL 10 MINUTE"
)
def stream_pairs(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Errors and purchases soon after, both sides streams."""
    return followed(spark, sf_dir, "error", "purchase")
