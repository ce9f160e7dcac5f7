"""The operators around the methods: joins, sets, aggregates, windows, functions, streams."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from reachgraph.operators.relational import asof_join, interval_join, range_join, reach_semi
from reachgraph.sources.graphs import NEAR_SQL, RULES, edges, near_edges
from reachgraph.streaming.events import batch_replay, next_events, static_counts, windowed_counts
from reachgraph.workloads import _FROM, _ends, graph, index, match, query, walk


def _read(spark: SparkSession, sf_dir: str, table: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{table}.parquet")


_H = f"WITH e(a, b) AS ({RULES['hands_to49']}) "


@query("SELECT DISTINCT p_brand AS brand, p_type AS type FROM part")
def project_distinct(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _read(spark, sf_dir, "part").select(F.col("p_brand").alias("brand"), F.col("p_type").alias("type")).distinct()


@query("SELECT o_orderkey AS a FROM orders WHERE o_orderstatus = 'F' AND o_custkey = 7")
def const_filter(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Constants on subject and object."""
    return match(spark, sf_dir, 'SELECT ?a WHERE { ?a status "F" . ?a placed_by customer/7 }')


@query(f"WITH e(a, b) AS ({RULES['hands_to48']}) SELECT e.a AS x, e.b AS y FROM e JOIN e f ON e.a = f.b AND e.b = f.a")
def self_loop(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Variables repeated across two patterns: edges that lead both ways."""
    return match(spark, sf_dir, "SELECT ?x ?y WHERE { ?x hands_to48 ?y . ?y hands_to48 ?x }")


@query("SELECT p_partkey AS k FROM part WHERE p_size BETWEEN 10 AND 20 AND p_brand IN ('Brand#11', 'Brand#12') AND regexp_matches(p_type, '^ECO') OR p_size IS NULL")
def filter_literal(spark: SparkSession, sf_dir: str) -> DataFrame:
    p = _read(spark, sf_dir, "part")
    return p.where(F.col("p_size").between(10, 20) & F.col("p_brand").isin("Brand#11", "Brand#12") & F.col("p_type").rlike("^ECO") | F.col("p_size").isNull()).select(F.col("p_partkey").alias("k"))


for _hint in ("merge", "shuffle_hash", "broadcast"):

    @query(_H + "SELECT e.a AS x, e.b AS m, f.b AS y FROM e JOIN e f ON e.b = f.a", f"join_{_hint.replace('shuffle_', '')}")
    def join_hinted(spark: SparkSession, sf_dir: str, hint: str = _hint) -> DataFrame:
        e = edges(spark, sf_dir, "hands_to49")
        return e.toDF("x", "m").join(e.toDF("m", "y").hint(hint), "m").select("x", "m", "y")


@query(walk("hands_to49") + "SELECT p_partkey AS k FROM part WHERE p_type = 'ECONOMY' AND p_partkey IN (SELECT x FROM r JOIN part q ON q.p_partkey = y AND q.p_type = 'PROMO' WHERE x <> y)")
def reach_semi_join(spark: SparkSession, sf_dir: str) -> DataFrame:
    s, t = _ends(spark, sf_dir)
    return reach_semi(s, "v", index(spark, sf_dir, "hands_to49").set_reach(s, t, "+")).select(F.col("v").alias("k"))


@query(walk("hands_to49") + "SELECT p_partkey AS k FROM part WHERE p_type = 'ECONOMY' AND p_partkey NOT IN (SELECT x FROM r JOIN part q ON q.p_partkey = y AND q.p_type = 'PROMO' WHERE x <> y)")
def reach_anti_join(spark: SparkSession, sf_dir: str) -> DataFrame:
    s, t = _ends(spark, sf_dir)
    return reach_semi(s, "v", index(spark, sf_dir, "hands_to49").set_reach(s, t, "+"), anti=True).select(F.col("v").alias("k"))


@query(_H + "SELECT p_partkey AS k, e.b AS y FROM part LEFT JOIN e ON e.a = p_partkey WHERE p_type = 'PROMO'")
def optional(spark: SparkSession, sf_dir: str) -> DataFrame:
    """A pattern that may be missing."""
    p = _read(spark, sf_dir, "part").where("p_type = 'PROMO'").select(F.col("p_partkey").alias("k"))
    return p.join(edges(spark, sf_dir, "hands_to49").toDF("k", "y"), "k", "left")


_BANDS = "SELECT 1 AS band, 1 AS lo, 12 AS hi UNION ALL SELECT 2, 10, 30 UNION ALL SELECT 3, 25, 50"


@query(f"SELECT p_partkey AS k, band FROM part JOIN ({_BANDS}) b ON p_size BETWEEN lo AND hi")
def range_joined(spark: SparkSession, sf_dir: str) -> DataFrame:
    bands = spark.createDataFrame([(1, 1, 12), (2, 10, 30), (3, 25, 50)], "band int, lo int, hi int")
    return range_join(_read(spark, sf_dir, "part"), bands, "p_size", "lo", "hi", 10).select(F.col("p_partkey").alias("k"), "band")


@query(
    "SELECT event_id, last_purchase FROM (SELECT event_id, event_type, last_value(CASE WHEN event_type = 'purchase' THEN event_id END IGNORE NULLS)"
    " OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN UNBOUNDED PRECEDING AND CURRENT ROW) AS last_purchase FROM events) t WHERE event_type = 'error'"
)
def asof_next(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The last purchase of the user before each error."""
    e = _read(spark, sf_dir, "events")
    right = e.where("event_type = 'purchase'").select("user_id", F.col("ts").alias("rt"), F.col("event_id").alias("last_purchase"))
    left = e.where("event_type = 'error'").select("event_id", "user_id", "ts")
    return asof_join(left, right, ["user_id"], "ts", "rt", ["last_purchase"], ["last_purchase"]).select("event_id", "last_purchase")


@query("SELECT a.event_id AS a, b.event_id AS b FROM events a JOIN events b ON a.user_id = b.user_id AND a.event_type = 'error' AND b.event_type = 'purchase' AND abs(epoch_us(a.ts) - epoch_us(b.ts)) <= 3600000000")
def interval_joined(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Errors and purchases of a user within an hour."""
    e = _read(spark, sf_dir, "events")
    one = lambda kind, n: e.where(F.col("event_type") == kind).select("user_id", F.col("event_id").alias(n), F.col("ts").alias(f"t{n}"))
    return interval_join(one("error", "a"), one("purchase", "b"), ["user_id"], "ta", "tb", 3600).select("a", "b")


for _op, _sql in (("union", "UNION ALL"), ("intersect", "INTERSECT"), ("except", "EXCEPT")):

    @query(_H + f"SELECT a AS v FROM e {_sql} SELECT b FROM e", f"set_{_op}")
    def set_operation(spark: SparkSession, sf_dir: str, op: str = _op) -> DataFrame:
        e = edges(spark, sf_dir, "hands_to49")
        a, b = e.select(F.col("s").alias("v")), e.select(F.col("t").alias("v"))
        return {"union": a.union, "intersect": a.intersect, "except": a.subtract}[op](b)


@query(walk("hands_to48", _FROM) + "SELECT x, n FROM (SELECT x, count(DISTINCT y) AS n FROM r WHERE x <> y GROUP BY x) t ORDER BY n DESC, x LIMIT 20")
def topk_reachers(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The 20 parts that reach most others."""
    ix = index(spark, sf_dir, "hands_to48")
    v = ix.edges.select(F.col("s").alias("v")).union(ix.edges.select("t")).distinct()
    pairs = ix.set_reach(_ends(spark, sf_dir)[0], v, "+")
    return pairs.groupBy("x").agg(F.countDistinct("y").alias("n")).orderBy(F.desc("n"), "x").limit(20)


@query(walk("hands_to48", _FROM) + "SELECT x, count(DISTINCT y) AS n FROM r WHERE x <> y GROUP BY x")
def reach_count(spark: SparkSession, sf_dir: str) -> DataFrame:
    ix = index(spark, sf_dir, "hands_to48")
    v = ix.edges.select(F.col("s").alias("v")).union(ix.edges.select("t")).distinct()
    return ix.set_reach(_ends(spark, sf_dir)[0], v, "+").groupBy("x").agg(F.countDistinct("y").alias("n"))


_PLACES = "SELECT n_regionkey AS region, n_nationkey AS nation, count(*) AS n FROM customer JOIN nation ON c_nationkey = n_nationkey GROUP BY "


def _places(spark: SparkSession, sf_dir: str) -> DataFrame:
    c, n = _read(spark, sf_dir, "customer"), _read(spark, sf_dir, "nation")
    return c.join(F.broadcast(n), c["c_nationkey"] == n["n_nationkey"]).select(F.col("n_regionkey").alias("region"), F.col("n_nationkey").alias("nation"))


@query(_PLACES + "ROLLUP (n_regionkey, n_nationkey)")
def reach_rollup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _places(spark, sf_dir).rollup("region", "nation").agg(F.count(F.lit(1)).alias("n"))


@query(_PLACES + "CUBE (n_regionkey, n_nationkey)")
def reach_cube(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _places(spark, sf_dir).cube("region", "nation").agg(F.count(F.lit(1)).alias("n"))


@query("SELECT p_type AS type, count(*) FILTER (WHERE p_size <= 25) AS small, count(*) FILTER (WHERE p_size > 25) AS large FROM part GROUP BY p_type")
def degree_pivot(spark: SparkSession, sf_dir: str) -> DataFrame:
    p = _read(spark, sf_dir, "part").withColumn("kind", F.when(F.col("p_size") <= 25, "small").otherwise("large"))
    return p.groupBy(F.col("p_type").alias("type")).pivot("kind", ["small", "large"]).agg(F.count(F.lit(1))).na.fill(0)


_DEG = _H + ", d AS (SELECT a AS v, count(*) AS d FROM e GROUP BY a) "


def _degrees(spark: SparkSession, sf_dir: str) -> DataFrame:
    return edges(spark, sf_dir, "hands_to49").groupBy(F.col("s").alias("v")).agg(F.count(F.lit(1)).alias("d"))


@query(_DEG + "SELECT CAST(quantile_cont(d, 0.5) AS DOUBLE) AS p50, CAST(quantile_cont(d, 0.99) AS DOUBLE) AS p99 FROM d")
def degree_pct(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _degrees(spark, sf_dir).agg(F.percentile("d", 0.5).alias("p50"), F.percentile("d", 0.99).alias("p99"))


@query(_DEG + "SELECT v, d, CAST(rank() OVER (ORDER BY d DESC) AS INTEGER) AS r, CAST(dense_rank() OVER (ORDER BY d DESC) AS INTEGER) AS dr FROM d")
def rank_degree(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Ranks of out-degrees; counts per degree are ranked, so no window holds all vertices."""
    d = _degrees(spark, sf_dir)
    per = d.groupBy("d").agg(F.count(F.lit(1)).alias("n"))
    w = Window.orderBy(F.desc("d"))
    ranks = per.select("d", (F.coalesce(F.sum("n").over(w.rowsBetween(Window.unboundedPreceding, -1)), F.lit(0)) + 1).cast("int").alias("r"), F.row_number().over(w).alias("dr"))
    return d.join(F.broadcast(ranks), "d").select("v", "d", "r", "dr")


for _name in ("next_order", "next_event", "next_turn", "relays", "relays_thin", "trades", "copy_of", "same_host", "within", "hands_to"):

    @query(f"SELECT a AS s, b AS t FROM ({RULES[_name]}) u", f"edges_{_name}")
    def rule(spark: SparkSession, sf_dir: str, name: str = _name) -> DataFrame:
        return edges(spark, sf_dir, name)


@query(NEAR_SQL.replace("SELECT a, b FROM", "SELECT a AS s, b AS t FROM", 1), "near_edges")
def near(spark: SparkSession, sf_dir: str) -> DataFrame:
    return near_edges(spark, sf_dir)


@query("SELECT doc_id AS d, item_id AS i FROM documents JOIN benchmark ON contains(documents.text, benchmark.text) AND benchmark.text <> ''")
def quotes(spark: SparkSession, sf_dir: str) -> DataFrame:
    from reachgraph.functions.ids import term_key

    return graph(spark, sf_dir).edges("quotes").select(term_key("s").alias("d"), term_key("o").alias("i"))


@query(
    "SELECT event_id, count(*) OVER w AS n, round(avg(value) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN 2 PRECEDING AND CURRENT ROW), 6) AS mean3 FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN UNBOUNDED PRECEDING AND CURRENT ROW)"
)
def window_frames(spark: SparkSession, sf_dir: str) -> DataFrame:
    w = Window.partitionBy("user_id").orderBy("ts", "event_id")
    return _read(spark, sf_dir, "events").select("event_id", F.count(F.lit(1)).over(w.rowsBetween(Window.unboundedPreceding, 0)).alias("n"), F.round(F.avg("value").over(w.rowsBetween(-2, 0)), 6).alias("mean3"))


@query("SELECT page_id, regexp_replace(regexp_replace(url, '^[a-z]+://', ''), '[/:?#].*$', '') AS host, upper(left(url, 4)) AS head, strpos(url, '.') AS dot FROM pages")
def fn_string(spark: SparkSession, sf_dir: str) -> DataFrame:
    p = _read(spark, sf_dir, "pages")
    return p.select("page_id", F.regexp_extract("url", r"^[a-z]+://([^/:?#]*)", 1).alias("host"), F.upper(F.substring("url", 1, 4)).alias("head"), F.instr("url", ".").cast("long").alias("dot"))


@query("SELECT o_orderkey AS k, date_diff('day', TIMESTAMP '1992-01-01', o_orderdate) AS days, CAST(date_trunc('month', o_orderdate) AS DATE) AS month FROM orders")
def fn_date(spark: SparkSession, sf_dir: str) -> DataFrame:
    o = _read(spark, sf_dir, "orders")
    return o.select(F.col("o_orderkey").alias("k"), F.datediff("o_orderdate", F.lit("1992-01-01")).cast("long").alias("days"), F.trunc("o_orderdate", "month").alias("month"))


@query("SELECT p_partkey AS k, round(ln(p_retailprice), 6) AS l, round(sqrt(p_retailprice), 6) AS q, p_partkey % 7 AS m FROM part")
def fn_math(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _read(spark, sf_dir, "part").select(F.col("p_partkey").alias("k"), F.round(F.log("p_retailprice"), 6).alias("l"), F.round(F.sqrt("p_retailprice"), 6).alias("q"), F.pmod("p_partkey", F.lit(7)).alias("m"))


@query(_H + "SELECT a AS v, list_sort(list_distinct(list(b))) AS adj, CAST(list_sum(list_transform(list(b), lambda x: x % 10)) AS BIGINT) AS digits FROM e GROUP BY a")
def fn_array(spark: SparkSession, sf_dir: str) -> DataFrame:
    adj = edges(spark, sf_dir, "hands_to49").groupBy(F.col("s").alias("v")).agg(F.collect_list("t").alias("l"))
    return adj.select("v", F.sort_array(F.array_distinct("l")).alias("adj"), F.aggregate("l", F.lit(0).cast("long"), lambda t, x: t + x % 10).alias("digits"))


@query("SELECT s_nationkey AS nation, count(*) FILTER (WHERE s_acctbal >= 0) AS pos, count(*) FILTER (WHERE s_acctbal < 0) AS neg FROM supplier GROUP BY s_nationkey")
def fn_map(spark: SparkSession, sf_dir: str) -> DataFrame:
    s = _read(spark, sf_dir, "supplier").withColumn("sign", F.when(F.col("s_acctbal") >= 0, "pos").otherwise("neg"))
    m = s.groupBy(F.col("s_nationkey").alias("nation"), "sign").agg(F.count(F.lit(1)).alias("n")).groupBy("nation").agg(F.map_from_entries(F.collect_list(F.struct("sign", "n"))).alias("m"))
    return m.select("nation", F.coalesce(F.element_at("m", "pos"), F.lit(0)).alias("pos"), F.coalesce(F.element_at("m", "neg"), F.lit(0)).alias("neg"))


@query("SELECT event_id, CAST(json_extract_string(props, '$.k') AS BIGINT) AS k FROM events")
def fn_json(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _read(spark, sf_dir, "events").select("event_id", F.get_json_object("props", "$.k").cast("long").alias("k"))


@query("SELECT o_orderkey AS k, CAST(CAST(o_totalprice AS DECIMAL(18,2)) AS VARCHAR) AS price FROM orders")
def fn_decimal(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _read(spark, sf_dir, "orders").select(F.col("o_orderkey").alias("k"), F.col("o_totalprice").cast("decimal(18,2)").cast("string").alias("price"))


@query("SELECT event_id, user_id, event_type FROM events")
def stream_dedupe(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Events read as a stream, without repeats."""
    return batch_replay(spark, sf_dir, lambda s: s.dropDuplicatesWithinWatermark(["event_id"]).select("event_id", "user_id", "event_type"))


@query("SELECT CAST(epoch(time_bucket(INTERVAL 1 HOUR, ts)) AS BIGINT) AS start, event_type, count(*) AS n FROM events GROUP BY 1, 2")
def stream_tumbling(spark: SparkSession, sf_dir: str) -> DataFrame:
    return windowed_counts(spark, sf_dir, "1 hour")


@query("SELECT start, event_type, count(*) AS n FROM (SELECT event_type, unnest([CAST(epoch(time_bucket(INTERVAL 30 MINUTES, ts)) AS BIGINT), CAST(epoch(time_bucket(INTERVAL 30 MINUTES, ts)) AS BIGINT) - 1800]) AS start FROM events) t GROUP BY 1, 2")
def stream_sliding(spark: SparkSession, sf_dir: str) -> DataFrame:
    return windowed_counts(spark, sf_dir, "1 hour", "30 minutes")


@query(
    "WITH g AS (SELECT user_id, ts, CASE WHEN lag(ts) OVER w IS NULL OR epoch_us(ts) - epoch_us(lag(ts) OVER w) >= 1800000000 THEN 1 ELSE 0 END AS fresh FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts)),"
    " s AS (SELECT user_id, ts, sum(fresh) OVER (PARTITION BY user_id ORDER BY ts) AS k FROM g) SELECT user_id, CAST(epoch_us(min(ts)) AS BIGINT) AS start, count(*) AS n FROM s GROUP BY user_id, k"
)
def stream_session(spark: SparkSession, sf_dir: str) -> DataFrame:
    return batch_replay(
        spark, sf_dir, lambda s: s.groupBy(F.session_window("ts", "30 minutes").alias("w"), "user_id").agg(F.count(F.lit(1)).alias("n")).select("user_id", F.unix_micros("w.start").alias("start"), "n"), mode="complete"
    )


@query(f"SELECT a AS s, b AS t FROM ({RULES['next_event']}) u")
def stream_edges(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Edges from each event of a user to the next, kept up in state."""
    return next_events(spark, sf_dir)


@query("SELECT e.event_type, u.n_errors, count(*) AS n FROM events e JOIN (SELECT user_id, count(*) AS n_errors FROM events WHERE event_type = 'error' GROUP BY user_id) u ON e.user_id = u.user_id GROUP BY 1, 2")
def stream_join(spark: SparkSession, sf_dir: str) -> DataFrame:
    return static_counts(spark, sf_dir)
