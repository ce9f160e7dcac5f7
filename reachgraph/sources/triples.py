"""Tables as properties and as triples; N-Triples; edge lists; index folders."""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from reachgraph.functions.ids import literal_id, term_id
from reachgraph.sources.graphs import edges


@dataclass(frozen=True)
class TripleMapping:
    """One property: a table, its subject and its object, and whether rows repeat."""

    prop: str
    table: str
    subject: Column
    object: Column
    where: str = "true"
    distinct: bool = False
    literal: Column | None = None  # text of the object, for the dictionary

    def rows(self, spark: SparkSession, sf_dir: str) -> DataFrame:
        df = spark.read.parquet(f"{sf_dir}/{self.table}.parquet").where(self.where)
        df = df.select(self.subject.alias("s"), self.object.alias("o")).where("s is not null and o is not null")
        return df.distinct() if self.distinct else df


def _lit(prop: str, table: str, kind: str, key: str, value: str, where: str = "true") -> TripleMapping:
    return TripleMapping(prop, table, term_id(kind, key), literal_id(value), where, False, F.col(value))


def _link(prop: str, table: str, a: tuple[str, str], b: tuple[str, str], distinct: bool = False) -> TripleMapping:
    return TripleMapping(prop, table, term_id(*a), term_id(*b), "true", distinct)


def _turn() -> Column:
    return term_id("turn", F.col("conv_id") * 100000 + F.col("turn"))


_HOST = r"^[a-z]+://([^/:?#]*)"

#: Declared lazily: columns need a running session.
def mappings() -> list[TripleMapping]:
    """The plain properties of the given tables."""
    named = [_lit("named", t, k, f"{c}_{i}", f"{c}_name") for t, k, c, i in (("region", "region", "r", "regionkey"), ("nation", "nation", "n", "nationkey"), ("customer", "customer", "c", "custkey"), ("supplier", "supplier", "s", "suppkey"), ("part", "part", "p", "partkey"))]
    host = F.regexp_extract("url", _HOST, 1)
    return [
        _link("in_region", "nation", ("nation", "n_nationkey"), ("region", "n_regionkey")),
        _link("in_nation", "customer", ("customer", "c_custkey"), ("nation", "c_nationkey")),
        _link("in_nation", "supplier", ("supplier", "s_suppkey"), ("nation", "s_nationkey")),
        _link("placed_by", "orders", ("order", "o_orderkey"), ("customer", "o_custkey")),
        _link("has_part", "lineitem", ("order", "l_orderkey"), ("part", "l_partkey"), True),
        _link("filled_by", "lineitem", ("order", "l_orderkey"), ("supplier", "l_suppkey"), True),
        _link("supplies", "lineitem", ("supplier", "l_suppkey"), ("part", "l_partkey"), True),
        _lit("segment", "customer", "customer", "c_custkey", "c_mktsegment"),
        _lit("status", "orders", "order", "o_orderkey", "o_orderstatus"),
        _lit("priority", "orders", "order", "o_orderkey", "o_orderpriority"),
        _lit("brand", "part", "part", "p_partkey", "p_brand"),
        _lit("type", "part", "part", "p_partkey", "p_type"),
        _lit("size", "part", "part", "p_partkey", "p_size"),
        *named,
        _link("done_by", "events", ("event", "event_id"), ("user", "user_id")),
        _lit("event_kind", "events", "event", "event_id", "event_type"),
        _lit("in_lang", "documents", "document", "doc_id", "lang"),
        _lit("from_source", "documents", "document", "doc_id", "source"),
        _lit("quality", "labels", "document", "doc_id", "quality"),
        _lit("toxic", "labels", "document", "doc_id", "toxic"),
        TripleMapping("on_host", "pages", term_id("page", "page_id"), literal_id(host), "url is not null", False, host),
        _lit("in_class", "embeddings", "vector", "vec_id", "label"),
        TripleMapping("turn_of", "conversations", _turn(), term_id("conversation", "conv_id")),
        TripleMapping("spoken_by", "conversations", _turn(), literal_id("role"), "true", False, F.col("role")),
    ]


#: Kind of the vertices of each transitive graph; ``within`` carries kinds already.
GRAPH_KINDS = {"next_order": "order", "next_event": "event", "next_turn": "turn", "hands_to": "part", "hands_to48": "part", "hands_to49": "part", "relays": "supplier", "relays_thin": "supplier", "trades": "nation", "copy_of": "document", "same_host": "page", "near": "vector", "within": None}


def quotes(spark: SparkSession, sf_dir: str, block: int = 10_000) -> DataFrame:
    """(s, o): documents and the benchmark items that their texts contain as they stand; ``block`` items at a time are broadcast."""
    items = spark.read.parquet(f"{sf_dir}/benchmark.parquet").where("text <> ''").select("item_id", F.col("text").alias("passage"))
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet").select("doc_id", "text")
    blocks = max(1, -(-items.count() // block))
    out = None
    for b in range(blocks):
        part = items if blocks == 1 else items.where(F.pmod(F.xxhash64("item_id", "passage"), F.lit(blocks)) == b)
        one = docs.join(F.broadcast(part), F.contains("text", "passage")).select(term_id("document", "doc_id").alias("s"), term_id("benchmark", "item_id").alias("o"))
        out = one if out is None else out.union(one)
    return out


def properties(spark: SparkSession, sf_dir: str) -> dict[str, Callable[[], DataFrame]]:
    """All properties by name, each a function that reads its edges (s, o) with tagged ids."""
    out: dict[str, Callable[[], DataFrame]] = {}
    by: dict[str, list[TripleMapping]] = {}
    for m in mappings():
        by.setdefault(m.prop, []).append(m)

    def plain(ms: list[TripleMapping]) -> Callable[[], DataFrame]:
        def read() -> DataFrame:
            df = ms[0].rows(spark, sf_dir)
            for m in ms[1:]:
                df = df.unionByName(m.rows(spark, sf_dir))
            return df

        return read

    def graph(name: str, kind: str | None) -> Callable[[], DataFrame]:
        def read() -> DataFrame:
            e = edges(spark, sf_dir, name)
            return e.select("s", "t").toDF("s", "o") if kind is None else e.select(term_id(kind, "s").alias("s"), term_id(kind, "t").alias("o"))

        return read

    out |= {name: plain(ms) for name, ms in by.items()}
    out |= {name: graph(name, kind) for name, kind in GRAPH_KINDS.items()}
    out["quotes"] = lambda: quotes(spark, sf_dir)
    return out


def property_ids(names: list[str]) -> dict[str, int]:
    """Small integer per property, in order of their names."""
    return {p: i for i, p in enumerate(sorted(names))}


def to_triples(spark: SparkSession, sf_dir: str, names: list[str]) -> DataFrame:
    """(s, p, o) of the named properties, without repeats."""
    props, ids = properties(spark, sf_dir), property_ids(names)
    df = None
    for name in names:
        one = props[name]().where("s is not null and o is not null").select("s", F.lit(ids[name]).alias("p"), "o")
        one = one.distinct()  # properties differ in p, so repeats are within one
        df = one if df is None else df.union(one)
    return df


def dictionary(spark: SparkSession, sf_dir: str, names: list[str] | None = None) -> DataFrame:
    """(id, lex): every literal of the plain properties. ``sound_dictionary`` also looks for ids with two texts."""
    df = None
    for m in mappings():
        if m.literal is None or names and m.prop not in names:
            continue
        one = spark.read.parquet(f"{sf_dir}/{m.table}.parquet").where(m.where).select(literal_id(m.literal).alias("id"), m.literal.cast("string").alias("lex")).where("lex is not null")
        df = one if df is None else df.union(one)
    return df.distinct()


def audit(terms: DataFrame) -> DataFrame:
    """Ids that stand for more than one text; no rows if the dictionary is sound."""
    return terms.groupBy("id").agg(F.count(F.lit(1)).alias("n")).where("n > 1")


def sound_dictionary(spark: SparkSession, sf_dir: str, names: list[str] | None = None) -> DataFrame:
    """``dictionary`` after ``audit``; two texts with one id are an error, never one term."""
    terms = dictionary(spark, sf_dir, names)
    if twice := audit(terms).limit(1).collect():
        raise ValueError(f"literal id {twice[0].id} stands for several texts; use wider ids")
    return terms


def encode(df: DataFrame, text: str, to: str) -> DataFrame:
    """Add the id of a text column."""
    return df.withColumn(to, literal_id(text))


def decode(df: DataFrame, column: str, terms: DataFrame, to: str) -> DataFrame:
    """Add the text of an id column; null for ids that are no literals."""
    return df.join(terms.select(F.col("id").alias(column), F.col("lex").alias(to)), column, "left")


#: One line of the N-Triples format.
_LINE = r'^\s*(<[^>]*>|_:\S+)\s+(<[^>]*>)\s+(<[^>]*>|_:\S+|"(?:[^"\\]|\\.)*"(?:@[A-Za-z0-9-]+|\^\^<[^>]*>)?)\s*\.\s*(?:#.*)?$'


def read_ntriples(spark: SparkSession, path: str) -> DataFrame:
    """(s, p, o) as text; comments and blank lines are passed over, malformed lines raise an error when read."""
    lines = spark.read.text(path).where(~F.col("value").rlike(r"^\s*(#.*)?$"))
    part = lambda i: F.regexp_extract("value", _LINE, i)
    sound = F.when(F.col("value").rlike(_LINE), part(1)).otherwise(F.raise_error(F.concat(F.lit("not a triple: "), "value")))
    return lines.select(sound.alias("s"), part(2).alias("p"), part(3).alias("o"))


def write_ntriples(triples: DataFrame, path: str) -> None:
    """Write text triples (s, p, o), one per line."""
    triples.select(F.concat_ws(" ", "s", "p", "o", F.lit("."))).write.mode("overwrite").text(path)


def read_edges(spark: SparkSession, fmt: str, path: str) -> DataFrame:
    """Edge list (s, t) of longs from csv, json, orc or parquet; nothing is inferred."""
    reader = spark.read.schema("s long, t long")
    return reader.option("header", True).csv(path) if fmt == "csv" else reader.format(fmt).load(path)
