"""The graphs under test: one SQL rule each, readable by Spark and by DuckDB.

``{orders}`` and the like stand for the tables. Every rule gives distinct edges
(a, b) as BIGINT.
"""

from __future__ import annotations

import re
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from reachgraph.functions.ids import BASE, KINDS

TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()


def _id(kind: str, key: str) -> str:
    return f"({KINDS[kind] * BASE} + CAST({key} AS BIGINT))"


def _next(table: str, key: str, group: str, order: str, where: str = "1 = 1") -> str:
    return (
        f"SELECT a, b FROM (SELECT {key} AS a, lead({key}) OVER (PARTITION BY {group} ORDER BY {order}) AS b FROM {{{table}}} WHERE {where}) n"
        " WHERE b IS NOT NULL"
    )


def _handed(column: str, where: str) -> str:
    return (
        f"SELECT DISTINCT x.{column} AS a, y.{column} AS b FROM {{lineitem}} x JOIN {{lineitem}} y"
        f" ON x.l_orderkey = y.l_orderkey AND y.l_linenumber = x.l_linenumber + 1 WHERE {where} AND x.{column} <> y.{column}"
    )


RULES = {
    "within": " UNION ALL ".join(
        (
            f"SELECT {_id('customer', 'c_custkey')} AS a, {_id('nation', 'c_nationkey')} AS b FROM {{customer}} WHERE c_nationkey IS NOT NULL",
            f"SELECT {_id('supplier', 's_suppkey')}, {_id('nation', 's_nationkey')} FROM {{supplier}} WHERE s_nationkey IS NOT NULL",
            f"SELECT {_id('nation', 'n_nationkey')}, {_id('region', 'n_regionkey')} FROM {{nation}} WHERE n_regionkey IS NOT NULL",
        )
    ),
    "next_order": _next("orders", "o_orderkey", "o_custkey", "o_orderdate, o_orderkey"),
    "next_event": _next("events", "event_id", "user_id", "ts, event_id"),
    "next_turn": _next("conversations", "(conv_id * 100000 + turn)", "conv_id", "turn"),
    "hands_to": _handed("l_partkey", "x.l_quantity >= 47"),
    "hands_to48": _handed("l_partkey", "x.l_quantity >= 48"),
    "hands_to49": _handed("l_partkey", "x.l_quantity >= 49"),
    "relays": _handed("l_suppkey", "x.l_quantity >= 50"),
    "relays_thin": _handed("l_suppkey", "x.l_quantity >= 45 AND x.l_returnflag = 'R' AND x.l_discount >= 0.09"),
    "trades": (
        "SELECT DISTINCT CAST(s_nationkey AS BIGINT) AS a, CAST(c_nationkey AS BIGINT) AS b FROM {lineitem} JOIN {supplier} ON l_suppkey = s_suppkey"
        " JOIN {orders} ON l_orderkey = o_orderkey JOIN {customer} ON o_custkey = c_custkey"
        " WHERE l_quantity >= 50 AND l_discount >= 0.10 AND l_returnflag = 'R' AND s_nationkey <> c_nationkey"
    ),
    "copy_of": _next("documents", "doc_id", "text", "doc_id", "text IS NOT NULL"),
    "same_host": _next("pages", "page_id", "regexp_replace(regexp_replace(url, '^[a-z]+://', ''), '[/:?#].*$', '')", "page_id", "url IS NOT NULL"),
}


def tables(spark: SparkSession, sf_dir: str, names: list[str] | None = None) -> dict[str, DataFrame]:
    """The given tables of a directory, by name."""
    return {t: spark.read.parquet(f"{sf_dir}/{t}.parquet") for t in names or TABLES}


def spark_sql(spark: SparkSession, sf_dir: str, text: str) -> DataFrame:
    """Run a rule or query with ``{table}`` placeholders over a directory."""
    return spark.sql(text, **tables(spark, sf_dir, sorted(set(re.findall(r"\{(\w+)\}", text)))))


def duck_sql(text: str) -> str:
    """The same text for an engine where the tables are views."""
    return re.sub(r"\{(\w+)\}", r"\1", text)


def edges(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    """Edges (s, t) of a graph."""
    if name == "near":
        return near_edges(spark, sf_dir)
    return spark_sql(spark, sf_dir, RULES[name]).selectExpr("CAST(a AS BIGINT) AS s", "CAST(b AS BIGINT) AS t")


NEAR_SQL = (
    "SELECT a, b FROM (SELECT x.vec_id AS a, y.vec_id AS b, row_number() OVER (PARTITION BY x.vec_id ORDER BY"
    " round(list_sum(list_transform(list_zip(x.embedding, y.embedding), lambda p: CAST(p[1] AS DOUBLE) * CAST(p[2] AS DOUBLE)))"
    " / sqrt(list_sum(list_transform(y.embedding, lambda p: CAST(p AS DOUBLE) * CAST(p AS DOUBLE)))), 12) DESC, y.vec_id) AS r"
    " FROM embeddings x JOIN embeddings y ON x.vec_id <> y.vec_id) n WHERE r <= 3"
)


def near_edges(spark: SparkSession, sf_dir: str, neighbours: int = 3, block: int = 8192) -> DataFrame:
    """Edges (s, t) from each vector to its nearest by cosine, ties to the smaller id.

    Every vector is asked for. ``block`` of them at a time go to the executors
    as one matrix and pass over all vectors, a slice at a time; a task keeps the
    best it has met so far alone, and the best of these are picked in the end.
    """
    v = spark.read.parquet(f"{sf_dir}/embeddings.parquet").select("vec_id", F.col("embedding").cast("array<double>").alias("e")).where("e is not null")
    blocks = max(1, -(-v.count() // block))
    found = None
    for b in range(blocks):
        part = v if blocks == 1 else v.where(F.pmod(F.xxhash64("vec_id"), F.lit(blocks)) == b)
        rows = part.orderBy("vec_id").toArrow()
        if not rows.num_rows:
            continue
        ids = rows["vec_id"].to_numpy()
        matrix = np.array(rows["e"].to_pylist(), dtype=np.float64)
        one = v.mapInArrow(_nearest(ids, matrix, neighbours), "s long, t long, likeness double")
        found = one if found is None else found.unionByName(one)
    if found is None:
        return spark.createDataFrame([], "s long, t long")
    best = Window.partitionBy("s").orderBy(F.desc("likeness"), "t")
    return found.withColumn("r", F.row_number().over(best)).where(F.col("r") <= neighbours).select("s", "t")


#: Likenesses that a task holds at a time.
CELLS = 1 << 20


def _nearest(ids: np.ndarray, matrix: np.ndarray, neighbours: int):
    schema = pa.schema([("s", pa.int64()), ("t", pa.int64()), ("likeness", pa.float64())])
    # a product of matrices is this near to the sums in order, rounding to 12 digits included
    slack = 2e-12 + 1e-12 * np.sqrt(np.nan_to_num((matrix * matrix).sum(axis=1)))
    step = max(1, CELLS // max(1, len(ids)))

    def better(best: tuple[np.ndarray, ...], others: np.ndarray, rows: np.ndarray) -> tuple[np.ndarray, ...]:
        who, there, likeness = best
        size = np.zeros(len(others))
        for d in range(matrix.shape[1]):  # summed in the order of the dimensions, as the definition does
            size += rows[:, d] * rows[:, d]
        about = (matrix @ rows.T) / np.sqrt(size)
        about[~np.isfinite(about) | (ids[:, None] == others[None, :])] = -np.inf
        least = np.full(len(ids), -np.inf)
        full = np.flatnonzero(np.bincount(who, minlength=len(ids)) >= neighbours)
        least[full] = likeness[np.searchsorted(who, full, "right") - 1]  # the last of each is its least
        if len(others) > neighbours:
            least = np.maximum(least, np.partition(about, -neighbours, axis=1)[:, -neighbours])
        i, j = np.nonzero((about >= (least - slack)[:, None]) & (about > -np.inf))
        dot = np.zeros(len(i))
        for d in range(matrix.shape[1]):
            dot += matrix[i, d] * rows[j, d]
        who, there = np.concatenate([who, i]), np.concatenate([there, others[j]])
        likeness = np.concatenate([likeness, np.round(dot / np.sqrt(size[j]), 12)])
        by = np.lexsort((there, -likeness, who))
        who, there, likeness = who[by], there[by], likeness[by]
        few = np.arange(len(who)) - np.searchsorted(who, who) < neighbours
        return who[few], there[few], likeness[few]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        best = np.empty(0, dtype=np.int64), np.empty(0, dtype=np.int64), np.empty(0)
        with np.errstate(all="ignore"):
            for batch in batches:
                for lo in range(0, batch.num_rows, step):
                    part = batch.slice(lo, step)
                    rows = part.column("e").flatten().to_numpy(zero_copy_only=False).reshape(part.num_rows, -1)
                    best = better(best, part.column("vec_id").to_numpy(), rows)
        who, there, likeness = best
        yield pa.RecordBatch.from_arrays([pa.array(c) for c in (ids[who], there, likeness)], schema=schema)

    return run
