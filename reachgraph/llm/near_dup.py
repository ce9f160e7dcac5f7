"""Near-duplicate documents by MinHash with tensored banding.

A document is the set of its distinct word shingles. Documents with equal sets
are one node, however many there are. A node gets a few small collections of
minhashes; a hash table is keyed by a *pair* of collections, so that m
collections of r minhashes serve m(m-1)/2 tables of 2r minhashes each, at about
the square root of the hashing that separate tables would take. Two nodes meet
if any two collections agree: with m=12 and r=2 a pair of similarity 0.8 is
missed with probability 0.0001, one of 0.9 with 0.00000002. Every link is
confirmed on the full sets.

In a large bucket nodes that are linked with none of its representatives are
not held against all others. A prefix filter finds the possible links: shingles
are ordered from rare to frequent, and two sets that reach the threshold share a
shingle early in this order, the earlier the closer their sizes are. What is
left of both sets from that shingle on must suffice for the overlap, so that
copies of one text which differ in shingles of their own never meet.
"""

from __future__ import annotations

import math
from collections.abc import Callable, Iterator
from itertools import combinations

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from reachgraph.llm.common import bound_batches, stored, sweep
from reachgraph.llm.components import bucket_components

COLLECTIONS, ROWS = 12, 2
#: Ratio of the bounds of the size classes in which the prefix filter looks.
SIZE_STEP = 1.02


class Shingler:
    """Sorted 64-bit hashes of the distinct word shingles of texts.

    Words are runs of anything but blank, tab, line feed, vertical tab, form
    feed and carriage return; only A-Z are lower-cased.
    """

    def __init__(self, width: int) -> None:
        self.width = width
        self.memo: dict[bytes, int] = {}

    def _word(self, word: bytes) -> int:
        value = self.memo.get(word)
        if value is None:
            if len(self.memo) > 300_000:
                self.memo.clear()
            value = self.memo[word] = xxhash.xxh64_intdigest(word)
        return value

    def __call__(self, text: str | None) -> np.ndarray:
        words = (text or "").encode("utf-8", "surrogatepass").lower().split()
        if not words:
            return np.empty(0, dtype=np.uint64)
        h = np.fromiter(map(self._word, words), dtype=np.uint64, count=len(words))
        width = min(self.width, len(h))
        out = np.full(len(h) - width + 1, len(h) if len(h) < self.width else 0, dtype=np.uint64)
        for i in range(width):
            out = out * np.uint64(0x9E3779B97F4A7C15) + h[i : len(h) - width + 1 + i]
            out ^= out >> np.uint64(29)
        return np.unique(_mixed(out))


def _mixed(x: np.ndarray) -> np.ndarray:
    x = (x ^ (x >> np.uint64(30))) * np.uint64(0xBF58476D1CE4E5B9)
    x = (x ^ (x >> np.uint64(27))) * np.uint64(0x94D049BB133111EB)
    return x ^ (x >> np.uint64(31))


def minhash_collections(shingles: np.ndarray, collections: int, rows: int, seed: int = 11) -> np.ndarray:
    """One hash per collection over its ``rows`` minhashes."""
    salts = np.random.default_rng(seed).integers(0, 2**63, size=(collections * rows, 1), dtype=np.uint64)
    low = np.full(collections * rows, np.iinfo(np.uint64).max)
    for part in np.array_split(shingles, -(-len(shingles) // 2048)):  # as much as stays in the cache
        np.minimum(low, _mixed(part ^ salts).min(axis=1), out=low)
    out = np.zeros(collections, dtype=np.uint64)
    for row in low.reshape(collections, rows).T:
        out = out * np.uint64(0x9E3779B97F4A7C15) ^ row
    return out


def _signatures(width: int, collections: int, rows: int, least: int):
    schema = pa.schema([("doc_id", pa.int64()), ("tie", pa.int64()), ("set", pa.binary()), ("n", pa.int64()), ("keys", pa.list_(pa.int64()))])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        shingle = Shingler(width)
        for batch in batches:
            nodes, sizes, keys = [], [], []
            for text in batch.column("text"):
                s = shingle(text.as_py())
                sizes.append(len(s))
                nodes.append(xxhash.xxh3_128_digest(s.tobytes()) if len(s) else None)
                keys.append(minhash_collections(s, collections, rows).view(np.int64).tolist() if len(s) >= least else None)
            arrays = [batch.column("doc_id"), batch.column("tie"), pa.array(nodes, type=pa.binary()), pa.array(sizes, type=pa.int64()), pa.array(keys, type=pa.list_(pa.int64()))]
            yield pa.RecordBatch.from_arrays(arrays, schema=schema)

    return run


def _linked(width: int, percent: int):
    schema = pa.schema([("a", pa.int64()), ("b", pa.int64())])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        shingle = Shingler(width)
        held: dict[int, np.ndarray] = {}

        def of(node: int, text: pa.StringScalar) -> np.ndarray:
            if node not in held:
                if len(held) > 64:
                    held.clear()
                held[node] = shingle(text.as_py())
            return held[node]

        for batch in batches:
            found_a, found_b = [], []
            for a, b, ta, tb in zip(batch.column("a").to_pylist(), batch.column("b").to_pylist(), batch.column("ta"), batch.column("tb"), strict=True):
                sb = of(b, tb)
                sa = shingle(ta.as_py())
                both = len(np.intersect1d(sa, sb, assume_unique=True))
                if 100 * both >= percent * (len(sa) + len(sb) - both):
                    found_a.append(a)
                    found_b.append(b)
            yield pa.RecordBatch.from_arrays([pa.array(found_a, type=pa.int64()), pa.array(found_b, type=pa.int64())], schema=schema)

    return run


def _verifier(texts: DataFrame, width: int, percent: int) -> Callable[[DataFrame], DataFrame]:
    def verify(pairs: DataFrame) -> DataFrame:
        a = texts.select(F.col("node").alias("a"), F.col("n").alias("na"), F.col("text").alias("ta"))
        b = texts.select(F.col("node").alias("b"), F.col("n").alias("nb"), F.col("text").alias("tb"))
        near = F.lit(100) * F.least("na", "nb") >= F.lit(percent) * F.greatest("na", "nb")
        return pairs.join(a, "a").join(b, "b").where(near).select("a", "b", "ta", "tb").mapInArrow(_linked(width, percent), "a long, b long")

    return verify


def _set_rows(width: int):
    schema = pa.schema([("node", pa.int64()), ("n", pa.int64()), ("shingle", pa.int64())])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        shingle = Shingler(width)
        for batch in batches:
            for node, text in zip(batch.column("node").to_pylist(), batch.column("text"), strict=True):
                s = shingle(text.as_py())
                size = np.full(len(s), len(s))
                yield pa.RecordBatch.from_arrays([pa.array(np.full(len(s), node)), pa.array(size), pa.array(s.view(np.int64))], schema=schema)

    return run


def set_rows(texts: DataFrame, nodes: DataFrame, width: int) -> DataFrame:
    """(node, n, shingle, m): the shingles of some nodes that several of them have, and how many do."""
    rows = stored(texts.join(nodes, "node", "left_semi").select("node", "text").mapInArrow(_set_rows(width), "node long, n long, shingle long"), "sets")
    common = rows.groupBy("shingle").agg(F.count(F.lit(1)).alias("m")).where("m > 1")
    return stored(rows.join(common, "shingle").select("node", "n", "shingle", "m"), "sets")


def possible_links(rows: DataFrame, open_: DataFrame, percent: int) -> DataFrame:
    """(a, b): pairs of ``open_(node, label, outer)`` of different labels, one outer, among them all that reach the threshold.

    ``rows`` is what ``set_rows`` gives for these nodes and maybe others. A
    shingle has the rank ``left``, the number of shingles of its set that are
    not before it in the order from rare to frequent. Shingles of one set alone
    take their places in it, but meet nothing. Of two sets the smaller one is
    found under its size class; the larger one asks each class that it can be
    linked with, for as many of its first shingles as that class calls for.
    """
    last = Window.partitionBy("node").orderBy(F.desc("m"), F.desc("shingle"))
    ranked = rows.join(open_.select("node"), "node", "left_semi").select("node", "n", "shingle", F.row_number().over(last).alias("left"))
    # of two sets of sizes n and m that are linked, the overlap is percent * (n + m) / (100 + percent) at least
    least = lambda total: F.lit(percent) * total <= F.lit(100 + percent) * F.col("left")
    fewest = F.ceil(F.lit(percent) * F.col("n") / 100)  # shingles of a set that is linked with one of n
    ranked = stored(ranked.where(least(F.col("n") + fewest)).join(open_, "node"), "ranked")
    grade = lambda n: F.floor(F.log(n) / F.lit(math.log(SIZE_STEP)) + F.lit(1e-9)).cast("int")
    # outer sets meet all others, those of the main component only outer ones
    short = ranked.where(least(2 * F.col("n"))).select(
        grade(F.col("n")).alias("grade"), "shingle", (~F.col("outer")).alias("tame"), *[F.col(c).alias(f"s_{c}") for c in ("node", "n", "label", "left")]
    )
    asked = F.sequence(grade(fewest), grade(F.col("n")))
    low = F.greatest(F.floor(F.pow(F.lit(SIZE_STEP), F.col("grade"))) - 1, fewest)
    long = ranked.withColumn("grade", F.explode(asked)).where(least(F.col("n") + low))
    sides = F.when(F.col("outer"), F.array(F.lit(False), F.lit(True))).otherwise(F.array(F.lit(False)))
    long = long.select("grade", "shingle", F.explode(sides).alias("tame"), "node", "n", "label", "left")
    enough = lambda left: F.lit(percent) * (F.col("n") + F.col("s_n")) <= F.lit(100 + percent) * F.col(left)
    order = (F.col("s_n") < F.col("n")) | (F.col("s_n") == F.col("n")) & (F.col("s_node") < F.col("node"))
    return (
        long.join(short, ["grade", "shingle", "tame"])
        .where(order & (F.col("label") != F.col("s_label")) & enough("left") & enough("s_left"))
        .select(F.greatest("node", "s_node").alias("a"), F.least("node", "s_node").alias("b"))
        .distinct()
    )


def near_duplicates(
    docs: DataFrame,
    *,
    id_col: str = "doc_id",
    text_col: str = "text",
    width: int = 5,
    percent: int = 80,
    collections: int = COLLECTIONS,
    rows: int = ROWS,
) -> DataFrame:
    """doc_id, tie, n_shingles, component_id, kept: one row per input row.

    Documents are linked if their shingle sets overlap by ``percent`` or more of
    the union; ``component_id`` is the smallest id that links lead to. A text
    with fewer than ``width`` words is one shingle. Null texts and texts without
    words have an empty set and are linked with nothing. ``kept`` marks rows
    whose id is the component's; a component without any id keeps its rows. Null
    ids take part, but never name a component that has an id. Repeated rows are
    of one component. ``tie`` is the hash of the text, to tell apart rows that
    share an id. Other columns are not read; an empty table gives an empty result.
    """
    spark = docs.sparkSession
    bound_batches(spark)
    # two different sets reach the threshold only if the smaller one has this many shingles
    least = max(1, -(-percent // max(1, 100 - percent))) if percent < 100 else 1
    plain = docs.select(
        F.col(id_col).cast("long").alias("doc_id"),
        F.coalesce(F.xxhash64(F.col(text_col)), F.lit(0).cast("long")).alias("tie"),
        F.col(text_col).cast("string").alias("text"),
    )
    sigs = stored(plain.mapInArrow(_signatures(width, collections, rows, least), "doc_id long, tie long, set binary, n long, keys array<long>"), "sigs")
    nodes = sigs.where("set is not null").groupBy("set")
    nodes = nodes.agg(F.min("doc_id").alias("first_id"), F.min(F.struct("doc_id", "tie")).alias("rep"), F.first("n").alias("n"), F.first("keys").alias("keys"))
    # numbers are given once and written down, so that they stay
    nodes = stored(nodes.withColumn("node", F.monotonically_increasing_id()), "nodes")
    # the pairs of collections are a constant, exploded first, so that the compiled code stays small
    tables = ", ".join(f"named_struct('t', {t}, 'i', {i}, 'j', {j})" for t, (i, j) in enumerate(combinations(range(collections), 2)))
    each = nodes.where("keys is not null").select("node", "keys", F.explode(F.expr(f"array({tables})")).alias("one"))
    buckets = each.select(F.xxhash64("one.t", F.col("keys")[F.col("one.i")], F.col("keys")[F.col("one.j")]).alias("key"), "node")

    texts: list[DataFrame] = []

    def verifier(members: DataFrame) -> Callable[[DataFrame], DataFrame]:
        wanted = members.select("node").distinct().join(nodes, "node").select("node", "n", F.col("rep.doc_id").alias("doc_id"), F.col("rep.tie").alias("tie"))
        both = plain["doc_id"].eqNullSafe(wanted["doc_id"]) & (plain["tie"] == wanted["tie"])
        found = plain.join(wanted, both).select("node", "n", "text")
        texts.append(stored(found.groupBy("node", "n").agg(F.first("text").alias("text")), "texts"))
        return _verifier(texts[0], width, percent)

    sets: list[DataFrame] = []

    def weigh(some: DataFrame) -> DataFrame:
        # the copy whose shingles most others have is nearest to all of them
        sets.append(set_rows(texts[0], some, width))
        return sets[0].groupBy("node").agg((F.sum("m") / F.max("n")).alias("weight"))

    labels = bucket_components(buckets, verifier, lambda open_: possible_links(sets[0], open_, percent), weigh)
    own = nodes.select("set", "node", "first_id").join(labels, "node", "left")
    first = stored(own.where("label is not null").groupBy("label").agg(F.min("first_id").alias("of_label")), "first")
    named = own.join(first, "label", "left").select("set", F.when(F.col("label").isNull(), F.col("first_id")).otherwise(F.col("of_label")).alias("first_id"))
    named = stored(named, "named")
    sweep(spark)
    component = F.when(F.col("set").isNull(), F.col("doc_id")).otherwise(F.col("first_id"))
    return sigs.join(named, "set", "left").select(
        "doc_id", "tie", F.col("n").alias("n_shingles"), component.alias("component_id"), F.col("doc_id").eqNullSafe(component).alias("kept")
    )


def drop_near_duplicates(docs: DataFrame, **options: object) -> DataFrame:
    """The documents of which one per component stays, with all their columns."""
    id_col, text_col = str(options.get("id_col", "doc_id")), str(options.get("text_col", "text"))
    marks = near_duplicates(docs, **options).where("kept").select(F.col("doc_id").alias("_id"), F.col("tie").alias("_tie"))
    tie = F.coalesce(F.xxhash64(F.col(text_col)), F.lit(0).cast("long"))
    rows = docs.withColumn("_text", tie).dropDuplicates([id_col, "_text"])
    same = rows[id_col].cast("long").eqNullSafe(marks["_id"]) & (rows["_text"] == marks["_tie"])
    return rows.join(marks, same, "left_semi").drop("_text")
