"""Exact top-k inner products with an impact-ordered, score-at-a-time index.

Vectors become integers. A shard of them is indexed by dimension: the posting
list of a dimension is sorted by value and cut into segments, each of which has
a quantised impact (its smallest and largest value). A query visits the segments
of all dimensions in descending order of what they can add, adding the segment's
guaranteed contribution to one accumulator per vector. From time to time it
bounds what any vector can still gain; it stops only when that bound proves that
all but a few vectors are out, and scores those few exactly.

Queries come in blocks of a fixed size, so what is sent to the executors does
not grow with the data; every block passes over all shards.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from reachgraph.llm.common import table

SCALE = 1024
LEVELS = 24


class ImpactIndex:
    """Postings of one shard. ``vectors`` is an integer matrix, one row per vector."""

    def __init__(self, ids: np.ndarray, vectors: np.ndarray, levels: int | None = None) -> None:
        self.ids, self.vectors = ids, vectors
        n, dims = vectors.shape
        levels = levels or min(LEVELS, max(4, n // 512))
        cuts = np.unique(np.linspace(0, n, min(levels, n) + 1).astype(np.int64))
        self.dim: list[int] = []
        self.members: list[np.ndarray] = []
        low, high = [], []
        for d in range(dims):
            order = np.argsort(vectors[:, d], kind="stable")
            values = vectors[order, d]
            for a, b in zip(cuts[:-1], cuts[1:], strict=True):
                self.dim.append(d)
                self.members.append(order[a:b])
                low.append(values[a])
                high.append(values[b - 1])
        self.dims = np.array(self.dim)
        self.low, self.high = np.array(low, dtype=np.int64), np.array(high, dtype=np.int64)

    def search(self, query: np.ndarray, k: int, own: int | None, few: int = 512) -> tuple[np.ndarray, np.ndarray]:
        """(scores, ids) of the k best, ties by smaller id; the query's own id takes no part."""
        n, dims = self.vectors.shape
        weight = query[self.dims]
        least = np.where(weight >= 0, weight * self.low, weight * self.high)
        most = np.where(weight >= 0, weight * self.high, weight * self.low)
        floor = np.full(dims, np.iinfo(np.int64).max)
        np.minimum.at(floor, self.dims, least)
        gain, reach, slack = least - floor[self.dims], most - floor[self.dims], most - least
        order = np.argsort(-reach, kind="stable")
        acc = np.zeros(n, dtype=np.int64)
        pending = [list() for _ in range(dims)]
        for s in order:
            pending[self.dims[s]].append(s)
        best_slack = np.zeros(dims, dtype=np.int64)
        at = [0] * dims
        possible = np.arange(n)
        k_all = k + (0 if own is None else int((self.ids == own).sum()))  # its own rows may be among the best
        step = max(1, len(order) // 12)
        for i, s in enumerate(order):
            d = self.dims[s]
            if gain[s]:
                acc[self.members[s]] += gain[s]
            best_slack[d] = max(best_slack[d], slack[s])
            at[d] += 1
            if n > few and (i + 1) % step == 0 and i * 2 > len(order):
                rest = sum(int(max(best_slack[e], reach[pending[e][at[e]]] if at[e] < len(pending[e]) else 0)) for e in range(dims))
                kth = np.partition(acc, n - k_all)[n - k_all] if n > k_all else acc.min()
                possible = np.flatnonzero(acc + rest >= kth)
                if len(possible) <= few:
                    break
        else:
            if n > few:
                rest = int(best_slack.sum())
                kth = np.partition(acc, n - k_all)[n - k_all] if n > k_all else acc.min()
                possible = np.flatnonzero(acc + rest >= kth)
        if own is not None:
            possible = possible[self.ids[possible] != own]
        scores, ids = self.vectors[possible] @ query, self.ids[possible]
        top = np.lexsort((ids, -scores))[:k]
        return scores[top], ids[top]


def _search(query_ids: np.ndarray, queries: np.ndarray, k: int, shard: int):
    schema = pa.schema([("query_id", pa.int64()), ("vec_id", pa.int64()), ("score", pa.int64())])

    def shards(batches: Iterator[pa.RecordBatch]) -> Iterator[tuple[np.ndarray, list]]:
        ids: list[int] = []
        vectors: list = []
        for batch in batches:
            ids += batch.column("vec_id").to_pylist()
            vectors += batch.column("v").to_pylist()
            if len(ids) >= shard:
                yield np.array(ids, dtype=np.int64), vectors
                ids, vectors = [], []
        if ids:
            yield np.array(ids, dtype=np.int64), vectors

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for ids, vectors in shards(batches):
            dims = max(queries.shape[1], max(map(len, vectors)))
            matrix = np.zeros((len(ids), dims), dtype=np.int64)
            for i, v in enumerate(vectors):
                matrix[i, : len(v)] = v
            index = ImpactIndex(ids, matrix)
            out: dict[str, list] = {f.name: [] for f in schema}
            for own, query in zip(query_ids.tolist(), queries, strict=True):
                scores, found = index.search(np.pad(query, (0, dims - len(query))), k, own)
                out["query_id"] += [own] * len(found)
                out["vec_id"] += found.tolist()
                out["score"] += scores.tolist()
            yield table(schema, out)

    return run


def quantised(vectors: DataFrame, id_col: str = "vec_id", vector_col: str = "embedding", scale: int = SCALE) -> DataFrame:
    """vec_id, v: integer vectors; rows with a null id, a null vector or a component that is null or not finite are left out."""
    x = F.col(vector_col).cast("array<double>")
    fine = F.forall(x, lambda c: c.isNotNull() & ~F.isnan(c) & (F.abs(c) < F.lit(float("inf"))))
    return (
        vectors.where(F.col(id_col).isNotNull() & F.col(vector_col).isNotNull() & fine)
        .select(F.col(id_col).cast("long").alias("vec_id"), F.transform(x, lambda c: F.floor(c * scale).cast("long")).alias("v"))
    )


def top_k(vectors: DataFrame, queries: DataFrame, *, k: int = 10, query_block: int = 4096, shard: int = 16384) -> DataFrame:
    """query_id, rank, vec_id, score: the k largest inner products of each query, ties to the smaller id.

    Both inputs are as ``quantised`` gives them. A query's own id is not among
    its candidates; a query id that occurs in several rows is searched by the
    row whose vector comes first in order. Vectors of different lengths are
    filled up with zeros. ``query_block`` queries at a time are sent to the
    executors. No queries or no vectors: an empty result.
    """
    spark = vectors.sparkSession
    queries = queries.groupBy("vec_id").agg(F.min("v").alias("v"))
    n_blocks = max(1, -(-queries.count() // query_block))
    found = None
    for b in range(n_blocks):
        part = queries if n_blocks == 1 else queries.where(F.pmod(F.xxhash64("vec_id"), F.lit(n_blocks)) == b)
        rows = part.orderBy("vec_id").collect()
        if not rows:
            continue
        dims = max(len(r.v) for r in rows)
        matrix = np.zeros((len(rows), max(1, dims)), dtype=np.int64)
        for i, r in enumerate(rows):
            matrix[i, : len(r.v)] = r.v
        one = vectors.mapInArrow(_search(np.array([r.vec_id for r in rows], dtype=np.int64), matrix, k, shard), "query_id long, vec_id long, score long")
        found = one if found is None else found.unionByName(one)
    if found is None:
        return spark.createDataFrame([], "query_id long, rank int, vec_id long, score long")
    best = Window.partitionBy("query_id").orderBy(F.desc("score"), "vec_id")
    return found.withColumn("rank", F.row_number().over(best)).where(F.col("rank") <= k).select("query_id", F.col("rank").cast("int").alias("rank"), "vec_id", "score")
