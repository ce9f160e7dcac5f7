"""Set reachability from label tables alone: joins at query time, no traversal."""

from __future__ import annotations

from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from reachgraph.operators.reach_index import ReachIndex, _dag, _exit, _entry, _rows
from reachgraph.session import materialise


@dataclass
class LabelTables:
    """inner(x, y): pairs within a shard; leave(x, exit); bridge(exit, entry); arrive(entry, y).

    The bridge is the closure between exits and entries, so this form costs space
    where the boundary is dense and saves every traversal of a query.
    """

    inner: DataFrame
    leave: DataFrame
    bridge: DataFrame
    arrive: DataFrame

    @classmethod
    def of(cls, index: ReachIndex) -> LabelTables:
        """Label tables of an index with a shared boundary."""
        if index.shared is None or index.layout != "shared":
            raise ValueError("label tables need an index with one shared boundary")
        labels = materialise(index.shards.mapInArrow(_labels, "kind int, a long, b long"), "labels")
        of = lambda kind, a, b: labels.where(F.col("kind") == kind).select(F.col("a").alias(a), F.col("b").alias(b))
        shared = index.shared

        def across(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            boundary, entries, _ = shared.value
            for batch in batches:
                exits = batch.column("v").to_numpy()
                x, y = boundary.reach(exits, _exit(exits), _entry(entries))
                yield pa.RecordBatch.from_arrays([pa.array(x), pa.array((y - 1) // 4)], names=["exit", "entry"])

        bridge = materialise(index.cut.select(F.col("s").alias("v")).distinct().mapInArrow(across, "exit long, entry long"), "bridge")
        return cls(of(0, "x", "y"), of(1, "x", "exit"), bridge, of(2, "entry", "y"))

    def set_reach(self, sources: DataFrame, targets: DataFrame, plus: str = "distinct") -> DataFrame:
        """Distinct pairs (x, y) over one edge or more."""
        x, y = sources.select(F.col("v").alias("x")).distinct(), targets.select(F.col("v").alias("y")).distinct()
        near = self.inner.join(x, "x", "left_semi").join(y, "y", "left_semi").select("x", "y")
        ends = self.arrive.join(y, "y", "left_semi")
        far = self.leave.join(x, "x", "left_semi").join(self.bridge, "exit").select("x", "entry").distinct().join(ends, "entry").select("x", "y")
        pairs = near.union(far).distinct()
        return pairs.where("x <> y") if plus == "distinct" else pairs


def _labels(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    schema = pa.schema([("kind", pa.int32()), ("a", pa.int64()), ("b", pa.int64())])
    for batch in batches:
        for row in _rows(batch):
            dag = _dag(row)
            ways = (dag.reach(dag.verts, dag.verts, dag.verts, empty_path=False), dag.reach(dag.verts, dag.verts, row["exits"]), dag.reach(row["entries"], row["entries"], dag.verts))
            for kind, (a, b) in enumerate(ways):
                yield pa.RecordBatch.from_arrays([pa.array(np.full(len(a), kind, dtype=np.int32)), pa.array(a), pa.array(b)], schema=schema)
