"""The table function ``reach_from``."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
from pyspark.sql import Row, SparkSession
from pyspark.sql.functions import udtf

from reachgraph.functions.kernels import Dag


class ReachFrom:
    """Vertices that a start reaches over one edge or more of a table of edges (s, t).

    One task reads the table, so it is for graphs that a task holds; larger ones
    are asked through ``ReachIndex``.
    """

    def __init__(self) -> None:
        self.s: list[int] = []
        self.t: list[int] = []
        self.start: int | None = None

    def eval(self, edge: Row, start: int) -> None:
        self.start = start
        if edge[0] is not None and edge[1] is not None:
            self.s.append(edge[0])
            self.t.append(edge[1])

    def terminate(self) -> Iterator[tuple[int]]:
        if self.s and self.start is not None:
            dag = Dag.of(np.array(self.s), np.array(self.t))
            one = np.array([self.start])
            _, found = dag.reach(one, one, dag.verts, empty_path=False)
            for v in found.tolist():
                yield (v,)


def register(spark: SparkSession, name: str = "reach_from") -> None:
    """``SELECT v FROM reach_from(TABLE(edges) WITH SINGLE PARTITION, start)``."""
    spark.udtf.register(name, udtf(ReachFrom, returnType="v bigint"))
