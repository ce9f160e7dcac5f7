"""Cost measures: time, geometric means, cold and warm runs, scaling, exchanges, index sizes, stability."""

from __future__ import annotations

import math
import time
from collections.abc import Callable

from pyspark.sql import DataFrame
from pyspark.sql import functions as F


def time_query(run: Callable[[], DataFrame]) -> tuple[float, int]:
    """(seconds, rows) of running a query to its last row."""
    start = time.perf_counter()
    rows = run().count()
    return time.perf_counter() - start, rows


def geo_mean(values: list[float]) -> float:
    """Geometric mean; 0 for no values."""
    return math.exp(sum(math.log(max(v, 1e-9)) for v in values) / len(values)) if values else 0.0


def cold_warm(run: Callable[[], DataFrame], repeats: int = 3) -> tuple[float, float]:
    """(seconds of a first run with empty caches, least of the repeats)."""
    run().sparkSession.catalog.clearCache()
    cold = time_query(run)[0]
    return cold, min(time_query(run)[0] for _ in range(repeats))


def ratio(base: float, ours: float) -> float:
    """How many times faster ours is."""
    return base / max(ours, 1e-9)


def strong_scaling(run: Callable[[int], DataFrame], workers: list[int]) -> list[tuple[int, float]]:
    """(workers, seconds) for one input; ``run`` gets the number of workers (shards)."""
    return [(k, time_query(lambda k=k: run(k))[0]) for k in workers]


def weak_scaling(run: Callable[[int, float], DataFrame], steps: list[tuple[int, float]]) -> list[tuple[int, float, float]]:
    """(workers, share, seconds) for inputs that grow with the workers."""
    return [(k, share, time_query(lambda k=k, share=share: run(k, share))[0]) for k, share in steps]


def vertex_sample(edges: DataFrame, share: float) -> DataFrame:
    """Edges between vertices of a sample, the same sample on every run."""
    cut = F.lit(int(share * 1_000_000))
    held = lambda c: F.pmod(F.xxhash64(F.col(c)), F.lit(1_000_000)) < cut
    return edges.where(held("s") & held("t"))


def _plan(df: DataFrame) -> object:
    """The physical plan of a query; the one that ran, if it has run under adaptive execution."""
    return df._jdf.queryExecution().executedPlan()


def _children(node: object) -> list[object]:
    """The nodes below a node, through the wrappers of adaptive execution and the reuse of exchanges."""
    kind = node.getClass().getSimpleName()
    if kind == "AdaptiveSparkPlanExec":
        return [node.executedPlan()]
    if kind.endswith("QueryStageExec"):
        return [node.plan()]
    if kind == "ReusedExchangeExec":
        return [node.child()]
    below = node.children()
    return [below.apply(i) for i in range(below.size())]


def _nodes(df: DataFrame) -> list[tuple[str, tuple[str, ...], object]]:
    """(kind, kinds of the nodes above, node) of every node."""
    out, todo = [], [(_plan(df), ())]
    while todo:
        node, above = todo.pop()
        kind = node.getClass().getSimpleName()
        out.append((kind, above, node))
        todo += [(child, (*above, kind)) for child in _children(node)]
    return out


def exchanges(df: DataFrame) -> int:
    """Shuffle exchanges in the plan of a query."""
    return sum(kind == "ShuffleExchangeExec" for kind, *_ in _nodes(df))


def shuffled_bytes(df: DataFrame) -> int:
    """Bytes that the exchanges of a query write, read off the metrics of a run of it."""
    df.collect()
    total = 0
    for kind, _, node in _nodes(df):
        if kind == "ShuffleExchangeExec":
            metric = node.metrics().get("shuffleBytesWritten")
            total += metric.get().value() if metric.isDefined() else 0
    return total


def rounds(index: object, sources: DataFrame, targets: DataFrame) -> int:
    """Exchanges of (source, entry) pairs that a reachability predicate needs, counted in its plan.

    These are the exchanges that bindings pass between leaving the shards of the
    sources and reaching those of the targets, and the steps over a boundary
    that is too large to be shared.
    """
    index.steps = 0
    df = index.set_reach(sources, targets, "+")
    df.count()
    between = 0
    for kind, above, node in _nodes(df):
        if kind == "ShuffleExchangeExec" and "FlatMapCoGroupsInArrowExec" in above and _departed(node):
            between += 1
    return between + index.steps


def _departed(node: object) -> bool:
    """Whether a part of a plan reads what departures were written to."""
    todo = _children(node)
    while todo:
        one = todo.pop()
        if one.getClass().getSimpleName() == "FileSourceScanExec" and "/departed-" in one.relation().location().rootPaths().mkString(" "):
            return True
        todo += _children(one)
    return False


def index_size(index: object) -> dict[str, int]:
    """Edges of the cut, of the boundary graph, of the shards' DAGs, and vertices of the shards."""
    shards = index.shards.agg(F.sum(F.size("src")), F.sum(F.size("verts"))).first()
    return {"cut": index.cut.count(), "boundary": index.boundary.count(), "dag_edges": shards[0] or 0, "vertices": shards[1] or 0, "edges": index.edges.count()}


def digest(df: DataFrame) -> tuple[int, int]:
    """(rows, order-free hash) of a result."""
    row = df.agg(F.count(F.lit(1)), F.sum(F.xxhash64(*df.columns).cast("decimal(38,0)"))).first()
    return row[0], int(row[1] or 0)


def stable(run: Callable[[], DataFrame], repeats: int = 3) -> bool:
    """Whether repeated runs give the same rows."""
    return len({digest(run()) for _ in range(repeats)}) == 1
