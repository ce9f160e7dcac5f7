"""Reachability indexes of many properties, built together in one set of jobs."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from reachgraph.operators.reach_index import ReachIndex

#: Bits that a vertex may take; the property's number stands above them.
BITS = 53


@dataclass(frozen=True)
class _ByProperty:
    """Shards of their own for every property, by vertex modulo ``k``."""

    k: int

    def column(self, v: Column) -> Column:
        own = F.pmod(v.bitwiseAND(F.lit((1 << BITS) - 1)), F.lit(self.k))
        return (F.shiftright(v, BITS) * self.k + own).cast("int")

    def parts(self, edges: DataFrame) -> DataFrame:
        both = edges.select(F.col("s").alias("v")).union(edges.select("t")).distinct()
        return both.withColumn("part", self.column(F.col("v")))


@dataclass
class MultiIndex:
    """One index over the disjoint union of properties; shards never mix properties, so each is asked alone."""

    index: ReachIndex
    numbers: dict[str, int]

    @classmethod
    def build(cls, properties: dict[str, DataFrame], k: int = 8, **options: object) -> MultiIndex:
        """Index edges (s, t) by property name; all shards of all properties are made in the same jobs. At most 128 properties."""
        if len(properties) > 128:
            raise ValueError("at most 128 properties share an index; build several")
        numbers = {name: i for i, name in enumerate(sorted(properties))}
        union = None
        for name, i in numbers.items():
            one = properties[name].select(_lift("s", i).alias("s"), _lift("t", i).alias("t"))
            union = one if union is None else union.union(one)
        return cls(ReachIndex.build(union, k, _ByProperty(k), **options), numbers)

    def set_reach(self, prop: str, sources: DataFrame, targets: DataFrame, kind: str = "+", **options: object) -> DataFrame:
        """``ReachIndex.set_reach`` over one property."""
        i = self.numbers[prop]
        lifted = [ends.select(_lift("v", i).alias("v")) for ends in (sources, targets)]
        low = F.lit((1 << BITS) - 1)
        pairs = self.index.set_reach(*lifted, kind, **options)
        return pairs.select(F.col("x").bitwiseAND(low).alias("x"), F.col("y").bitwiseAND(low).alias("y"))


def _lift(column: str, number: int) -> Column:
    return F.col(column) + F.lit(number << BITS)
