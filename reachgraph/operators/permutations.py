"""Sorted copies of the triples, sharded by subject or by object."""

from __future__ import annotations

import uuid
from collections.abc import Callable
from dataclasses import dataclass, field

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from reachgraph.plans.optimizer import PERMUTATIONS, choose_permutation
from reachgraph.session import shared_folder

SUBJECT_KEY, OBJECT_KEY = ("SPO", "SOP", "PSO"), ("OSP", "OPS", "POS")


def shard_triples(triples: DataFrame, k: int) -> DataFrame:
    """(s, p, o, part, by): each triple in the shard of its subject and in that of its object, once if they are the same."""
    copies = F.array_distinct(F.array(F.pmod("s", F.lit(k)), F.pmod("o", F.lit(k))))
    placed = triples.select("s", "p", "o", F.explode(copies).alias("part"))
    by = F.concat(F.when(F.pmod("s", F.lit(k)) == F.col("part"), "s").otherwise(""), F.when(F.pmod("o", F.lit(k)) == F.col("part"), "o").otherwise(""))
    return placed.withColumn("by", by).withColumn("part", F.col("part").cast("int"))


@dataclass
class IndexStore:
    """Permutations in one folder: ``perm/p=<property>`` for PSO and POS, ``perm`` for the others."""

    spark: SparkSession
    path: str
    k: int = 8

    def write(self, triples: DataFrame, perms: tuple[str, ...] = ("PSO", "POS")) -> IndexStore:
        """Write the permutations. Sorting within shards lets scans skip row groups by their bounds."""
        for perm in perms:
            key = perm[0].lower() if perm[0] != "P" else perm[1].lower()
            placed = triples.withColumn("part", F.pmod(key, F.lit(self.k)).cast("int")).repartition(self.k, "part")
            writer = placed.sortWithinPartitions(*perm.lower()).write.mode("overwrite")
            (writer.partitionBy("p") if perm[0] == "P" else writer).parquet(f"{self.path}/{perm.lower()}")
        return self

    def scan(self, perm: str | None = None, *, s: int | None = None, p: int | None = None, o: int | None = None) -> DataFrame:
        """Triples that have the given constants, from the permutation that they lead to."""
        given = {"s": s, "p": p, "o": o}
        perm = perm or choose_permutation("".join(c for c in "spo" if given[c] is not None))
        df = self.spark.read.schema("s long, p int, o long, part int").parquet(f"{self.path}/{perm.lower()}")
        for c in perm.lower():
            if given[c] is not None:
                df = df.where(F.col(c) == F.lit(given[c]))
        return df.select("s", "p", "o")

    def register(self, prefix: str = "idx") -> None:
        """Views over the permutations that were written."""
        for perm in PERMUTATIONS:
            try:
                self.scan(perm).createOrReplaceTempView(f"{prefix}_{perm.lower()}")
            except Exception as gone:  # noqa: BLE001
                if "PATH_NOT_FOUND" not in str(gone):
                    raise


@dataclass
class PropertyStore:
    """PSO and POS of properties: edges (s, o) without repeats, bucketed by one end and sorted by both.

    Tables lie in the shared folder and are written when first asked for. Scans
    with a constant read one bucket and few row groups of it; joins on the ends
    that two tables are bucketed by need no exchange.
    """

    spark: SparkSession
    k: int = 8
    tables: dict[tuple[str, str], DataFrame] = field(default_factory=dict)

    def table(self, prop: str, by: str, rows: Callable[[], DataFrame]) -> DataFrame:
        """(s, o) placed by ``by``, ``s`` or ``o``.

        Where one object has much more than a bucket's share, as the literals of
        a property may, POS is sorted by object but placed by subject.
        """
        if (prop, by) not in self.tables:
            if by == "s":
                clean = rows().toDF("s", "o").where("s is not null and o is not null")
                # the placing also brings equal edges together
                placed, key, order = clean.repartition(self.k, "s").distinct(), "s", ("s", "o")
            else:
                edges = self.table(prop, "s", rows)
                most = edges.groupBy("o").agg(F.count(F.lit(1)).alias("n")).agg(F.max("n").alias("most"), F.sum("n").alias("n")).first()
                key = "s" if most.n and most.most * self.k > 2 * most.n else "o"
                placed, order = edges.repartition(self.k, key), ("o", "s")
            name = f"{'pso' if by == 's' else 'pos'}_{uuid.uuid4().hex}"
            writer = placed.write.format("parquet").bucketBy(self.k, key).sortBy(*order)
            writer.option("path", f"{shared_folder(self.spark)}/{name}").saveAsTable(name)
            self.tables[prop, by] = self.spark.table(name)
        return self.tables[prop, by]
