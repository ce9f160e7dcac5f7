"""Secret scans over an incremental, content-addressed blob ledger.

Every version of every text is a blob, named by the SHA-256 of its bytes. The
ledger records which (blob, rule, rule version) have been scanned and what was
found; a scan looks only at pairs that the ledger lacks, once per blob however
many paths hold it, and joins the findings back to all paths.
"""

from __future__ import annotations

import hashlib
import re
from collections.abc import Callable, Iterator
from dataclasses import dataclass

import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from reachgraph.llm.common import bound_batches, shared_folder, table


@dataclass(frozen=True)
class Rule:
    """What to look for. A match counts if its ``group`` has at least ``least`` characters.

    Matches are leftmost and do not overlap within a rule; one that is too
    short is dropped but still uses up its characters.
    """

    kind: str
    pattern: str
    least: int = 1
    group: int = 0
    flags: int = re.ASCII
    version: int = 1


#: The base rules, in the order of their kinds.
BASE_RULES = (
    Rule("assign", r"""(password|passwd|secret|token|api_?key)["']?\x20*[:=]\x20*["']?([A-Za-z0-9+/_.=-]+)""", 8, 2, re.ASCII | re.IGNORECASE),
    Rule("access", r"AKIA[A-Z0-9]+", 16),
    Rule("hex", r"[0-9a-f]+", 32),
)

#: Formats that the base rules do not know.
MORE_RULES = (
    Rule("pem", r"-----BEGIN (?:[A-Z]+ )*PRIVATE KEY-----"),
    Rule("jwt", r"eyJ[A-Za-z0-9_-]{8,}\.[A-Za-z0-9_-]{8,}\.[A-Za-z0-9_-]{8,}"),
    Rule("ghtoken", r"gh[pousr]_[A-Za-z0-9]{36,}"),
    Rule("chattoken", r"xox[abprs]-[A-Za-z0-9-]{10,}"),
    Rule("urlpass", r"[a-z][a-z0-9+.-]{1,20}://[^\x20/:@\x09-\x0D]{1,64}:[^\x20/@\x09-\x0D]{1,64}@"),
)

RULES = BASE_RULES + MORE_RULES

_SPAN = "array<struct<kind:string,start:long,end:long>>"
_LEDGER = "blob string, rule string, version int, spans " + _SPAN


def finder(rule: Rule) -> Callable[[str], list[tuple[int, int]]]:
    """A function from a text to the spans of a rule, in code points, end exclusive."""
    pattern = rule.pattern
    if pattern == r"[0-9a-f]+":
        # runs that are too short are dropped anyway; let the engine skip them
        pattern = rf"[0-9a-f]{{{rule.least},}}"
    search = re.compile(pattern, rule.flags).finditer

    def spans(text: str) -> list[tuple[int, int]]:
        return [m.span() for m in search(text) if m.end(rule.group) - m.start(rule.group) >= rule.least]

    return spans


def _scan(rules: tuple[Rule, ...]):
    schema = pa.schema([("blob", pa.string()), ("rule", pa.string()), ("version", pa.int32()), ("spans", pa.list_(pa.struct([("kind", pa.string()), ("start", pa.int64()), ("end", pa.int64())])))])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        finders = [(r, finder(r)) for r in rules]
        for batch in batches:
            out: dict[str, list] = {f.name: [] for f in schema}
            for blob, text, known in zip(*(batch.column(c).to_pylist() for c in ("blob", "text", "known")), strict=True):
                known = set(known or ())
                for rule, find in finders:
                    if f"{rule.kind}/{rule.version}" in known:
                        continue
                    spans = find(text)
                    for name, value in zip(out, (blob, rule.kind, rule.version, [{"kind": rule.kind, "start": s, "end": e} for s, e in spans]), strict=True):
                        out[name].append(value)
            yield table(schema, out)

    return run


class BlobLedger:
    """Findings by (blob, rule, rule version), in one Parquet folder that scans append to."""

    def __init__(self, spark: SparkSession, path: str | None = None) -> None:
        self.spark = spark
        self.path = path or f"{shared_folder(spark)}/ledger-{hashlib.sha256(repr(id(self)).encode()).hexdigest()[:8]}-{spark.sparkContext.startTime}"
        self._written = self._exists()

    def _exists(self) -> bool:
        path = self.spark._jvm.org.apache.hadoop.fs.Path(self.path)
        return path.getFileSystem(self.spark._jsc.hadoopConfiguration()).exists(path)

    def rows(self) -> DataFrame:
        """blob, rule, version, spans; one row per scanned pair, once even if two scans wrote it."""
        if not self._written:
            return self.spark.createDataFrame([], _LEDGER)
        return self.spark.read.schema(_LEDGER).parquet(self.path)

    def scan(self, texts: DataFrame, text_col: str = "text", rules: tuple[Rule, ...] = RULES) -> DataFrame:
        """Scan the pairs of these texts that the ledger lacks; return the new ledger rows.

        A blob is handed to a worker once: texts meet under their content
        address after a partial aggregation, so that a large group of copies
        neither travels nor lands in one task.
        """
        bound_batches(self.spark)
        text = F.coalesce(F.col(text_col).cast("string"), F.lit(""))
        blobs = texts.select(address(text).alias("blob"), text.alias("text")).groupBy("blob").agg(F.first("text").alias("text"))
        wanted = {f"{r.kind}/{r.version}" for r in rules}
        if self._written:
            name = F.concat_ws("/", "rule", F.col("version").cast("string"))
            known = self.rows().select("blob", name.alias("name")).where(F.col("name").isin(*wanted)).groupBy("blob").agg(F.collect_set("name").alias("known"))
            blobs = blobs.join(known, "blob", "left").where(F.coalesce(F.size("known"), F.lit(0)) < len(wanted))
        else:
            blobs = blobs.withColumn("known", F.lit(None).cast("array<string>"))
        found = blobs.mapInArrow(_scan(rules), _LEDGER)
        found.write.mode("append").option("compression", "zstd").parquet(self.path)
        self._written = True
        return self.rows()


def address(text: Column) -> Column:
    """Content address of a text."""
    return F.sha2(text.cast("binary"), 256)


def scan_paths(
    docs: DataFrame,
    ledger: BlobLedger | None = None,
    *,
    path_cols: tuple[str, ...] = ("doc_id",),
    text_col: str = "text",
    rules: tuple[Rule, ...] = RULES,
) -> DataFrame:
    """The path columns, blob and spans (kind, start, end) of every row of ``docs``.

    Null texts are empty and have no spans. Rows with null paths, repeated rows
    and many rows with one text each get their own result row. Spans are sorted
    by start, then by the order of the rules. Columns not named are not read.
    """
    spark = docs.sparkSession
    ledger = ledger or BlobLedger(spark)
    found = ledger.scan(docs, text_col, rules)
    order = {r.kind: i for i, r in enumerate(rules)}
    rank = F.create_map(*[F.lit(x) for kv in order.items() for x in kv])
    wanted = [F.struct(F.lit(r.kind).alias("rule"), F.lit(r.version).alias("version")) for r in rules]
    spans = (
        found.where(F.struct("rule", "version").isin(*wanted))
        .where(F.size("spans") > 0)
        .select("blob", F.explode(F.array_distinct("spans")).alias("s"))
        .distinct()
        .groupBy("blob")
        .agg(F.sort_array(F.collect_list(F.struct(F.col("s.start").alias("start"), rank[F.col("s.kind")].alias("rank"), F.col("s.kind").alias("kind"), F.col("s.end").alias("end")))).alias("spans"))
    )
    text = F.coalesce(F.col(text_col).cast("string"), F.lit(""))
    paths = docs.select(*path_cols, address(text).alias("blob"))
    none = F.array().cast("array<struct<start:long,rank:int,kind:string,end:long>>")
    return paths.join(spans, "blob", "left").withColumn("spans", F.coalesce("spans", none))
