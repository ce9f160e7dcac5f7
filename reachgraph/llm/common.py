"""Shared helpers of the training-data operators.

Everything an operator must keep between jobs is written to the folder that
``spark.checkpoint.dir`` names, which driver and executors share; only where
that setting is absent (tests, a laptop) a folder of this process is used.
"""

from __future__ import annotations

import atexit
import gc
import shutil
import tempfile
import uuid

import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

#: Fixed value: what separates words, in the regular-expression dialects of Java, Python and RE2.
WORD = r"[^\x20\x09-\x0D]+"

#: Bytes of one Arrow batch handed to a Python worker, and its most rows.
ARROW_BYTES = 8 << 20
ARROW_ROWS = 2_000

_own_folder: list[str] = []


def read(spark: SparkSession, sf_dir: str, table: str) -> DataFrame:
    """A table of the given directory."""
    return spark.read.parquet(f"{sf_dir}/{table}.parquet")


def bound_batches(spark: SparkSession) -> None:
    """Keep Arrow batches small, so that long texts do not pile up in a Python worker."""
    for key, most in (
        ("spark.sql.execution.arrow.maxBytesPerBatch", ARROW_BYTES),
        ("spark.sql.execution.arrow.maxRecordsPerBatch", ARROW_ROWS),
    ):
        try:
            now = int(spark.conf.get(key, str(most + 1)).rstrip("bB"))
        except ValueError:
            now = most + 1
        if not 0 < now <= most:
            spark.conf.set(key, str(most))


def shared_folder(spark: SparkSession) -> str:
    """The cluster's shared folder for cut lineage; one of this process where none is set."""
    named = spark.conf.get("spark.checkpoint.dir", None)
    if named:
        return named.rstrip("/")
    if not _own_folder:
        _own_folder.append(tempfile.mkdtemp(prefix="reachgraph-"))
        atexit.register(shutil.rmtree, _own_folder[0], ignore_errors=True)
    return "file://" + _own_folder[0]


_CLEANUP = "spark.sql.classic.shuffleDependency.fileCleanup.enabled"


def stored(df: DataFrame, name: str = "part") -> DataFrame:
    """Write ``df`` to the shared folder and read it back: lineage is cut and lost executors cost nothing.

    Nothing reads the shuffle files of the write again, so they go when it ends.
    """
    spark = df.sparkSession
    path = f"{shared_folder(spark)}/{name}-{uuid.uuid4().hex}"
    before = spark.conf.get(_CLEANUP, "false")
    spark.conf.set(_CLEANUP, "true")
    try:
        df.write.option("compression", "zstd").parquet(path)
    finally:
        spark.conf.set(_CLEANUP, before)
    return spark.read.schema(df.schema).parquet(path)


def drop_stored(df: DataFrame) -> None:
    """Delete what ``stored`` wrote, once nothing reads it any more."""
    spark = df.sparkSession
    home = shared_folder(spark).split(":", 1)[-1].lstrip("/")
    for folder in {f.rsplit("/", 1)[0] for f in df.inputFiles()}:
        if home in folder:
            path = spark._jvm.org.apache.hadoop.fs.Path(folder)
            path.getFileSystem(spark._jsc.hadoopConfiguration()).delete(path, True)


def sweep(spark: SparkSession) -> None:
    """Let Spark drop the shuffle files of finished jobs now, not when the driver happens to need memory."""
    gc.collect()
    spark._jvm.System.gc()


def word_count(text: Column | str) -> Column:
    """Number of words of a text; 0 for null."""
    col = F.col(text) if isinstance(text, str) else text
    return F.coalesce(F.regexp_count(col, F.lit(WORD)), F.lit(0)).cast("long")


def small(df: DataFrame, most_rows: int) -> DataFrame:
    """Mark ``df`` for broadcast if it has at most ``most_rows`` rows; else leave the join to a shuffle.

    ``df`` should be cheap to count (a stored table or an aggregate of one).
    """
    return F.broadcast(df) if df.limit(most_rows + 1).count() <= most_rows else df


def table(batch_schema: pa.Schema, columns: dict[str, list]) -> pa.RecordBatch:
    """A record batch of Python lists."""
    return pa.RecordBatch.from_arrays([pa.array(columns[f.name], type=f.type) for f in batch_schema], schema=batch_schema)
