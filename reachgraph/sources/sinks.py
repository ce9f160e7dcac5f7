"""Where results go."""

from __future__ import annotations

import uuid

from pyspark.sql import DataFrame, SparkSession


def write_result(df: DataFrame, path: str, fmt: str = "parquet", *, by: str | None = None, files: int | None = None) -> str:
    """Write a result as a new version under ``path`` and return the version's folder.

    Readers of older versions are not disturbed, and a version that has no
    ``_SUCCESS`` file was not written to its end. ``by`` partitions the folder,
    ``files`` bounds the number of files.
    """
    version = f"{path.rstrip('/')}/v-{uuid.uuid4().hex}"
    writer = (df.coalesce(files) if files else df).write.option("header", True) if fmt == "csv" else (df.coalesce(files) if files else df).write
    (writer.partitionBy(by) if by else writer).format(fmt).save(version)
    return version


def read_result(spark: SparkSession, version: str, schema: str, fmt: str = "parquet") -> DataFrame:
    """A version that ``write_result`` wrote."""
    return spark.read.schema(schema).option("header", True).format(fmt).load(version)
