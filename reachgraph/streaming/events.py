"""Events as a stream: counts by window, sessions, and the next-event edges kept in state."""

from __future__ import annotations

import uuid
from collections.abc import Callable, Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from reachgraph.session import shared_folder

#: The columns of the events table.
SCHEMA = "event_id long, ts timestamp, user_id long, event_type string, value double, props string"
LATE, LATE_MICROS = "10 minutes", 600_000_000


def event_stream(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The events of a directory as a stream with a watermark; rows later than it are dropped by stateful steps."""
    reader = spark.readStream.schema(SCHEMA).option("pathGlobFilter", "events.parquet")
    return reader.parquet(sf_dir).where("ts is not null").withWatermark("ts", LATE)


def drain(stream: DataFrame, mode: str = "append") -> DataFrame:
    """Run a stream over all that is there and return what it has put out."""
    spark = stream.sparkSession
    folder = f"{shared_folder(spark)}/stream-{uuid.uuid4().hex}"
    if mode == "append":
        run = stream.writeStream.format("parquet").option("path", f"{folder}/out").option("checkpointLocation", f"{folder}/state").trigger(availableNow=True).start()
        run.awaitTermination()
        return spark.read.schema(stream.schema).parquet(f"{folder}/out")

    def last(batch: DataFrame, _: int) -> None:
        batch.write.mode("overwrite").parquet(f"{folder}/out")

    run = stream.writeStream.foreachBatch(last).outputMode(mode).option("checkpointLocation", f"{folder}/state").trigger(availableNow=True).start()
    run.awaitTermination()
    return spark.read.schema(stream.schema).parquet(f"{folder}/out")


def batch_replay(spark: SparkSession, sf_dir: str, step: Callable[[DataFrame], DataFrame], mode: str = "append") -> DataFrame:
    """A stateful step over the event stream, run to the end."""
    return drain(step(event_stream(spark, sf_dir)), mode)


def windowed_counts(spark: SparkSession, sf_dir: str, length: str, slide: str | None = None) -> DataFrame:
    """(start, event_type, n) by tumbling or sliding windows."""
    window = F.window("ts", length, slide) if slide else F.window("ts", length)
    return batch_replay(
        spark, sf_dir, lambda s: s.groupBy(window.alias("w"), "event_type").agg(F.count(F.lit(1)).alias("n")).select(F.unix_seconds("w.start").alias("start"), "event_type", "n"), "complete"
    )


def _link(key: tuple, batches: Iterator[pd.DataFrame], state: object) -> Iterator[pd.DataFrame]:
    """Changes of the edges between the events of one user: 1 for a new edge, -1 for one that a later arrival has split.

    The state has the events, in order, that a late one may still stand among.
    """
    got = pd.concat(list(batches))
    held = list(zip(*state.get, strict=True)) if state.exists else []
    fresh = {(int(ts.value) // 1000, int(i)) for ts, i in zip(got["ts"], got["event_id"], strict=True)} - set(held)
    if state.exists:
        fresh = {e for e in fresh if e > held[0]}  # what stood before the first one is known no more
    after = sorted({*held, *fresh})
    old = set(zip(held[:-1], held[1:], strict=True))
    new = set(zip(after[:-1], after[1:], strict=True))
    if after:
        since = after[-1][0] - LATE_MICROS
        first = max(0, sum(ts < since for ts, _ in after) - 1)
        state.update(tuple(map(list, zip(*after[first:], strict=True))))
    rows = [(a[1], b[1], 1) for a, b in sorted(new - old)] + [(a[1], b[1], -1) for a, b in sorted(old - new)]
    yield pd.DataFrame(rows, columns=["s", "t", "change"], dtype="int64")


def edge_changes(stream: DataFrame) -> DataFrame:
    """(s, t, change) of the edges from each event of a user to the next, by time and id, whatever the batches.

    An event that comes later than ``LATE`` behind its user's newest and before
    all that are kept is left out, as the watermark has it.
    """
    return stream.groupBy("user_id").applyInPandasWithState(_link, "s long, t long, change long", "ts array<long>, id array<long>", "append", "NoTimeout")


def next_events(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(s, t): each event and the next of its user, by time and id."""
    changes = batch_replay(spark, sf_dir, edge_changes)
    return changes.groupBy("s", "t").agg(F.sum("change").alias("n")).where("n > 0").select("s", "t")


def followed(spark: SparkSession, sf_dir: str, first: str, then: str, within: str = "10 minutes") -> DataFrame:
    """(a, b): events of two kinds of one user, the second at most ``within`` after the first; both sides are streams."""
    a = event_stream(spark, sf_dir).where(F.col("event_type") == first).select(F.col("event_id").alias("a"), F.col("user_id").alias("u"), F.col("ts").alias("at"))
    b = event_stream(spark, sf_dir).where(F.col("event_type") == then).select(F.col("event_id").alias("b"), F.col("user_id").alias("v"), F.col("ts").alias("bt"))
    near = F.expr(f"u = v AND bt > at AND bt <= at + INTERVAL {within}")
    return drain(a.join(b, near).select("a", "b"))


def static_counts(spark: SparkSession, sf_dir: str) -> DataFrame:
    """(event_type, n_errors, n): the stream joined with a static table of errors per user."""
    errors = spark.read.parquet(f"{sf_dir}/events.parquet").where("event_type = 'error'").groupBy("user_id").agg(F.count(F.lit(1)).alias("n_errors"))
    return batch_replay(spark, sf_dir, lambda s: s.join(errors, "user_id").groupBy("event_type", "n_errors").agg(F.count(F.lit(1)).alias("n")), "complete")
