"""Streaming upkeep: the earliest-origin index, recognition against it, windows and deduplication.

Each runs over a file stream to its end (``availableNow``), writes what every micro-batch changes, and reads the last state back. State is kept
by Spark under a checkpoint in the shared folder, so a restarted query goes on where it stopped. Minima commute, so releases may arrive in any order.
"""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..plans.store import Store


def source(spark: SparkSession, path: str, files_per_batch: int | None = None) -> DataFrame:
    """A file stream over a table that is a folder or a single file (only a pattern may name a file)."""
    schema = spark.read.parquet(path).schema
    path = path.rstrip("/")
    path = f"{path[:-1]}[{path[-1]}]"
    reader = spark.readStream.schema(schema)
    if files_per_batch:
        reader = reader.option("maxFilesPerTrigger", files_per_batch)
    return reader.parquet(path)


def changes(stream: DataFrame, tag: str, mode: str = "update", change: Callable[[DataFrame], DataFrame] = lambda df: df, store: Store | None = None) -> DataFrame:
    """Runs a stream to its end; every micro-batch's output rows, with ``batch``. A batch that is tried again replaces its own files.

    With the ``store`` of an earlier run it goes on from there, and gives the rows of both.
    """
    store = store or Store(stream.sparkSession, tag)

    def put(df: DataFrame, batch: int) -> None:
        change(df).withColumn("batch", F.lit(batch)).write.mode("overwrite").parquet(store.path(f"out/n={batch}"))

    query = stream.writeStream.outputMode(mode).option("checkpointLocation", store.path("state")).trigger(availableNow=True).foreachBatch(put).start()
    query.awaitTermination()
    return stream.sparkSession.read.parquet(store.path("out/*"))


def to_the_end(rows: DataFrame, last: DataFrame, time: str, tag: str, query: Callable[[DataFrame], DataFrame]) -> DataFrame:
    """Append-mode output of ``query`` over a stream ``rows``, closed by one more run that reads the row of ``last``.

    A window that is still open when a stream ends is never put out in append mode. ``last`` (one row of the stream's columns, its time beyond
    all others) comes in a source of its own, which stays empty until the first run has read everything; it then moves the watermark over every window.
    """
    spark = rows.sparkSession
    store = Store(spark, tag)
    last.limit(0).write.parquet(store.path("last"))
    both = rows.unionByName(spark.readStream.schema(rows.schema).parquet(store.path("last")))
    changes(query(both), tag, "append", store=store)
    last.write.mode("append").parquet(store.path("last"))
    return changes(query(both), tag, "append", store=store)


def latest(rows: DataFrame, *keys: str) -> DataFrame:
    """The last state of each key."""
    values = [c for c in rows.columns if c not in (*keys, "batch")]
    return rows.groupBy(*keys).agg(F.max_by(F.struct(*values), "batch").alias("v")).select(*keys, *[F.col(f"v.{c}").alias(c) for c in values])


def origin_index(features: DataFrame) -> DataFrame:
    """print, group_id, first_at from a stream of (print, group_id, released_at)."""
    first = F.min(F.struct(F.col("released_at").isNull().alias("late"), "released_at", "group_id")).alias("o")
    state = features.groupBy("print").agg(first).select("print", F.col("o.group_id").alias("group_id"), F.col("o.released_at").alias("first_at"))
    return latest(changes(state, "origin"), "print")


def recognize(subject_prints: DataFrame, index: DataFrame) -> DataFrame:
    """Evidence of a stream of (subject, print) against a fixed index."""
    return changes(subject_prints.join(index, "print"), "recognize", "append").drop("batch").distinct()


def windowed(events: DataFrame, time: str, late: str, window, *keys: str) -> DataFrame:
    """Counts and sums per window (tumbling, sliding or session) and key; rows later than the watermark are dropped."""
    counted = events.withWatermark(time, late).groupBy(window.alias("w"), *keys).agg(F.count("*").alias("n"), F.sum("value").alias("total"))
    return counted.select(F.col("w.start").alias("start"), F.col("w.end").alias("end"), *keys, "n", "total")
