"""The refined feature index on disk, with the digest of the configuration that made it."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..operators.recognize import DetectConfig


def write_index(index: DataFrame, path: str, config: DetectConfig) -> None:
    """Parquet sorted by print within files, so that scans prune by its statistics; lists go to a table of their own.

    A popular print's (artifact, version) list can be long; matching reads only prints, groups and times.
    """
    slim = index.select("print", "group_id", *[c for c in ("first_at",) if c in index.columns])
    slim.repartition("print").sortWithinPartitions("print").write.mode("overwrite").parquet(f"{path}/prints")
    if "av" in index.columns:
        index.select("print", F.explode("av").alias("v")).select("print", "v.*").write.mode("overwrite").parquet(f"{path}/versions")
    index.sparkSession.createDataFrame([(config.digest(),)], "digest string").coalesce(1).write.mode("overwrite").parquet(f"{path}/config")


def load_index(spark: SparkSession, path: str, config: DetectConfig) -> DataFrame:
    """The prints; raises if they were made with another configuration, as they could then never match."""
    made = spark.read.parquet(f"{path}/config").first()["digest"]
    if made != config.digest():
        raise ValueError(f"the index was built with configuration {made}, not {config.digest()}")
    return spark.read.parquet(f"{path}/prints")


def bucketed(index: DataFrame, table: str, buckets: int) -> None:
    """The index as a table bucketed by print: joins with prints bucketed alike need no shuffle of it."""
    index.select("print", "group_id").write.mode("overwrite").bucketBy(buckets, "print").sortBy("print").saveAsTable(table)
