"""Tables written once to the shared folder, so that iteration keeps a short lineage."""

from __future__ import annotations

import atexit
import gc
import tempfile
import uuid

from pyspark.sql import DataFrame, SparkSession


def shared_root(spark: SparkSession) -> str:
    """``spark.checkpoint.dir``; a local session without it gets a folder of its own."""
    root = spark.conf.get("spark.checkpoint.dir", None)
    if root:
        return root.rstrip("/")
    if not spark.sparkContext.master.startswith("local"):
        raise ValueError("set spark.checkpoint.dir to a folder that driver and executors share")
    if not hasattr(shared_root, "local"):
        shared_root.local = "file://" + tempfile.mkdtemp(prefix="cloneprint-")
    return shared_root.local


def _delete(jvm, conf, path: str) -> None:
    at = jvm.org.apache.hadoop.fs.Path(path)
    at.getFileSystem(conf).delete(at, True)


def _sweep(jvm, conf, path: str) -> None:
    try:
        _delete(jvm, conf, path)
    except Exception:  # noqa: BLE001  the JVM may be gone before the driver's end; the cluster's own clean-up is left then
        pass


class Store:
    """Keeps DataFrames as Parquet under a folder of its own; what is not dropped before goes at the driver's end, as DataFrames that were returned still read it."""

    def __init__(self, spark: SparkSession, tag: str):
        self.spark, self.base = spark, f"{shared_root(spark)}/{tag}-{uuid.uuid4().hex}"
        atexit.register(_sweep, spark.sparkContext._jvm, spark.sparkContext._jsc.hadoopConfiguration(), self.base)

    def path(self, name: str) -> str:
        return f"{self.base}/{name}"

    def keep(self, df: DataFrame, name: str, compression: str | None = None) -> DataFrame:
        df.write.parquet(self.path(name), compression=compression)
        return self.spark.read.schema(df.schema).parquet(self.path(name))

    def free(self) -> None:
        """Spark deletes the shuffle files that no DataFrame needs any more; without this they stay until the driver's memory happens to run short."""
        # Spark holds on to its last query until another one ends
        self.spark.range(1).collect()
        gc.collect()
        self.spark.sparkContext._jvm.System.gc()

    def drop(self, *names: str) -> None:
        for name in names:
            _delete(self.spark.sparkContext._jvm, self.spark.sparkContext._jsc.hadoopConfiguration(), self.path(name))
