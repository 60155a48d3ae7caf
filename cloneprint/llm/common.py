"""Shared plumbing: scratch tables in the shared folder, and connected components."""

from __future__ import annotations

import contextlib
import ctypes
import gc
import os

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..plans.store import Store


#: bytes of its own that a worker may keep between tasks
LITTLE = 96 << 20


class Scratch(Store):
    """A store whose tables are compressed more, and which can bound the rows of an Arrow batch while it writes wide rows."""

    def keep(self, df: DataFrame, name: str, batch: int | None = None) -> DataFrame:
        key = "spark.sql.execution.arrow.maxRecordsPerBatch"
        before = self.spark.conf.get(key)
        if batch:
            self.spark.conf.set(key, str(batch))
        try:
            df.write.option("compression", "zstd").parquet(self.path(name))
        finally:
            self.spark.conf.set(key, before)
        return self.spark.read.schema(df.schema).parquet(self.path(name))


def give_back() -> None:
    """Free memory goes back to the system, as far as the allocators let it; a process that holds little is left alone."""
    with contextlib.suppress(OSError), open("/proc/self/statm") as f:
        _, resident, shared, *_ = map(int, f.read().split())
        if (resident - shared) * os.sysconf("SC_PAGE_SIZE") < LITTLE:
            return
    gc.collect()
    pa.default_memory_pool().release_unused()
    with contextlib.suppress(OSError, AttributeError):  # not every C library has it
        ctypes.CDLL(None).malloc_trim(0)


def lean(run):
    """``run`` for Spark's Python workers. They stay for tasks of later stages, some of them idle; without this each keeps what its largest task took."""

    def wrapped(batches):
        try:
            yield from run(batches)
        finally:
            give_back()

    return wrapped


def read_table(spark: SparkSession, sf_dir: str, name: str, *columns: str) -> DataFrame:
    df = spark.read.parquet(f"{sf_dir}/{name}.parquet")
    return df.select(*columns) if columns else df


def quoted(name: str) -> str:
    """A column's name for expressions, whatever characters it has."""
    return "`" + name.replace("`", "``") + "`"


def unused(df: DataFrame, name: str) -> str:
    """``name``, or a longer one that no column of ``df`` has."""
    taken = {c.lower() for c in df.columns}
    while name.lower() in taken:
        name += "_"
    return name


def local_forest(batches):
    """Edges (a, b) of one partition to (node, root): the same connectivity, a row a node."""
    parent: dict[int, int] = {}

    def find(x: int) -> int:
        root = x
        while parent.setdefault(root, root) != root:
            root = parent[root]
        while parent[x] != root:
            parent[x], x = root, parent[x]
        return root

    def flush():
        nodes = [(n, r) for n in list(parent) if (r := find(n)) != n]
        parent.clear()
        cols = np.array(nodes, dtype=np.int64).reshape(-1, 2)
        return pa.RecordBatch.from_arrays([pa.array(cols[:, 0]), pa.array(cols[:, 1])], ["a", "b"])

    for batch in batches:
        for a, b in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), strict=True):
            x, y = find(a), find(b)
            if x != y:
                parent[max(x, y)] = min(x, y)
        if len(parent) > 1_000_000:  # a forest of part of the edges is a valid set of edges too
            yield flush()
    yield flush()


def connected_components(edges: DataFrame, scratch: Scratch, name: str = "cc", rounds: int | None = None) -> DataFrame:
    """(a, b) long edges to (node, label): the smallest id reachable, for every id with an edge.

    Each partition first shrinks to a forest; then rounds of smallest-neighbour labels
    with pointer jumping run until a round changes nothing. Hot nodes are harmless: minima
    are combined before the shuffle, and joins read written tables, so hot keys split. With ``rounds``, equal labels
    still mean one component, but one component may keep several labels.
    """
    spark = edges.sparkSession
    star = scratch.keep(edges.select(F.col("a").cast("long").alias("a"), F.col("b").cast("long").alias("b")).mapInArrow(lean(local_forest), "a long, b long"), f"{name}-e")
    both = star.unionByName(star.select(F.col("b").alias("a"), F.col("a").alias("b")))
    # `down` keeps one row a node: a first guess from its own edges
    labels = scratch.keep(both.groupBy(F.col("a").alias("node")).agg(F.least(F.col("node"), F.min("b")).alias("label")), f"{name}-0")
    step = 0
    while True:
        step += 1
        seen = labels.select(F.col("node").alias("a"), "label")
        up = star.join(seen, "a").select(F.col("b").alias("node"), "label")
        down = star.select("b", F.col("a").alias("to")).join(seen.withColumnRenamed("a", "b"), "b").select(F.col("to").alias("node"), "label")
        lower = scratch.keep(labels.unionByName(up).unionByName(down).groupBy("node").agg(F.min("label").alias("label")), f"{name}-{step}m")
        jump = lower.select(F.col("node").alias("label"), F.col("label").alias("to"))
        new = scratch.keep(lower.join(jump, "label", "left").select("node", F.coalesce("to", "label").alias("label")), f"{name}-{step}")
        changed = step != rounds and new.join(labels.withColumnRenamed("label", "old"), "node").where("label <> old").limit(1).count()
        scratch.drop(f"{name}-{step - 1}", f"{name}-{step}m")
        labels = new
        if not changed:
            scratch.drop(f"{name}-e")
            return labels
