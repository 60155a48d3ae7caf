"""Per-group Python over a stream: rows of a group come side by side, so no group needs a task or a call of its own."""

from __future__ import annotations

from collections.abc import Callable, Iterable
from itertools import pairwise

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql.pandas.types import to_arrow_schema
from pyspark.sql.types import StructType

OUT_ROWS = 20_000


def by_group(df: DataFrame, keys: list[str], run: Callable[[list[tuple]], Iterable[tuple]], schema: StructType) -> DataFrame:
    """``run`` on the rows of each group, as tuples in the order of the columns; a group must fit a task, which the caller sees to."""
    places = [df.columns.index(k) for k in keys]
    kind = to_arrow_schema(schema)

    def stream(batches):
        key, rows, out = None, [], []

        def sent():
            columns = list(zip(*out, strict=True)) if out else [[]] * len(kind)
            return pa.RecordBatch.from_arrays([pa.array(c, f.type) for c, f in zip(columns, kind, strict=True)], schema=kind)

        for batch in batches:
            for row in zip(*(c.to_pylist() for c in batch.columns), strict=True):
                now = tuple(row[p] for p in places)
                if now != key:
                    if rows:
                        out.extend(run(rows))
                    key, rows = now, []
                    if len(out) >= OUT_ROWS:
                        yield sent()
                        out.clear()
                rows.append(row)
        if rows:
            out.extend(run(rows))
        yield sent()

    return df.repartition(*keys).sortWithinPartitions(*keys).mapInArrow(stream, schema)


def runs(batches: Iterable[pa.RecordBatch], keys: tuple[str, ...]) -> Iterable[pa.Table]:
    """A table for each run of rows with equal integer keys, of batches that come sorted by them."""
    held: list = []
    last = None
    for batch in batches:
        values = np.stack([batch.column(k).to_numpy() for k in keys], 1)
        starts = [0, *(np.flatnonzero((values[1:] != values[:-1]).any(1)) + 1), len(values)] if len(values) else []
        for a, b in pairwise(starts):
            now = tuple(values[a])
            if held and now != last:
                yield pa.Table.from_batches(held)
                held = []
            held.append(batch.slice(a, b - a))
            last = now
    if held:
        yield pa.Table.from_batches(held)


def strongly_connected(edges: Iterable[tuple]) -> dict:
    """node -> number of its strongly connected set, for nodes of edges (a, b)."""
    graph: dict = {}
    for a, b in edges:
        graph.setdefault(a, []).append(b)
        graph.setdefault(b, [])
    index: dict = {}
    low: dict = {}
    of: dict = {}
    stack: list = []
    for start in graph:
        if start in index:
            continue
        walk = [(start, iter(graph[start]))]
        index[start] = low[start] = len(index)
        stack.append(start)
        while walk:
            node, after = walk[-1]
            for to in after:
                if to not in index:
                    index[to] = low[to] = len(index)
                    stack.append(to)
                    walk.append((to, iter(graph[to])))
                    break
                if to not in of:
                    low[node] = min(low[node], index[to])
            else:
                walk.pop()
                if walk:
                    low[walk[-1][0]] = min(low[walk[-1][0]], low[node])
                if low[node] == index[node]:
                    while True:
                        member = stack.pop()
                        of[member] = index[node]
                        if member == node:
                            break
    return of
