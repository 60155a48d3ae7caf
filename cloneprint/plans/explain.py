"""What a plan shows: scans, joins, Python, and the cost counters of a run."""

from __future__ import annotations

import re
import time

from pyspark.sql import DataFrame


def plan_text(df: DataFrame, mode: str = "formatted") -> str:
    return df._jdf.queryExecution().explainString(df.sparkSession._jvm.org.apache.spark.sql.execution.ExplainMode.fromString(mode))


def operators(df: DataFrame) -> dict[str, int]:
    """Physical operators and how often each occurs."""
    counts: dict[str, int] = {}
    for line in plan_text(df, "simple").splitlines():
        if m := re.match(r"[\s:+*()\d-]*([A-Z]\w+)", line):
            counts[m[1]] = counts.get(m[1], 0) + 1
    return counts


def read_columns(df: DataFrame) -> list[set[str]]:
    """Columns of each file scan."""
    return [set(re.findall(r"(\w+):", m)) for m in re.findall(r"ReadSchema: struct<(.*?)>\n", plan_text(df))]


def uses_python(df: DataFrame) -> bool:
    return bool(re.search(r"BatchEvalPython|ArrowEvalPython|MapInPandas|MapInArrow|FlatMapGroups", plan_text(df)))


def _number(text: str) -> float:
    """A metric as the status store prints it: a count, or a total with a unit."""
    last = (text.strip().splitlines() or [""])[-1].split("(")[0].replace(",", "").split()
    scale = {"KiB": 2**10, "MiB": 2**20, "GiB": 2**30, "TiB": 2**40, "ms": 1e-3, "m": 60.0, "min": 60.0, "h": 3600.0}
    return float(last[0]) * scale.get(last[1] if len(last) > 1 else "", 1.0) if last and re.fullmatch(r"-?[\d.]+", last[0]) else 0.0


def counters(df: DataFrame) -> dict[str, float]:
    """Costs of computing every row of ``df``: seconds, bytes shuffled and spilled, rows that joins put out (candidates), and exchanges."""
    spark = df.sparkSession
    store = spark._jsparkSession.sharedState().statusStore()
    before = store.executionsCount()
    seconds = timed(df)
    runs = store.executionsList()
    out = {"seconds": seconds, "shuffle_bytes": 0.0, "spill_bytes": 0.0, "join_rows": 0.0, "exchanges": 0.0}
    for k in range(int(before), runs.size()):
        run = runs.apply(k).executionId()
        values = store.executionMetrics(run)
        nodes = store.planGraph(run).allNodes()
        for i in range(nodes.size()):
            node = nodes.apply(i)
            out["exchanges"] += node.name() == "Exchange"
            for j in range(node.metrics().size()):
                metric = node.metrics().apply(j)
                if (got := values.get(metric.accumulatorId())).isDefined():
                    name, value = metric.name(), _number(got.get())
                    out["shuffle_bytes"] += value * (name == "shuffle bytes written")
                    out["spill_bytes"] += value * (name == "spill size")
                    out["join_rows"] += value * (name == "number of output rows" and "Join" in node.name())
    return out


def timed(df: DataFrame) -> float:
    """Seconds to compute every row, with no sink."""
    start = time.perf_counter()
    df.write.format("noop").mode("overwrite").save()
    return time.perf_counter() - start
