"""Refinement of reference features: supporting and trivial units, class graph and centrality, earliest origin."""

from __future__ import annotations

import math
from statistics import NormalDist

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import Window
from pyspark.sql.types import DoubleType, StructField, StructType

from ..functions import complexity as C
from ..functions import text as T
from ..plans.groups import by_group
from ..plans.store import Store

#: edges and nodes of one component that a task may hold at once; larger components go by rounds of joins
LOCAL_ROWS = 2_000_000

# Words that mark classes which only carry structure.
STRUCTURAL = ("factory", "adaptor", "adapter", "convertor", "converter", "builder", "proxy", "wrapper", "facade", "decorator", "visitor", "listener", "exception")


def drop_empty(classes: DataFrame, functions: DataFrame, key: str) -> DataFrame:
    """Classes with at least one function that has a body."""
    return classes.join(functions.select(key).distinct(), key, "left_semi")


def is_structural(name: Column) -> Column:
    """The last word of the name is one of the structural words."""
    words = T.name_words(name)
    return F.coalesce(F.try_element_at(words, F.lit(-1)).isin(*STRUCTURAL), F.lit(False))


def is_test(path: Column, rule: str = "word") -> Column:
    """A path element starts or ends with "test": as a word, or (``literal``) as mere letters."""
    parts = F.filter(F.split(path, r"[/.]"), lambda p: p != "")
    if rule == "literal":
        return F.exists(parts, lambda p: F.lower(p).rlike("^test|tests?$"))
    ends = lambda p: F.array(F.try_element_at(T.name_words(p), F.lit(1)), F.try_element_at(T.name_words(p), F.lit(-1)))
    return F.exists(parts, lambda p: F.coalesce(F.arrays_overlap(ends(p), F.array(F.lit("test"), F.lit("tests"))), F.lit(False)))


def drop_trivial(functions: DataFrame, text: str, cut: float = C.TRIVIAL_BELOW, variant: str = "log", min_unit_chars: int | None = None) -> DataFrame:
    """Functions at or above the complexity cut, or (for prose) longer than ``min_unit_chars``."""
    if min_unit_chars is not None:
        return functions.where(F.length(text) > min_unit_chars)
    return functions.where(F.round(C.prose_complexity(F.col(text), variant), 6) >= cut)


def drop_supporting(classes: DataFrame, functions: DataFrame, key: str, path: str, text: str, cut: float = C.TRIVIAL_BELOW) -> tuple[DataFrame, DataFrame]:
    """Classes after all four rules, and how many classes each rule takes away in turn: rule, n_left."""
    kept, tally = classes, [classes.select(F.lit("0 all").alias("rule"), key)]
    steps = (
        ("1 empty", lambda c: drop_empty(c, functions, key)),
        ("2 trivial", lambda c: drop_empty(c, drop_trivial(functions, text, cut), key)),
        ("3 structural", lambda c: c.where(~is_structural(F.element_at(F.split(path, "/"), -1)))),
        ("4 tests", lambda c: c.where(~is_test(F.col(path)))),
    )
    for name, rule in steps:
        kept = rule(kept)
        tally.append(kept.select(F.lit(name).alias("rule"), key))
    every = tally[0]
    for t in tally[1:]:
        every = every.unionByName(t)
    return kept, every.groupBy("rule").agg(F.count("*").alias("n_left"))


def _rank_component(damping: float, iterations: int, tolerance: float | None):
    def run(rows):
        """Rows (component, src, dst) of one component, nodes without an edge as dst alone."""
        import numpy as np

        names = sorted({r[1] for r in rows if r[1] is not None} | {r[2] for r in rows})
        at = {name: k for k, name in enumerate(names)}
        pairs = np.array([(at[r[1]], at[r[2]]) for r in rows if r[1] is not None], np.int64).reshape(-1, 2)
        src, dst = pairs[:, 0], pairs[:, 1]
        n = len(names)
        out = np.bincount(src, minlength=n)
        rank = np.full(n, 1.0 / n)
        for _ in range(iterations):
            got = np.bincount(dst, rank[src] / out[src], minlength=n)
            new = (1 - damping) / n + damping * (got + rank[out == 0].sum() / n)
            change, rank = np.abs(new - rank).max(), new
            if tolerance is not None and change <= tolerance:
                break
        return [(rows[0][0], name, float(r)) for name, r in zip(names, rank.tolist(), strict=True)]

    return run


def pagerank(edges: DataFrame, damping: float = 0.85, iterations: int = 20, tolerance: float | None = None, nodes: DataFrame | None = None, local_rows: int = LOCAL_ROWS) -> DataFrame:
    """component, node, rank for all components at once; edges: component, src (used), dst (using).

    A node that nothing uses passes its rank evenly to its component. Without ``tolerance`` the rounds are fixed. Components of at most ``local_rows`` edges
    and nodes are ranked one by one in a single pass; larger ones by rounds of joins.
    """
    store = Store(edges.sparkSession, "rank")
    edge = store.keep(edges.select("component", "src", "dst").distinct(), "edges")
    rows = edge
    if nodes is not None:
        rows = rows.unionByName(nodes.select("component", F.lit(None).cast(edge.schema["src"].dataType).alias("src"), F.col("node").alias("dst")))
        rows = store.keep(rows, "rows")
    large = store.keep(rows.groupBy("component").agg(F.count("*").alias("n")).where(F.col("n") > local_rows).select("component"), "large")
    several = not large.isEmpty()
    small = rows.join(large, "component", "left_anti") if several else rows
    kind = StructType([edge.schema["component"], StructField("node", edge.schema["dst"].dataType), StructField("rank", DoubleType())])
    out = by_group(small, ["component"], _rank_component(damping, iterations, tolerance), kind)
    if several:
        more = None if nodes is None else nodes.join(large, "component", "left_semi")
        out = out.unionByName(_rank_rounds(edge.join(large, "component", "left_semi"), damping, iterations, tolerance, more, store))
    return out


def _rank_rounds(edge: DataFrame, damping: float, iterations: int, tolerance: float | None, nodes: DataFrame | None, store: Store) -> DataFrame:
    """The same by a join and two sums a round, whatever the size of a component."""
    degree = edge.groupBy("component", "src").agg(F.count("*").alias("out"))
    edge = store.keep(edge.join(degree, ["component", "src"]), "weighted")
    seen = edge.select("component", F.col("src").alias("node")).unionByName(edge.select("component", F.col("dst").alias("node")))
    seen = (seen if nodes is None else seen.unionByName(nodes.select("component", "node"))).distinct()
    sizes = seen.groupBy("component").agg(F.count("*").alias("size"))
    users = edge.select("component", F.col("src").alias("node"), F.lit(True).alias("uses")).distinct()
    node = store.keep(seen.join(sizes, "component").join(users, ["component", "node"], "left").select("component", "node", "size", F.coalesce("uses", F.lit(False)).alias("uses")), "nodes")
    rank, step = node.withColumn("rank", 1.0 / F.col("size")), 0
    while step < iterations:
        step += 1
        given = edge.join(rank.select("component", F.col("node").alias("src"), "rank"), ["component", "src"]).groupBy("component", F.col("dst").alias("node")).agg(F.sum(F.col("rank") / F.col("out")).alias("got"))
        loose = rank.groupBy("component").agg(F.sum(F.when(~F.col("uses"), F.col("rank")).otherwise(0.0)).alias("loose"))
        new = (1 - damping) / F.col("size") + damping * (F.coalesce("got", F.lit(0.0)) + F.col("loose") / F.col("size"))
        after = node.join(given, ["component", "node"], "left").join(loose, "component").select("component", "node", "size", "uses", new.alias("rank"))
        if step % 4 == 0 or tolerance is not None or step == iterations:
            after = store.keep(after, f"rank-{step}")
            if tolerance is not None and after.alias("x").join(rank.alias("y"), ["component", "node"]).agg(F.max(F.abs(F.col("x.rank") - F.col("y.rank")))).first()[0] <= tolerance:
                rank = after
                break
        rank = after
    return rank.select("component", "node", "rank")


def centrality_percentile(ranks: DataFrame, approximate: bool = False) -> DataFrame:
    """pct in 0..1, 0 for a component's top class; ties share it.

    Distinct ranks are counted first and only the counts are put in order, so a component's copies of one rank never meet in a task.
    """
    level = F.round("rank", 12).alias("level")
    if approximate:
        cuts = ranks.groupBy("component").agg(F.percentile_approx("rank", 0.5, 100_000).alias("median"))
        return ranks.join(cuts, "component").withColumn("pct", F.when(F.col("rank") >= F.col("median"), 0.0).otherwise(1.0)).drop("median")
    counts = ranks.groupBy("component", level).agg(F.count("*").alias("k"))
    down = Window.partitionBy("component").orderBy(F.desc("level"))
    ahead = F.sum("k").over(down.rowsBetween(Window.unboundedPreceding, -1))
    total = F.sum("k").over(Window.partitionBy("component"))
    pct = counts.select("component", "level", F.coalesce(F.try_divide(F.coalesce(ahead, F.lit(0)), total - 1), F.lit(0.0)).alias("pct"))
    return ranks.withColumn("level", F.round("rank", 12)).join(pct, ["component", "level"]).select("component", "node", "rank", "pct")


def keep_central(percentiles: DataFrame, cut: float = 0.5) -> DataFrame:
    return percentiles.where(F.col("pct") <= cut)


def calibrate_cutoff(percentiles: DataFrame, confirmed: DataFrame, cut: float = 0.5) -> DataFrame:
    """Where confirmed reused classes lie: tenth of the percentile, n, and the share inside the cut over all."""
    hit = percentiles.join(confirmed.select("component", "node").distinct(), ["component", "node"], "left_semi")
    tenth = F.floor(F.least(F.col("pct"), F.lit(0.999999)) * 10 + 1e-9).cast("int")
    per = hit.groupBy(tenth.alias("tenth")).agg(F.count("*").alias("n"), F.count_if(F.col("pct") <= cut).alias("n_in"))
    totals = per.agg(F.sum("n").alias("all_n"), F.sum("n_in").alias("all_in"))
    return per.crossJoin(F.broadcast(totals)).select("tenth", "n", F.round(F.col("all_in") / F.col("all_n"), 6).alias("share_in"))  # one row each side at most ten


def sample_size(confidence: float = 0.95, margin: float = 0.05, share: float = 0.5) -> int:
    """Rows needed to estimate a proportion."""
    z = round(NormalDist().inv_cdf((1 + confidence) / 2), 2)
    return math.ceil(z * z * share * (1 - share) / margin**2)


def sample_sizes(units: DataFrame, by: str, hit: Column, cases: list[tuple[float, float]]) -> DataFrame:
    """by, n_units, share, confidence, margin, n: rows needed in each group to estimate the share of units with ``hit`` anew, taking its measured share."""
    per = units.groupBy(by).agg(F.count("*").alias("n_units"), F.count_if(hit).alias("n_hit")).withColumn("p", F.col("n_hit") / F.col("n_units"))
    case = F.explode(F.array(*[F.struct(F.lit(c).alias("confidence"), F.lit(m).alias("margin"), F.lit(round(NormalDist().inv_cdf((1 + c) / 2), 2)).alias("z")) for c, m in cases])).alias("case")
    n = F.ceil(F.col("case.z") * F.col("case.z") * F.col("p") * (1 - F.col("p")) / (F.col("case.margin") * F.col("case.margin")))
    return per.select(by, "n_units", "p", case).select(by, "n_units", F.round("p", 6).alias("share"), "case.confidence", "case.margin", n.cast("long").alias("n"))


def sample_exact(df: DataFrame, key: str, n: int, seed: int = 0) -> DataFrame:
    """The n rows with the smallest hash of key and seed: the same rows whatever the partitioning."""
    return df.orderBy(F.md5(F.concat_ws(":", F.lit(str(seed)), F.col(key).cast("string"))), key).limit(n)


def merge_in_group(features: DataFrame) -> DataFrame:
    """One row per (group_id, print): its (artifact, version) list and earliest release. features: group_id, artifact_id, version, print, released_at."""
    pair = F.struct("artifact_id", "version")
    return features.groupBy("group_id", "print").agg(F.sort_array(F.collect_set(pair)).alias("av"), F.min("released_at").alias("first_at"))


def origin_only(merged: DataFrame) -> DataFrame:
    """One row per print: the group that released it first (null times last, then the smaller name).

    A minimum over structs combines before the shuffle; a ranking window would move every row.
    """
    first = F.min(F.struct(F.col("first_at").isNull().alias("late"), "first_at", "group_id"))
    origin = merged.groupBy("print").agg(first.alias("o"), F.count("*").alias("n_groups"))
    return origin.select("print", F.col("o.group_id").alias("group_id"), F.col("o.first_at").alias("first_at"), "n_groups")


def build_index(features: DataFrame) -> DataFrame:
    """print, group_id, first_at, av of the origin group only."""
    merged = merge_in_group(features)
    origin = origin_only(features.groupBy("group_id", "print").agg(F.min("released_at").alias("first_at"))).select("print", "group_id")
    return merged.join(origin, ["print", "group_id"], "left_semi")


def origin_flip(features: DataFrame, observed: Column) -> DataFrame:
    """Prints whose origin differs when only the rows that satisfy ``observed`` are seen: print, true_group, seen_group."""
    per = lambda df: origin_only(df.groupBy("group_id", "print").agg(F.min("released_at").alias("first_at"))).select("print", "group_id")
    full, seen = per(features), per(features.where(observed))
    both = full.withColumnRenamed("group_id", "true_group").join(seen.withColumnRenamed("group_id", "seen_group"), "print")
    return both.where("true_group <> seen_group").select("print", "true_group", "seen_group")
