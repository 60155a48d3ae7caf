"""The detector end to end: prints of linked classes, a refined index of the reference side, and verdicts for subjects.

    prints = class_prints(units, config)                    # class_id, pos, line
    index = reference_index(prints, classes, uses, config)
    verdict = detect(subject_prints, index, config)

Every step that ``DetectConfig`` names is one that can be left out, so the same code runs the full method and its ablations.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions import complexity as C
from ..functions import hashing as H
from ..plans.store import Store
from . import extract as E
from . import recognize as N
from . import refine as R
from .recognize import DetectConfig


def _real(config: DetectConfig, text: str, value=None):
    """Whether a function is no trivial one."""
    if config.min_unit_chars is not None:
        return F.length(text) > config.min_unit_chars
    if config.complexity_cut is not None:
        value = C.prose_complexity(F.col(text), config.complexity_variant) if value is None else value
        return F.round(value, 6) >= config.complexity_cut
    return F.lit(True)


def class_prints(units: DataFrame, config: DetectConfig) -> DataFrame:
    """class_id, print of classes whose functions are text units (class_id, pos, line)."""
    if config.variant == "mixed":
        return E.mixed_print(units.where(_real(config, "line")), config.hash_kind)
    store = Store(units.sparkSession, "prints")
    functions = E.functions_of(units, config.skeleton, config.hash_kind).withColumn("real", _real(config, "line"))
    if not config.linking:
        return prints_of(functions, None, config)
    functions = store.keep(functions, "functions")
    return prints_of(functions.drop("line", "name"), E.call_edges(functions), config)


def prints_of(functions: DataFrame, calls: DataFrame | None, config: DetectConfig) -> DataFrame:
    """The same from functions (class_id, fn, loc, own, real) and calls (class_id, caller, callee, n).

    Trivial functions go before linking, on both sides alike; a call of one is then a call that leaves the class.
    """
    kept = functions.where("real")
    if not config.linking or calls is None:
        node = H.added(F.col("own"), H.own_hash(F.lit(E.FUNCTION), config.hash_kind))
        whole = kept.groupBy("class_id").agg(H.total(node).alias("s"))
        return whole.select("class_id", H.added(F.col("s"), H.own_hash(F.lit(E.CLASS), config.hash_kind)).alias("print"))
    store = Store(functions.sparkSession, "linked")
    real = kept.select("class_id", "fn")
    inside = calls.join(real.withColumnRenamed("fn", "caller"), ["class_id", "caller"])
    inside = store.keep(inside.join(real.select("class_id", F.col("fn").alias("callee"), F.lit(True).alias("held")), ["class_id", "callee"], "left"), "calls")
    acyclic = E.break_cycles(inside.where("held").drop("held"), kept, config.loop_scope)
    outside = inside.where("held is null").select("class_id", "caller", "callee", "n", F.lit("external").alias("status"))
    acyclic = store.keep(acyclic.unionByName(outside), "acyclic")
    return E.class_print(E.link(kept, acyclic, config.hash_kind, config.recursion), acyclic, config.roots, config.hash_kind)


def reference_index(prints: DataFrame, classes: DataFrame, uses: DataFrame | None, config: DetectConfig) -> DataFrame:
    """print, group_id, first_at, av of the reference side.

    classes: class_id, component, group_id, artifact_id, version, path, released_at; uses: component, src, dst (class ids, dst uses src). Classes
    without a print (no function, or trivial ones only) are gone already; structural and test classes go by their paths, then the less
    central half, then what another group released first.
    """
    store = Store(prints.sparkSession, "reference")
    kept = classes.join(prints.select("class_id").distinct(), "class_id", "left_semi")
    if config.structural:
        kept = kept.where(~R.is_structural(F.element_at(F.split("path", "/"), -1)))
    if config.tests:
        kept = kept.where(~R.is_test(F.col("path")))
    if config.central_cut is not None and uses is not None:
        kept = store.keep(kept, "classes")
        node = kept.select("component", F.col("class_id").alias("node"))
        edges = uses.join(node.withColumnRenamed("node", "src"), ["component", "src"], "left_semi").join(node.withColumnRenamed("node", "dst"), ["component", "dst"], "left_semi")
        central = R.keep_central(R.centrality_percentile(R.pagerank(edges, nodes=node)), config.central_cut)
        kept = kept.join(central.select("component", F.col("node").alias("class_id")), ["component", "class_id"], "left_semi")
    features = prints.join(kept, "class_id")
    if not config.origin:
        return R.merge_in_group(features)
    return R.build_index(store.keep(features.select("group_id", "artifact_id", "version", "print", "released_at"), "features"))


def detect(subjects: DataFrame, index: DataFrame, config: DetectConfig) -> DataFrame:
    """subject, group_id (or artifact_id), n_evidence. subjects: subject, class_id, print, and owner if a subject's own group is no evidence."""
    evidence = N.match(subjects, index)
    if config.exclude_self:
        evidence = evidence.where("owner <> group_id")
    if config.level == "artifact":
        evidence = evidence.select("subject", "print", F.explode("av.artifact_id").alias("artifact_id")).distinct()
        return N.recognize(evidence, config.min_evidence, "artifact_id")
    if config.level != "group":
        raise ValueError(f"no level {config.level!r}")
    return N.recognize(evidence, config.min_evidence)
