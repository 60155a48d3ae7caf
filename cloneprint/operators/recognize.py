"""Recognition: match subject prints with the refined index; one piece of evidence is reuse."""

from __future__ import annotations

from dataclasses import asdict, dataclass
from hashlib import sha256

from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import Window


@dataclass(frozen=True)
class DetectConfig:
    """How ``detect`` makes prints, refines the reference side and decides. Both sides must share what changes a print or the index."""

    skeleton: str = "exact"
    hash_kind: str = "portable"
    variant: str = "additive"  # or "mixed", which hashes by level and does not link
    linking: bool = True
    recursion: str = "site"
    loop_scope: str = "scc"
    roots: str = "entry"
    complexity_variant: str = "log"
    complexity_cut: float | None = 60.0
    min_unit_chars: int | None = None  # for prose, in place of the complexity cut
    structural: bool = True
    tests: bool = True
    central_cut: float | None = 0.5
    origin: bool = True
    min_evidence: int = 1
    exclude_self: bool = False
    level: str = "group"

    def digest(self) -> str:
        """Of all that an index depends on; what only the decision uses is left out."""
        made = {k: v for k, v in asdict(self).items() if k not in ("min_evidence", "exclude_self", "level")}
        return sha256(repr(sorted(made.items())).encode()).hexdigest()[:16]


def match(subject_prints: DataFrame, index: DataFrame, exclude_self: bool = False, verdict_only: bool = False) -> DataFrame:
    """Evidence: subject, class_id, print, group_id (and av). A plain equi-join: Spark broadcasts a small index and sorts a large one.

    ``verdict_only`` drops classes and lists, so that a subject's copies of one print meet the index once.
    """
    if verdict_only:
        out = subject_prints.select("subject", "print").distinct().join(index.select("print", "group_id"), "print")
    else:
        out = subject_prints.join(index, "print")
    return out.where(F.col("subject").cast("string") != F.col("group_id").cast("string")) if exclude_self else out


def recognize(evidence: DataFrame, min_evidence: int = 1, group: str = "group_id") -> DataFrame:
    """subject, group, n_evidence: reuse of each group with enough distinct matched prints."""
    return evidence.groupBy("subject", group).agg(F.count_distinct("print").alias("n_evidence")).where(F.col("n_evidence") >= min_evidence)


def version_candidates(evidence: DataFrame) -> DataFrame:
    """subject, group_id, artifact_id, version, n_support: versions that the most evidence carries (all of it, if there are such)."""
    prints = evidence.select("subject", "group_id", "print", "av").dropDuplicates(["subject", "group_id", "print"])
    support = prints.select("subject", "group_id", F.explode("av").alias("v")).groupBy("subject", "group_id", F.col("v.artifact_id").alias("artifact_id"), F.col("v.version").alias("version")).agg(F.count("*").alias("n_support"))
    most = support.groupBy("subject", "group_id").agg(F.max("n_support").alias("most"))
    return support.join(most, ["subject", "group_id"]).where("n_support = most").drop("most")


def outdated_copies(candidates: DataFrame, releases: DataFrame) -> DataFrame:
    """Per (subject, group_id, artifact_id): newest supported version, newest release, days between."""
    when = releases.select("artifact_id", "version", "released_at")
    have = candidates.join(when, ["artifact_id", "version"]).groupBy("subject", "group_id", "artifact_id").agg(F.max("released_at").alias("copied_at"))
    newest = when.groupBy("artifact_id").agg(F.max("released_at").alias("newest_at"))
    return have.join(newest, "artifact_id").select("subject", "group_id", "artifact_id", "copied_at", "newest_at", F.datediff("newest_at", "copied_at").alias("days_behind")).where("newest_at > copied_at")


def reuse_reason(evidence: DataFrame, component_sizes: DataFrame, stripped: DataFrame, unpublished: DataFrame | None = None) -> DataFrame:
    """subject, component, share, reason: licence stripped, origin off the repository, whole copy, or partial copy.

    component_sizes: component, size. stripped: subject, component. unpublished: components whose source nobody released.
    """
    got = evidence.groupBy("subject", "component").agg(F.count_distinct("print").alias("n"))
    share = got.join(component_sizes, "component").withColumn("share", F.round(F.col("n") / F.col("size"), 6))
    flag = stripped.select("subject", "component").distinct().withColumn("stripped", F.lit(True))
    share = share.join(flag, ["subject", "component"], "left")
    off = F.lit(False)
    if unpublished is not None:
        share = share.join(unpublished.select("component").distinct().withColumn("off", F.lit(True)), "component", "left")
        off = F.coalesce("off", F.lit(False))
    reason = F.when(F.coalesce("stripped", F.lit(False)), "licence stripped").when(off, "off repository").when(F.col("share") >= 1, "whole copy").otherwise("partial copy")
    return share.select("subject", "component", "share", reason.alias("reason"))


def explain_false_positives(evidence: DataFrame, texts: DataFrame) -> DataFrame:
    """subject, class_id, generated, from_web: matched classes that say where else they come from. texts: class_id, text."""
    hit = evidence.select("subject", "class_id").distinct().join(texts, "class_id")
    generated = F.lower("text").rlike("generated by|do not edit")
    web = F.lower("text").rlike("https?://|stack ?overflow")
    return hit.select("subject", "class_id", generated.alias("generated"), web.alias("from_web"))


def top_evidence(verdict: DataFrame, k: int, group: str = "group_id") -> DataFrame:
    """The k groups with most evidence of each subject."""
    order = Window.partitionBy("subject").orderBy(F.desc("n_evidence"), group)
    return verdict.withColumn("place", F.row_number().over(order)).where(F.col("place") <= k)
