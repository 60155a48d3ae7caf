"""Ground-truth rules: paths, change-log phrases, licence asymmetry, author affiliation, and their union."""

from __future__ import annotations

from functools import reduce

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

# Phrases that tell of copied code, vendor folders, and platform names.
PHRASES = ("forked from", "copied from", "copy from", "modified version of", "based on the work of", "based on the work done by", "based on work of", "part of")
VENDOR_FOLDERS = ("shared", "ext", "jre")
PLATFORMS = ("arm64", "x86", "x64", "amd64", "linux", "windows", "win", "win32", "win64", "darwin", "macos", "osx", "android", "ios")
LICENCE = r"licen[sc]e|copyright|all rights reserved"


def phrase(text: Column) -> Column:
    return F.regexp_extract(F.lower(text), "(" + "|".join(PHRASES) + ")", 1)


def phrase_evidence(classes: DataFrame, key: str, text: str) -> DataFrame:
    """key, phrase of texts that name where they come from."""
    return classes.select(key, phrase(F.col(text)).alias("phrase")).where("phrase <> ''")


def vendor(host: Column) -> Column:
    """The label that names a host's owner: the one before the registered domain, or the domain's own if there is none."""
    parts = F.split(host, "[.]")
    return F.coalesce(F.try_element_at(parts, F.lit(-3)), F.try_element_at(parts, F.lit(-2)), host)


def has_licence(text: Column) -> Column:
    return F.lower(text).rlike(LICENCE)


def licence_evidence(pairs: DataFrame) -> DataFrame:
    """subject, component where the component's class has a licence text and the subject's copy has none. pairs: subject, component, subject_text, component_text."""
    return pairs.where(has_licence(F.col("component_text")) & ~has_licence(F.col("subject_text"))).select("subject", "component").distinct()


def path_evidence(files: DataFrame, path: str, group: Column) -> DataFrame:
    """Files with flags in_group (the group's name as folders of the path) and vendor (a vendor folder)."""
    folders = F.concat(F.lit("/"), F.translate(group, ".", "/"), F.lit("/"))
    parts = F.split(F.lower(path), "/")
    vendor = F.arrays_overlap(parts, F.array(*[F.lit(v) for v in VENDOR_FOLDERS]))
    return files.withColumns({"in_group": F.contains(F.lower(F.concat(F.col(path), F.lit("/"))), F.lower(folders)), "vendor": vendor})


def affiliations(text: Column) -> Column:
    """Domains of the e-mail addresses in a text."""
    return F.array_distinct(F.regexp_extract_all(text, F.lit(r"[\w.]+@([\w.]+)"), F.lit(1)))


def author_evidence(pairs: DataFrame) -> DataFrame:
    """subject, component whose author lists overlap. pairs: subject, component, subject_authors, component_authors."""
    return pairs.where(F.arrays_overlap("subject_authors", "component_authors")).select("subject", "component").distinct()


def truth_from_rules(**rules: DataFrame) -> DataFrame:
    """subject, component, rules (sorted names, joined by commas) of all pairs that any rule gives."""
    tagged = [df.select("subject", "component", F.lit(name).alias("rule")) for name, df in rules.items()]
    every = reduce(DataFrame.unionByName, tagged)
    return every.groupBy("subject", "component").agg(F.array_join(F.array_sort(F.collect_set("rule")), ",").alias("rules"))


def curate_subjects(subjects: DataFrame, min_stars: int = 20) -> DataFrame:
    """Subjects that are no forks, build, and have enough stars."""
    return subjects.where(~F.col("is_fork") & F.col("builds") & (F.col("stars") >= min_stars))


def curate_components(components: DataFrame, name: str = "artifact_id") -> DataFrame:
    """Components without the platform variants of one another."""
    return components.where(~F.lower(name).rlike("[-_.](" + "|".join(PLATFORMS) + ")([-_.]|$)"))


def licence_stripped(evidence: DataFrame, texts: DataFrame, components: DataFrame) -> DataFrame:
    """Pairs of evidence (subject, class_id, component) whose component text has a licence that the copy lacks."""
    both = evidence.join(texts.select("class_id", F.col("text").alias("subject_text")), "class_id").join(components.select("component", F.col("text").alias("component_text")), "component")
    return licence_evidence(both)
