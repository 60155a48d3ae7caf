"""Compared methods: function ratio, file hash and path, manifests, and exact containment."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..plans.store import Store
from . import similar as S
from .study import overlap_ratio

THETA = 0.15
#: characters of patterns that one automaton may hold; more take another pass
PATTERN_CHARS = 16_000_000


def function_ratio(subject: DataFrame, component: DataFrame, theta: float = THETA) -> DataFrame:
    """subject, component, shared, ratio where at least ``theta`` of a component's distinct functions stand in the subject."""
    return overlap_ratio(subject, component, "component").where(F.col("ratio") >= theta)


def function_ratio_similar(subject: DataFrame, component: DataFrame, theta: float = THETA, percent: int = S.PERCENT) -> DataFrame:
    """The ratio with similar functions as matches. Columns: subject or component, text; functions under three words are left out.

    Subject functions that hold too few shingles of any component go first. What is left of both sides is put in classes of equal shingle sets, and classes are compared once,
    however many functions they hold.
    """
    store = Store(subject.sparkSession, "ratio")
    tag = lambda df, owner, side: S.shingled(df.select(F.struct(F.lit(side).alias("side"), F.col(owner).alias("owner")).alias("id"), "text"), "id", "text")
    parts = tag(component, "component", "c")
    sets = store.keep(S.reaching(tag(subject, "subject", "s"), parts, percent).unionByName(parts), "sets", "zstd")
    groups = S.classes(sets, store)
    near = S.both_ways(S.prefix_join(groups, percent), groups).select(F.col("rep").alias("a"), F.col("other").alias("b"))
    held = sets.join(groups.select("rep", "h1", "h2"), ["h1", "h2"]).select("id.side", "id.owner", "rep").distinct()
    s = held.where("side = 's'").select(F.col("owner").alias("subject"), F.col("rep").alias("a"))
    c = held.where("side = 'c'").select(F.col("owner").alias("component"), F.col("rep").alias("b"))
    size = c.groupBy("component").agg(F.count("*").alias("size"))
    shared = s.join(near, "a").join(c, "b").select("subject", "component", "b").distinct().groupBy("subject", "component").agg(F.count("*").alias("shared"))
    return shared.join(size, "component").select("subject", "component", "shared", F.round(F.col("shared") / F.col("size"), 6).alias("ratio")).where(F.col("ratio") >= theta)


def theta_sweep(subject: DataFrame, component: DataFrame, thetas: list[float]) -> DataFrame:
    """theta, subject, component of every threshold: one match, then each ratio is listed under the thresholds it reaches."""
    ratio = overlap_ratio(subject, component, "component")
    return ratio.select(F.explode(F.filter(F.array(*[F.lit(float(t)) for t in thetas]), lambda t: F.col("ratio") >= t)).alias("theta"), "subject", "component")


def build_function_db(functions: DataFrame) -> DataFrame:
    """Function features of all versions, each once: print, n_groups, group_id (smallest holder)."""
    return functions.groupBy("print").agg(F.count_distinct("group_id").alias("n_groups"), F.min("group_id").alias("group_id"))


def file_hash_match(subjects: DataFrame, components: DataFrame) -> DataFrame:
    """subject, component of files with equal hash; copies of one hash on a side count once."""
    return subjects.select("subject", "hash").distinct().join(components.select("component", "hash").distinct(), "hash").select("subject", "component").distinct()


def path_suffix(path, depth: int = 2):
    """Last elements of a path, lower-cased."""
    parts = F.filter(F.split(F.lower(path), "/"), lambda p: p != "")
    return F.array_join(F.slice(parts, F.greatest(F.size(parts) - depth + 1, F.lit(1)), depth), "/")


def file_path_match(files: DataFrame, owner: str, path: str, depth: int = 2) -> DataFrame:
    """suffix, n_files, n_owners of path suffixes that several owners share."""
    tagged = files.select(owner, path_suffix(F.col(path), depth).alias("suffix")).where("suffix <> ''")
    return tagged.groupBy("suffix").agg(F.count("*").alias("n_files"), F.count_distinct(owner).alias("n_owners")).where("n_owners > 1")


def declared_from_manifest(manifests: DataFrame) -> DataFrame:
    """subject, group_id, artifact_id, version, malformed of each dependency of an XML manifest (columns subject, xml)."""
    block = F.regexp_extract_all("xml", F.lit(r"(?s)(<dependency>.*?</dependency>)"), F.lit(1))
    sound = F.col("xml").rlike(r"(?s)<project[ >].*</project>\s*$") & (F.size(block) == F.regexp_count("xml", F.lit("<dependency>")))
    pick = lambda name: F.when(F.regexp_extract("d", rf"<{name}>\s*([^<]*?)\s*</{name}>", 1) != "", F.regexp_extract("d", rf"<{name}>\s*([^<]*?)\s*</{name}>", 1))
    return manifests.select("subject", (~sound).alias("malformed"), F.explode_outer(F.when(sound, block)).alias("d")).select(
        "subject", pick("groupId").alias("group_id"), pick("artifactId").alias("artifact_id"), pick("version").alias("version"), "malformed"
    )


def contains_truth(texts: DataFrame, patterns: DataFrame, text_id: str, pattern_id: str) -> DataFrame:
    """(text_id, pattern_id) where a text holds a whole pattern.

    One automaton finds all patterns in a pass over each text; no pair of text and pattern is formed. Patterns reach executors in
    slices of bounded size.
    """
    spark: SparkSession = texts.sparkSession
    wanted = patterns.select(F.col(pattern_id).cast("long").alias("p"), F.col("text").alias("t")).where("t <> ''")
    slices = max(1, -(-(wanted.agg(F.sum(F.length("t"))).first()[0] or 0) // PATTERN_CHARS))
    out = None
    for k in range(slices):
        part = [(r["p"], r["t"]) for r in wanted.where(F.pmod(F.xxhash64("p"), F.lit(slices)) == k).collect()]
        handle = spark.sparkContext.broadcast(part)
        found = texts.select(F.col(text_id).cast("long"), "text").mapInArrow(_contained(handle, text_id, pattern_id), f"{text_id} long, {pattern_id} long")
        out = found if out is None else out.unionByName(found)
    return out


def _contained(handle, text_id: str, pattern_id: str):
    def run(batches):
        import ahocorasick
        import pyarrow as pa

        machine, owners = ahocorasick.Automaton(), {}
        for p, t in handle.value:
            owners.setdefault(t, []).append(p)
        for t in owners:
            machine.add_word(t, t)
        if owners:
            machine.make_automaton()
        for batch in batches:
            a, b = [], []
            for key, text in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), strict=True):
                for t in {t for _, t in machine.iter(text)} if owners and text else ():
                    for p in owners[t]:
                        a.append(key)
                        b.append(p)
            yield pa.RecordBatch.from_arrays([pa.array(a, pa.int64()), pa.array(b, pa.int64())], [text_id, pattern_id])

    return run
