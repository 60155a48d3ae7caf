"""From documents to packed training sequences.

Quality classifier, near duplicates, repeated passages, benchmark copies, packing: each stage reads what the one before
wrote, and takes (spark, docs, sf_dir).

Defined cases, in every stage: an empty table gives an empty one with the same columns; other columns pass through whatever their names. A null text counts as
empty: the classifier scores it, the stages after it leave it as it is, and it packs as its end id. A null doc_id never groups with another row. Rows that
repeat a doc_id and its text are one document and stay or go together; a doc_id with several texts goes as a near duplicate if any of them links to an earlier
id, while its other stages judge each text.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from cloneprint.llm import decontaminate, minhash_dedup, packing, quality, substring_dedup
from cloneprint.llm.common import Scratch, quoted, read_table, unused
from cloneprint.llm.encode import public_path

#: a document goes when its score is below this; lower than the operator's own cut, so that doubtful documents stay
QUALITY_CUT = 0.5


def quality_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Keeps documents that the classifier does not reject."""
    model = quality.fit(docs, read_table(spark, sf_dir, "labels", "doc_id", "quality"))
    name = unused(docs, "score")
    return quality.score(docs, model, docs.columns, name).where(F.col(name) >= QUALITY_CUT).drop(name)


def near_duplicate_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Keeps the document with the smallest id of each group of near duplicates."""
    scratch = Scratch(spark, "near-stage")
    gone = scratch.keep(minhash_dedup.near_duplicates(docs).where("not kept").select("doc_id").distinct(), "gone")
    return docs.join(gone, "doc_id", "left_anti").select(*[quoted(c) for c in docs.columns])


def substring_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Cuts passages that stand in an earlier document; what has no word left goes."""
    spans = unused(docs, "spans")
    cut = substring_dedup.dedup_units(docs, spans_col=spans)
    left = cut.where((F.size(spans) == 0) | F.col("text").rlike(r"[^\x20\x09-\x0D]"))
    return left.withColumn("n_chars", F.when(F.size(spans) > 0, F.char_length("text").cast("long")).otherwise(F.col("n_chars"))).drop(spans)


def decontamination_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Drops documents that hold a benchmark item or an edited copy."""
    scratch = Scratch(spark, "leak-stage")
    # judged by the text, which needs no id
    texts = docs.select(F.xxhash64("text").alias("doc_id"), "text")
    gone = scratch.keep(decontaminate.contaminated(texts, read_table(spark, sf_dir, "benchmark")).select(F.col("doc_id").alias("gone")).distinct(), "gone")
    return docs.join(gone, F.xxhash64(docs["text"]) == gone["gone"], "left_anti")


def packing_stage(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    return packing.pack(docs, public_path(), window=1024, end=0)


STAGES = [
    ("quality classifier", quality_stage),
    ("minhash near-dedup", near_duplicate_stage),
    ("substring dedup", substring_stage),
    ("benchmark decontamination", decontamination_stage),
    ("packing", packing_stage),
]
#: no stage but the last is expressible in SQL; tests compare with a brute-force version
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    scratch, docs = Scratch(spark, "pipeline"), read_table(spark, sf_dir, "documents")
    for name, stage in STAGES:
        docs = scratch.keep(stage(spark, docs, sf_dir), name.replace(" ", "-"))
    return docs
