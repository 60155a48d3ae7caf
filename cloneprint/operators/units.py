"""Units of comparison (files, classes, functions) from prose and mark-up tables."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions import text as T


def lines(docs: DataFrame, *keep: str, text: str = "text") -> DataFrame:
    """A row per non-empty line: the kept columns, pos (from 0), line."""
    return docs.select(*keep, F.posexplode(F.split(text, "\n")).alias("pos", "line")).where("line <> ''")


def sentences(units: DataFrame, *keep: str, text: str = "line") -> DataFrame:
    """A row per non-empty sentence of each unit: the kept columns, s_pos, sentence (lower-cased)."""
    parts = F.posexplode(F.split(text, T.SENTENCE_END)).alias("s_pos", "part")
    return units.select(*keep, parts).select(*keep, "s_pos", F.lower(F.trim("part")).alias("sentence")).where("sentence <> ''")


def paragraphs(pages: DataFrame) -> DataFrame:
    """A row per paragraph element of a page: page_id, host, pos, para."""
    found = F.regexp_extract_all("html", F.lit(r"<p(?: [^>]*)?>([^<]*)</p>"), F.lit(1))
    return pages.select("page_id", host("url").alias("host"), F.posexplode(found).alias("pos", "para")).where("para <> ''")


def host(url: str):
    return F.regexp_extract(url, r"^[a-z]+://([^/:?#]+)", 1)


def path(url: str):
    return F.regexp_extract(url, r"^[a-z]+://[^/?#]+([^?#]*)", 1)


def with_count(units: DataFrame, key: str) -> DataFrame:
    """Units with n_same (units of equal ``key``) and is_clone; counted before any row moves, so hot keys cost one row a task."""
    counts = units.groupBy(key).agg(F.count("*").alias("n_same"))
    return units.join(counts, key).withColumn("is_clone", F.col("n_same") > 1)


def clone_rate(units: DataFrame, key: str, level: str) -> DataFrame:
    """One row: level, n_units, n_clones (units whose key occurs again), rate."""
    per_key = units.groupBy(key).agg(F.count("*").alias("n"))
    return per_key.agg(F.sum("n").alias("n_units"), F.coalesce(F.sum(F.when(F.col("n") > 1, F.col("n"))), F.lit(0)).alias("n_clones")).select(
        F.lit(level).alias("level"), "n_units", "n_clones", F.round(F.try_divide("n_clones", "n_units"), 6).alias("rate")
    )
