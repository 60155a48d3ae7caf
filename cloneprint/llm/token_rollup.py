"""Token counts as delta-maintained rollups.

A batch is a set of signed changes: an insert adds a document's count, a delete takes it back, a revision does both. It is summed
by source, language and tokenizer version before it is stored, so stored rows depend on the keys, not on the documents. A batch is
written under its id in one rename; committing an id again changes nothing, so a retried or replayed batch counts once. Totals
are the sum of the stored batches; ``compact`` folds them into one without losing the ids.

Defined cases: null sources and languages are keys of their own; a null text counts 0 tokens and 1 document; repeated rows count as often as
they occur; an empty batch is stored as such; groups whose documents and tokens are both 0 after all batches are left out.
"""

from __future__ import annotations

from urllib.parse import quote, unquote
from uuid import uuid4

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import Scratch

KEYS = ("source", "lang", "tokenizer")
#: marks that a recount of low-quality texts leaves out
MARKS = "#$%&*!|"
#: versions of counting, as patterns of one token
TOKENIZERS = {"blank-1": r"[^\x20\x09-\x0D]+", "split-1": r"[A-Za-z0-9]+|[^A-Za-z0-9\x20\x09-\x0D]"}


class Rollup:
    """Batches under one folder: ``batch=<id>`` holds a batch's sums; ``compacted=<n>`` the sums of the ids it lists.

    The compacted folder with the largest number counts, with those batches that it does not list. A new one has a larger number and is
    published by one rename before anything that it replaces is deleted, so a crash between any two steps loses nothing and counts nothing twice.
    """

    def __init__(self, spark: SparkSession, folder: str):
        self.spark, self.folder = spark, folder.rstrip("/")
        self._jvm = spark.sparkContext._jvm
        self.fs = self._path(self.folder).getFileSystem(spark.sparkContext._jsc.hadoopConfiguration())

    def _path(self, at: str):
        return self._jvm.org.apache.hadoop.fs.Path(at)

    def _names(self, kind: str) -> list[str]:
        at = self._path(self.folder)
        found = (s.getPath().getName() for s in self.fs.listStatus(at)) if self.fs.exists(at) else ()
        return sorted(n.removeprefix(f"{kind}=") for n in found if n.startswith(f"{kind}="))

    def _compacted(self) -> str | None:
        return max(self._names("compacted"), default=None, key=int)

    def _folded(self, last: str | None) -> set[str]:
        """Ids of the batches inside a compacted folder."""
        return {r["id"] for r in self.spark.read.schema("id string").parquet(f"{self.folder}/compacted={last}/ids").collect()} if last else set()

    def committed(self) -> set[str]:
        """Ids of the batches that count."""
        return {unquote(n) for n in self._names("batch")} | self._folded(self._compacted())

    def _publish(self, temp: str, name: str) -> bool:
        """A rename is the one step that makes a folder count; a folder that is there stays."""
        to = self._path(f"{self.folder}/{name}")
        done = not self.fs.exists(to) and self.fs.rename(self._path(f"{self.folder}/{temp}"), to)
        if not done:
            self.fs.delete(self._path(f"{self.folder}/{temp}"), True)
        return done

    def commit(self, batch_id: str, changes: DataFrame) -> bool:
        """Stores a batch of (source, lang, tokenizer, docs, tokens) changes; False if its id is there already."""
        if batch_id in self.committed():
            return False
        temp = f"_tmp-{uuid4().hex}"  # each attempt its own
        sums = changes.groupBy(*KEYS).agg(F.sum("docs").alias("docs"), F.sum("tokens").alias("tokens"))
        sums.write.parquet(f"{self.folder}/{temp}")
        return self._publish(temp, f"batch={quote(batch_id, safe='')}")

    def _stored(self, batches: list[str] | None = None) -> DataFrame:
        kind = "source string, lang string, tokenizer string, docs long, tokens long"
        last = self._compacted()
        inside = self._folded(last)
        parts = [f"{self.folder}/batch={n}" for n in (self._names("batch") if batches is None else batches) if unquote(n) not in inside]
        parts += [f"{self.folder}/compacted={last}/sums"] if last else []
        return self.spark.read.schema(kind).option("recursiveFileLookup", "true").parquet(*parts) if parts else self.spark.createDataFrame([], kind)

    def totals(self, batches: list[str] | None = None) -> DataFrame:
        """Sums of all batches, or of the compacted ones and those named."""
        sums = self._stored(batches).groupBy(*KEYS).agg(F.sum("docs").alias("n_docs"), F.sum("tokens").alias("n_tokens"))
        return sums.where("n_docs <> 0 or n_tokens <> 0")

    def compact(self) -> None:
        """Folds all batches into one; their ids stay known. One compaction may run at a time, beside any commits."""
        last, batches = self._compacted(), self._names("batch")
        ids = sorted({unquote(n) for n in batches} | self._folded(last))
        temp = f"_tmp-{uuid4().hex}"
        self.totals(batches).select(*KEYS, F.col("n_docs").alias("docs"), F.col("n_tokens").alias("tokens")).write.parquet(f"{self.folder}/{temp}/sums")
        self.spark.createDataFrame([(i,) for i in ids], "id string").write.parquet(f"{self.folder}/{temp}/ids")
        if self._publish(temp, f"compacted={int(last or 0) + 1:09d}"):
            self._sweep()

    def _sweep(self) -> None:
        """Deletes what the newest compacted folder replaces."""
        last = self._compacted()
        inside = self._folded(last)
        for n in self._names("compacted"):
            if n != last:
                self.fs.delete(self._path(f"{self.folder}/compacted={n}"), True)
        for n in self._names("batch"):
            if unquote(n) in inside:
                self.fs.delete(self._path(f"{self.folder}/batch={n}"), True)


def counts(text: Column) -> Column:
    """Array of (tokenizer, tokens) of a text."""
    return F.array(*[F.struct(F.lit(name).alias("tokenizer"), F.coalesce(F.regexp_count(text, F.lit(p)), F.lit(0)).cast("long").alias("tokens")) for name, p in TOKENIZERS.items()])


def changes(counted: DataFrame, sign: int) -> DataFrame:
    """Inserts (+1) or deletes (-1) of counted documents."""
    each = counted.select("source", "lang", F.explode("counts").alias("c"))
    return each.select("source", "lang", F.col("c.tokenizer").alias("tokenizer"), F.lit(sign).cast("long").alias("docs"), (F.col("c.tokens") * sign).alias("tokens"))


def replay(docs: DataFrame, labels: DataFrame) -> DataFrame:
    """All documents inserted; low-quality ones recounted without marks; toxic ones deleted; each batch sent twice."""
    spark, scratch = docs.sparkSession, Scratch(docs.sparkSession, "rollup")
    flags = labels.groupBy("doc_id").agg(F.max(F.col("toxic") == 1).alias("toxic"), F.max(F.col("quality") == 0).alias("low"))
    # both counts in the one pass that reads texts: joining first would move every text; texts without a mark are counted once
    text = F.col("text").cast("string")
    counted = docs.select("doc_id", "source", "lang", text.alias("text"), counts(text).alias("old"))
    marked = F.coalesce(F.length(F.translate("text", MARKS, "")) < F.length("text"), F.lit(False))
    counted = counted.select("doc_id", "source", "lang", "old", F.when(marked, counts(F.translate("text", MARKS, ""))).otherwise(F.col("old")).alias("new"))
    known = scratch.keep(counted.join(flags, "doc_id", "left"), "known")
    old, new = (known.select("source", "lang", "toxic", "low", F.col(c).alias("counts")) for c in ("old", "new"))
    rollup = Rollup(spark, scratch.path("totals"))
    batches = {
        "0001-insert": changes(old, 1),
        "0002-revise": changes(old.where("low"), -1).unionByName(changes(new.where("low"), 1)),
        "0003-delete": changes(old.where("toxic and not low"), -1).unionByName(changes(new.where("toxic and low"), -1)),
    }
    for _ in range(2):
        for name, batch in batches.items():
            rollup.commit(name, batch)
    rollup.compact()
    return rollup.totals()


_COUNT = " union all ".join(
    f"select doc_id, source, lang, '{name}' as tokenizer, cast(coalesce(len(regexp_extract_all(case when low then regexp_replace(text, '[#$%&*!|]', '', 'g') else text end, '{p}')), 0) as bigint) as tokens, toxic from flagged" for name, p in TOKENIZERS.items()
)
REPLAY_SQL = f"""
with flags as (select doc_id, max(toxic = 1) as toxic, max(quality = 0) as low from labels group by doc_id),
flagged as (select d.*, coalesce(f.toxic, false) as toxic, coalesce(f.low, false) as low from documents d left join flags f using (doc_id)),
counted as ({_COUNT})
select source, lang, tokenizer, cast(count(*) as bigint) as n_docs, cast(sum(tokens) as bigint) as n_tokens
from counted where not toxic group by source, lang, tokenizer
"""
