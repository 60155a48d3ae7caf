"""Time and cost of both methods: seconds of building features and of recognition, by size of the subjects, and counters of the plans.

Results are measurements, so they differ from run to run; no SQL can give them.
"""

from __future__ import annotations

from pyspark.sql import Window
from pyspark.sql import functions as F

from ..operators import baselines as B
from ..operators import extract as E
from ..operators import recognize as N
from ..operators import refine as R
from ..operators import units as U
from ..plans import explain
from ..plans.store import Store
from . import engine
from .tables import table

GROUPS = 8


def _generation(spark, d):
    """The reference side of each method over all documents: the refined class index, and the function database of all versions."""
    sentences = E.additive_print(engine._sentences(spark, d), "sentence", F.col("source").alias("group_id"))
    return {"class print": R.build_index(engine._features(spark, d)), "function ratio": B.build_function_db(sentences)}


def _recognition(subjects, index, components):
    return {"class print": N.recognize(N.match(subjects, index, verdict_only=True)), "function ratio": B.function_ratio(subjects, components)}


def _sides(spark, d, store):
    return store.keep(engine._item_index(spark, d), "index"), store.keep(engine._component_prints(spark, d), "components")


def seconds(spark, d):
    """method, step, n_items, seconds, per_item of generation and recognition, over whole tables."""
    store = Store(spark, "seconds")
    n = table(spark, d, "documents").count()
    made = {k: explain.timed(df) for k, df in _generation(spark, d).items()}
    found = {k: explain.timed(df) for k, df in _recognition(engine._subject_prints(spark, d), *_sides(spark, d, store)).items()}
    rows = [(method, step, n, s, s / max(n, 1)) for step, took in (("generation", made), ("recognition", found)) for method, s in took.items()]
    return spark.createDataFrame(rows, "method string, step string, n_items long, seconds double, per_item double")


def by_size(spark, d):
    """method, n_groups, mean and variance of the seconds per subject, and their correlation with size, over groups of subjects of like size."""
    store = Store(spark, "bysize")
    docs = table(spark, d, "documents", "doc_id", "source", "lang", "text", F.coalesce(F.length("text"), F.lit(0)).alias("size"))
    # bounds of the groups from the sizes' counts, so that no subjects are put in order
    counts = docs.groupBy("size").agg(F.count("*").alias("n"))
    upto = F.sum("n").over(Window.orderBy("size"))
    bounds = counts.select("size", F.ceil(upto * GROUPS / F.sum("n").over(Window.partitionBy())).alias("g")).groupBy("g").agg(F.max("size").alias("top")).orderBy("g").collect()
    index, components = _sides(spark, d, store)
    rows, low = [], -1
    for r in bounds:  # at most GROUPS
        part = docs.where((F.col("size") > low) & (F.col("size") <= r["top"]))
        low = r["top"]
        n, size = part.agg(F.count("*"), F.avg("size")).first()
        sentences = U.sentences(U.lines(part, "doc_id"), "doc_id").where(F.length("sentence") > engine.MIN_CHARS)
        prints = E.additive_print(sentences, "sentence", F.col("doc_id").alias("subject"), F.col("doc_id").alias("class_id"))
        rows += [(method, n, float(size or 0), explain.timed(df) / max(n, 1)) for method, df in _recognition(prints, index, components).items()]
    took = spark.createDataFrame(rows, "method string, n long, size double, per_subject double")
    return took.groupBy("method").agg(F.count("*").alias("n_groups"), F.avg("per_subject").alias("mean_seconds"), F.var_samp("per_subject").alias("var_seconds"), F.corr("size", "per_subject").alias("r_size"))


def counters(spark, d):
    """method, seconds, shuffle_bytes, spill_bytes, join_rows, exchanges of recognition over all documents."""
    store = Store(spark, "counters")
    rows = [(method, *explain.counters(df).values()) for method, df in _recognition(engine._subject_prints(spark, d), *_sides(spark, d, store)).items()]
    return spark.createDataFrame(rows, "method string, seconds double, shuffle_bytes double, spill_bytes double, join_rows double, exchanges double")


QUERIES = {"rq2_seconds": seconds, "rq2_seconds_by_size": by_size, "rq2_cost_counters": counters}
ORACLE: dict[str, str] = {}
