"""Accuracy, set and correlation measures."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F


def prf(predicted: DataFrame, truth: DataFrame, by: list[str] | None = None, methods: DataFrame | None = None) -> DataFrame:
    """tp, fp, fn, precision, recall, f1 over distinct (subject, component) pairs; ``by`` columns of ``predicted`` give a row each.

    ``methods`` lists what to give a row even without any prediction; its precision is then null.
    """
    by = by or []
    pred = predicted.select(*by, "subject", "component").distinct()
    true = truth.select("subject", "component").distinct()
    hit = pred.join(true.withColumn("hit", F.lit(1)), ["subject", "component"], "left")
    found = hit.groupBy(*by).agg(F.count("hit").alias("tp"), (F.count("*") - F.count("hit")).alias("fp"))
    if methods is not None:
        found = methods.select(*by).distinct().join(found, by, "left").select(*by, *[F.coalesce(c, F.lit(0)).cast("long").alias(c) for c in ("tp", "fp")])
    size = true.agg(F.count("*").alias("size"))
    out = found.crossJoin(F.broadcast(size)).withColumn("fn", F.col("size") - F.col("tp"))  # one row
    p, r = F.try_divide("tp", F.col("tp") + F.col("fp")), F.try_divide("tp", "size")
    f1 = F.try_divide(2 * F.col("tp"), 2 * F.col("tp") + F.col("fp") + F.col("fn"))
    return out.select(*by, "tp", "fp", "fn", F.round(p, 6).alias("precision"), F.round(r, 6).alias("recall"), F.round(f1, 6).alias("f1"))


def macro_prf(predicted: DataFrame, truth: DataFrame, by: list[str] | None = None) -> DataFrame:
    """Means over subjects: precision of those with a prediction, recall and f1 of those with a true component."""
    by = by or []
    pred = predicted.select(*by, "subject", "component").distinct()
    true = truth.select("subject", "component").distinct()
    size = true.groupBy("subject").agg(F.count("*").alias("n_t"))
    hit = pred.join(true.withColumn("hit", F.lit(1)), ["subject", "component"], "left").groupBy(*by, "subject").agg(F.count("*").alias("n_p"), F.count("hit").alias("hit"))
    per = hit.join(size, "subject", "left")
    # a true subject without a prediction adds nothing to the sums, so only their number is needed
    sums = per.groupBy(*by).agg(F.avg(F.col("hit") / F.col("n_p")).alias("p"), F.sum(F.try_divide("hit", "n_t")).alias("r"), F.sum(F.when(F.col("n_t") > 0, 2 * F.col("hit") / (F.col("n_p") + F.col("n_t")))).alias("f"))
    n = size.agg(F.count("*").alias("n"))
    mean = lambda c: F.round(F.try_divide(F.coalesce(c, F.lit(0.0)), "n"), 6)
    return sums.crossJoin(F.broadcast(n)).select(*by, F.round("p", 6).alias("precision"), mean("r").alias("recall"), mean("f").alias("f1"))  # one row


def improvement_rate(cc: DataFrame, pm: DataFrame, strict: bool = False) -> DataFrame:
    """Per subject with cloned components: n_cc, n_pm, n_new, n_both, ir (percent), dr (percent, null without declared ones).

    ir = new / declared; 100 if nothing is declared (``strict``: only with two or more cloned).
    """
    a = cc.select("subject", "component").distinct().withColumn("c", F.lit(1))
    b = pm.select("subject", "component").distinct().withColumn("p", F.lit(1))
    both = a.join(b, ["subject", "component"], "full").groupBy("subject").agg(F.count("c").alias("n_cc"), F.count("p").alias("n_pm"), F.count_if(F.col("c").isNotNull() & F.col("p").isNull()).alias("n_new"))
    both = both.where("n_cc > 0").withColumn("n_both", F.col("n_cc") - F.col("n_new"))
    alone = F.when(F.col("n_cc") >= (2 if strict else 1), F.lit(1.0))
    ir = F.when(F.col("n_pm") == 0, alone).otherwise(F.try_divide("n_new", "n_pm"))
    return both.select("subject", "n_cc", "n_pm", "n_new", "n_both", F.round(100 * ir, 6).alias("ir"), F.round(100 * F.try_divide("n_both", "n_pm"), 6).alias("dr"))


def mean_rates(rates: DataFrame) -> DataFrame:
    """One row: n_subjects, mean_ir, mean_dr; undefined rates are left out of their mean."""
    return rates.agg(F.count("*").alias("n_subjects"), F.round(F.avg("ir"), 4).alias("mean_ir"), F.round(F.avg("dr"), 4).alias("mean_dr"))


def prevalence(cc: DataFrame, subjects: DataFrame) -> DataFrame:
    """One row: n_subjects, n_with (subjects with a cloned component), n_cc, share."""
    per = cc.groupBy("subject").agg(F.count_distinct("component").alias("k"))
    got = subjects.select("subject").distinct().join(per, "subject", "left")
    return got.agg(F.count("*").alias("n_subjects"), F.count("k").alias("n_with"), F.coalesce(F.sum("k"), F.lit(0)).alias("n_cc")).withColumn("share", F.round(F.try_divide("n_with", "n_subjects"), 6))


def strength(r: Column) -> Column:
    """Name of a correlation's size; 0.6 to 0.8 has none."""
    a = F.abs(r)
    return F.when(a < 0.3, "weak").when(a <= 0.6, "moderate").when(a >= 0.8, "strong").otherwise("unnamed")


def correlation(subjects: DataFrame, cc: DataFrame, *attributes: str) -> DataFrame:
    """attribute, r (Pearson, of the number of cloned components), strength; subjects without any count as 0."""
    per = cc.groupBy("subject").agg(F.count_distinct("component").alias("k"))
    base = subjects.join(per, "subject", "left").withColumn("k", F.coalesce("k", F.lit(0)).cast("double"))
    wide = base.agg(*[F.corr("k", F.col(a).cast("double")).alias(a) for a in attributes])
    rows = wide.select(F.explode(F.array(*[F.struct(F.lit(a).alias("attribute"), F.round(F.col(a), 6).alias("r")) for a in attributes])).alias("x"))
    return rows.select("x.attribute", "x.r", strength(F.col("x.r")).alias("strength"))


def size_profile(subjects: DataFrame, size: str, work: str, buckets: list[int]) -> DataFrame:
    """Work per subject by size bucket: bucket, n, mean_work, var_work."""
    level = F.size(F.filter(F.array(*[F.lit(b) for b in buckets]), lambda b: F.col(size) >= b))
    return subjects.groupBy(level.alias("bucket")).agg(F.count("*").alias("n"), F.round(F.avg(work), 4).alias("mean_work"), F.round(F.var_samp(work), 4).alias("var_work"))
