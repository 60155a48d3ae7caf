"""The Java front end on sources made from the parts table: a class per part, two functions, calls and branches by the part's size."""

from __future__ import annotations

from pyspark.sql import functions as F

from ..functions import text as T
from ..operators import detect as D
from ..operators import units as U
from ..sources import java
from .tables import table

#: files that do not parse, beside the good ones
BROKEN = (("broken/one.java", "class A { void f() {"), ("broken/two.java", "class B } {"))
#: Java has no cut here: every function of these small classes is below the published one
CONFIG = D.DetectConfig(complexity_cut=None, central_cut=None, exclude_self=True)


def _sources(spark, d):
    """path, text, and the numbers that shape the class: k branches, m calls."""
    part = table(spark, d, "part", "p_partkey", "p_name", "p_brand", "p_type", "p_size")
    one, two = (F.concat(F.split("p_name", " ")[k], F.lit("It")) for k in (0, 1))  # no word alone, as some are reserved
    k, m = F.col("p_size") % 4, F.col("p_size") % 3
    text = F.concat(
        F.lit("package "), F.lower("p_type"), F.lit(";\n/* part "), F.col("p_partkey"), F.lit(" \"quoted\" // mark */\npublic class "), F.translate(F.initcap("p_name"), " ", ""),
        F.lit(" {\n  int "), one, F.lit("(int a) {"), F.repeat(F.lit(" if (a > 1) { a = a - 1; }"), k), F.lit(" return "), F.when(m > 0, F.concat(two, F.lit("(a)"))).otherwise("a"),
        F.lit("; }\n  int "), two, F.lit("(int b) { String s = \"http://"), one, F.lit("\"; return "), F.when(m == 2, F.concat(one, F.lit("(b)"))).otherwise("b"), F.lit("; }\n}\n"),
    )
    return part.select(F.concat("p_brand", F.lit("/"), "p_partkey", F.lit(".java")).alias("path"), text.alias("text"), F.col("p_brand").alias("owner"), "p_partkey")


def _parsed(spark, d):
    return java.units(_sources(spark, d))


def functions(spark, d):
    return _parsed(spark, d).select("path", "class_name", "fn_name", "pos", "loc", "cc", "error")


def calls(spark, d):
    return java.calls(_parsed(spark, d))


def report(spark, d):
    files = _sources(spark, d).select("path", "text").unionByName(spark.createDataFrame(list(BROKEN), "path string, text string"))
    return java.parse_report(java.units(files))


def file_clones(spark, d):
    hashed = _sources(spark, d).select("path", F.md5(T.normalize(F.col("text"), "java")).alias("hash"))
    return U.with_count(hashed, "hash").select("path", "n_same", "is_clone")


def _prints(spark, d):
    parsed = _parsed(spark, d)
    return D.prints_of(java.functions(parsed).withColumn("real", F.lit(True)), java.calls(parsed), CONFIG)


def class_clones(spark, d):
    """Classes of one linked print, names and values left out: first, n_classes."""
    return _prints(spark, d).groupBy("print").agg(F.min("class_id").alias("first"), F.count("*").alias("n_classes")).select("first", "n_classes")


def detect(spark, d):
    """Brands whose class another brand released first, by part number."""
    files = _sources(spark, d).select("path", "owner", "p_partkey")
    prints = _prints(spark, d).withColumn("path", F.regexp_replace("class_id", "#[^#]*$", ""))
    at = prints.select("class_id", "path").join(files, "path")
    classes = at.select("class_id", F.col("owner").alias("component"), F.col("owner").alias("group_id"), F.col("owner").alias("artifact_id"), F.col("p_partkey").alias("version"), "path", F.col("p_partkey").alias("released_at"))
    subjects = prints.join(files, "path").select(F.col("path").alias("subject"), "class_id", "print", "owner")
    return D.detect(subjects, D.reference_index(prints.drop("path"), classes, None, CONFIG), CONFIG)


QUERIES = {"java_functions": functions, "java_calls": calls, "java_parse_report": report, "java_file_clones": file_clones, "java_class_clones": class_clones, "java_detect": detect}
_NAME = "array_to_string(list_transform(string_split(p_name, ' '), lambda w: upper(w[1]) || lower(w[2:])), '')"
_JAVA = f"""java as (select p_brand || '/' || p_partkey || '.java' as path, {_NAME} as name, string_split(p_name, ' ')[1] || 'It' as one, string_split(p_name, ' ')[2] || 'It' as two, p_size % 4 as k, p_size % 3 as m, p_brand, p_partkey from part)"""
ORACLE = {
    "java_functions": f"with {_JAVA} select path, name as class_name, one as fn_name, 0 as pos, 1 as loc, cast(1 + k as int) as cc, cast(null as varchar) as error from java union all select path, name, two, 1, 1, 1, null from java",
    "java_calls": f"with {_JAVA} select path || '#' || name as class_id, 0 as caller, 1 as callee, cast(1 as bigint) as n from java where m > 0 union all select path || '#' || name, 1, 0, 1 from java where m = 2",
    "java_parse_report": "select count(*) + 2 as n_files, cast(2 as bigint) as n_errors from part",
    "java_file_clones": f"with {_JAVA} select path, count(*) over (partition by name, one, two, k, m) as n_same, count(*) over (partition by name, one, two, k, m) > 1 as is_clone from java",
    "java_class_clones": f"with {_JAVA} select min(path || '#' || name) as first, count(*) as n_classes from java group by k, m",
    "java_detect": f"with {_JAVA}, origin as (select k, m, arg_min(p_brand, p_partkey) as group_id from java group by all) select path as subject, group_id, cast(1 as bigint) as n_evidence from java join origin using (k, m) where p_brand <> group_id",
}
