"""Granularity study and similar functions on the given tables."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions import text as T
from ..operators import extract as E
from ..operators import similar as S
from ..operators import study as G
from ..operators import units as U
from ..plans.store import Store
from . import sql as Q
from .tables import table

MIN_CHARS = 20


def _lines(spark: SparkSession, d: str, *more: str) -> DataFrame:
    return U.lines(table(spark, d, "documents", "doc_id", "source", "text"), "doc_id", "source", *more)


def file_clones(spark, d):
    return G.file_clones(table(spark, d, "documents", "doc_id", "text"), "doc_id").select("doc_id", "hash", "n_same", "is_clone")


def line_clones(spark, d):
    return G.unit_clones(_lines(spark, d), "line", "doc_id", "pos").select("doc_id", "pos", "n_same", "is_clone")


def _sentences(spark, d):
    return U.sentences(_lines(spark, d), "doc_id", "source", "pos")


def sentence_clones(spark, d):
    return G.unit_clones(_sentences(spark, d), "sentence", "doc_id").groupBy("doc_id").agg(F.count("*").alias("n_units"), F.count_if("is_clone").alias("n_clones"))


def turn_clones(spark, d):
    turns = table(spark, d, "conversations", "conv_id", "turn", "text").where("text <> ''")
    return G.unit_clones(turns, "text", "conv_id", "turn").select("conv_id", "turn", "n_same", "is_clone")


def para_clones(spark, d):
    paras = U.paragraphs(table(spark, d, "pages", "page_id", "url", "html"))
    return G.unit_clones(paras, "para", "page_id", "host", "pos").select("page_id", "host", "pos", "n_same", "is_clone")


def granularity(spark, d):
    docs = table(spark, d, "documents", "doc_id", "text").where("text <> ''")
    hashed = lambda df, c: df.select(F.md5(T.normalize(F.col(c))).alias("hash"))
    return G.granularity_report(hashed(docs, "text"), hashed(_lines(spark, d), "line"), hashed(_sentences(spark, d), "sentence"))


def multi_class_files(spark, d):
    turns = G.multi_class_share(table(spark, d, "conversations", "conv_id"), "conv_id").withColumn("kind", F.lit("turn"))
    return turns.unionByName(G.multi_class_share(_lines(spark, d), "doc_id").withColumn("kind", F.lit("line")))


def partial_copies(spark, d):
    docs = table(spark, d, "documents", "doc_id", "text")
    files = docs.select("doc_id", F.md5(T.normalize(F.col("text"))).alias("hash"))
    units = _lines(spark, d).select("doc_id", F.md5(T.normalize(F.col("line"))).alias("hash"))
    return G.partial_copies(files, units, "doc_id")


def _sets(spark, d, least=None):
    """Shingle sets of lines; a line goes by document and position, whatever their sizes."""
    lines = _lines(spark, d) if least is None else _lines(spark, d).where(F.length("line") > least)
    return S.shingled(lines.select(F.struct("doc_id", "pos", "source").alias("id"), "line"), "id", "line")


def _similar(join):
    def run(spark, d):
        groups = S.classes(_sets(spark, d), Store(spark, "similar"))
        pairs = S.named(join(groups), groups)
        return pairs.select(F.col("a.doc_id").alias("a_doc"), F.col("a.pos").alias("a_pos"), F.col("b.doc_id").alias("b_doc"), F.col("b.pos").alias("b_pos"), "sim")

    return run


def minhash_recall(spark, d):
    """One row: pairs of the exact join, false ones of the banded join, and whether it finds 95 in 100."""
    store = Store(spark, "recall")
    groups = S.classes(_sets(spark, d), store)
    exact = store.keep(S.prefix_join(groups), "exact")
    store.free()
    found = store.keep(S.minhash_join(groups), "found")
    store.free()
    both = exact.select("a", "b", F.lit(1).alias("e")).join(found.select("a", "b", F.lit(1).alias("f")), ["a", "b"], "full")
    counts = both.agg(F.count("e").alias("n_exact"), (F.count("*") - F.count("e")).alias("n_false"), F.count_if(F.col("e").isNotNull() & F.col("f").isNotNull()).alias("hit"))
    return counts.select("n_exact", "n_false", (F.col("hit") * 100 >= F.col("n_exact") * 95).alias("enough"))


def similar_units(spark, d):
    store = Store(spark, "similar")
    sets, groups = S.classes_of(_sets(spark, d), store)
    units = S.unit_links(sets, groups, S.prefix_join(groups))
    return units.select("id.doc_id", "id.pos", F.col("first.doc_id").alias("rep_doc"), F.col("first.pos").alias("rep_pos"), "n_links")


def function_clone_rate(spark, d):
    return similar_units(spark, d).agg(F.count("*").alias("n_units"), F.count_if(F.col("n_links") > 0).alias("n_clones")).withColumn("rate", F.round(F.try_divide("n_clones", "n_units"), 6))


def _functions(spark, d):
    units = _lines(spark, d).where(F.length("line") > MIN_CHARS)
    return units.select(F.col("doc_id").alias("class_id"), F.col("source").alias("owner"), F.col("pos").alias("fn"), F.md5(T.normalize(F.col("line"))).alias("hash"))


def _similar_functions(spark, d):
    """Functions by their class of equal shingle sets, and which classes are similar."""
    store = Store(spark, "functions")
    # made once, as shingling costs more than what is written
    sets, groups = S.classes_of(_sets(spark, d, MIN_CHARS), store)
    name = lambda c: F.concat_ws(":", f"{c}.doc_id", f"{c}.pos")
    pairs = store.keep(S.named(S.prefix_join(groups), groups).select(name("a").alias("hash"), name("b").alias("other"), "sim"), "pairs")
    near = pairs.unionByName(pairs.select(F.col("other").alias("hash"), F.col("hash").alias("other"), "sim"))
    near = near.unionByName(groups.select(name("first").alias("hash"), name("first").alias("other"), F.lit(1.0).alias("sim")))
    functions = sets.select("id", "h1", "h2").join(groups.select("h1", "h2", "first"), ["h1", "h2"]).select(F.col("id.doc_id").alias("class_id"), F.col("id.source").alias("owner"), F.col("id.pos").alias("fn"), name("first").alias("hash"))
    functions, near = store.keep(functions, "named"), store.keep(near, "near")
    store.drop("members", "classes", "pairs")
    store.free()
    return functions, near


def _calls(spark, d):
    return E.call_edges(E.functions_of(_lines(spark, d).withColumnRenamed("doc_id", "class_id")))


def _associated(scope):
    return lambda spark, d: G.associated_pct(_calls(spark, d), _functions(spark, d), scope)


def associated_similar(spark, d):
    functions, near = _similar_functions(spark, d)
    return G.associated_pct(_calls(spark, d), functions, "class", near.select("hash", "other"))


def _associated_hist(of):
    def run(spark, d):
        return G.pct_histogram(of(spark, d).groupBy("class_id", "caller").agg(F.max("pct").alias("pct")))

    return run


def _conjugate(variant):
    return lambda spark, d: G.conjugate_pct(_functions(spark, d), variant)


def _conjugate_similar(variant):
    return lambda spark, d: G.conjugate_pct_similar(*_similar_functions(spark, d), variant)


def conjugate_hist(spark, d):
    return G.pct_histogram(G.conjugate_pct(_functions(spark, d), "matching"))


def _prints(spark, d, least):
    long = F.length("sentence") > least
    docs = E.additive_print(_sentences(spark, d).where(long), "sentence", F.col("doc_id").alias("subject"))
    items = U.sentences(U.lines(table(spark, d, "benchmark", "item_id", "text"), "item_id"), "item_id").where(long)
    return docs, E.additive_print(items, "sentence", F.col("item_id").alias("component"))


def overlap_raw(spark, d):
    return G.overlap_ratio(*_prints(spark, d, 0), denominator="subject")


def overlap_nontrivial(spark, d):
    return G.overlap_ratio(*_prints(spark, d, MIN_CHARS), denominator="subject")


QUERIES = {
    "study_file_clones": file_clones, "study_line_clones": line_clones, "study_sentence_clones": sentence_clones, "study_granularity": granularity,
    "study_turn_clones": turn_clones, "study_para_clones": para_clones, "study_multi_class_files": multi_class_files, "study_partial_copies": partial_copies,
    "study_similar_pairs_index": _similar(S.index_join), "study_similar_pairs_prefix": _similar(S.prefix_join), "study_similar_pairs_minhash": _similar(S.minhash_join), "study_minhash_recall": minhash_recall,
    "study_similar_units": similar_units, "study_function_clone_rate": function_clone_rate,
    "study_associated": _associated("class"), "study_associated_project": _associated("project"), "study_associated_anywhere": _associated("anywhere"), "study_associated_similar": associated_similar,
    "study_associated_hist": _associated_hist(_associated("class")), "study_associated_similar_hist": _associated_hist(associated_similar),
    "study_conjugate_similar_pairs": _conjugate_similar("pairs"), "study_conjugate_similar_functions": _conjugate_similar("functions"), "study_conjugate_similar_matching": _conjugate_similar("matching"), "study_conjugate_pairs": _conjugate("pairs"), "study_conjugate_functions": _conjugate("functions"),
    "study_conjugate_matching": _conjugate("matching"), "study_conjugate_hist": conjugate_hist, "study_overlap_raw": overlap_raw, "study_overlap_nontrivial": overlap_nontrivial,
}

_L, _S = f"with {Q.LINES}", f"with {Q.LINES}, {Q.SENTENCES}"
_SAME = "count(*) over (partition by hash) as n_same, count(*) over (partition by hash) > 1 as is_clone"
_RATE = lambda level, src, col: f"select '{level}' as level, cast(sum(n) as bigint) as n_units, cast(coalesce(sum(case when n > 1 then n end), 0) as bigint) as n_clones, round(sum(case when n > 1 then n else 0 end) / sum(n), 6) as rate from (select count(*) as n from {src} where {col} <> '' group by {Q.NORMAL(col)})"
_FNS = f"fx as (select doc_id as class_id, source as owner, pos as fn, {Q.NORMAL('line')} as hash from lines where length(line) > {MIN_CHARS})"
_ASSOC = f"""with recursive {Q.LINES}, {Q.CALLS}, {_FNS},
edge as (select c.doc_id as class_id, c.caller, c.callee, x.owner, x.hash as ch, y.hash as eh from calls c join fx x on x.class_id = c.doc_id and x.fn = c.caller join fx y on y.class_id = c.doc_id and y.fn = c.callee where c.caller <> c.callee),
spots as (select distinct hash, class_id as other, owner as other_owner from fx),
beside as (select e.*, s.other from edge e join spots s on s.hash = e.ch and s.other_owner <> e.owner),
assoc as (select b.class_id, b.caller, b.other, count(*) as n_callees, count(s.hash) as n_cloned, round(count(s.hash) / count(*), 6) as pct from beside b left join spots s on s.hash = b.eh and s.other = b.other group by all)"""
_SIMILAR = f"""{Q.shingled(f'length(line) > {MIN_CHARS}')}, fs as materialized (select doc_id as class_id, source as owner, pos as fn, rep as hash from sets join groups using (g)),
near as materialized (select a as hash, b as other from similar_pairs union all select b, a from similar_pairs union all select rep, rep from groups)"""
_ASSOC_PROJECT = _ASSOC.replace("select distinct hash, class_id as other, owner as other_owner from fx", "select distinct hash, owner as other, owner as other_owner from fx")
_ASSOC_ANY = f"""with recursive {Q.LINES}, {Q.CALLS}, {_FNS}, owners as (select distinct hash, owner from fx),
edge as (select c.doc_id as class_id, c.caller, c.callee, exists (select 1 from owners o where o.hash = x.hash and o.owner <> x.owner) as there, exists (select 1 from owners o where o.hash = y.hash and o.owner <> x.owner) as hit from calls c join fx x on x.class_id = c.doc_id and x.fn = c.caller join fx y on y.class_id = c.doc_id and y.fn = c.callee where c.caller <> c.callee)
select class_id, caller, cast(null as varchar) as other, count(*) as n_callees, count(case when hit then 1 end) as n_cloned, round(count(case when hit then 1 end) / count(*), 6) as pct from edge where there group by class_id, caller"""
_ASSOC_SIMILAR = f"""with recursive {Q.LINES}, {Q.CALLS}, {_SIMILAR},
edge as (select c.doc_id as class_id, c.caller, c.callee, x.owner, x.hash as ch, y.hash as eh from calls c join fs x on x.class_id = c.doc_id and x.fn = c.caller join fs y on y.class_id = c.doc_id and y.fn = c.callee where c.caller <> c.callee),
spots as materialized (select distinct n.hash, f.class_id as other, f.owner as other_owner from fs f join near n on n.other = f.hash),
beside as (select e.*, s.other from edge e join spots s on s.hash = e.ch and s.other_owner <> e.owner),
assoc as (select b.class_id, b.caller, b.other, count(*) as n_callees, count(s.hash) as n_cloned, round(count(s.hash) / count(*), 6) as pct from beside b left join spots s on s.hash = b.eh and s.other = b.other group by all)"""


def _conj_similar_sql(variant: str) -> str:
    top = "select class_a, class_b, any_value(n_pairs) as n_pairs, cast(2 * sum(ca * cb) as bigint) as n_conj from conj group by class_a, class_b"
    if variant == "functions":
        top = "select class_a, class_b, any_value(n_pairs) as n_pairs, cast(sum(c) as bigint) as n_conj from (select distinct class_a, class_b, n_pairs, 'a' as side, ha as h, ca as c from conj union all select distinct class_a, class_b, n_pairs, 'b', hb, cb from conj) group by class_a, class_b"
    return f"""with {Q.LINES}, {_SIMILAR}, sizes as (select class_id, count(*) as size from fs group by all), held as materialized (select class_id, owner, hash, count(*) as c from fs group by all),
shared2 as materialized (select x.class_id as class_a, y.class_id as class_b, x.hash as ha, y.hash as hb, x.c as ca, y.c as cb from held x join near n on n.hash = x.hash join held y on y.hash = n.other where x.class_id < y.class_id and x.owner <> y.owner),
counted as (select *, cast(sum(ca * cb) over (partition by class_a, class_b) as bigint) as n_pairs, sum(cb) over (partition by class_a, class_b, ha) as na, sum(ca) over (partition by class_a, class_b, hb) as nb from shared2),
conj as materialized (select * from counted where n_pairs > 1 and n_pairs - na - nb + 1 >= 1)
select class_a, class_b, n_pairs, n_conj, round(n_conj / (x.size + y.size), 6) as pct from ({top}) join sizes x on x.class_id = class_a join sizes y on y.class_id = class_b where n_conj > 0"""


_HIST = "select cast(floor(least(pct, 1.0) * 10 + 1e-9) as int) as bin, count(*) as n from {} group by 1"


def _conj_sql(variant: str) -> str:
    top = {"pairs": "2 * sum(case when n_pairs - ca - cb + 1 >= 1 then ca * cb else 0 end)", "functions": "sum(case when n_pairs - ca - cb + 1 >= 1 then ca + cb else 0 end)", "matching": "case when sum(least(ca, cb)) >= 2 then 2 * sum(least(ca, cb)) else 0 end"}[variant]
    return f"""with {Q.LINES}, {_FNS}, sizes as (select class_id, count(*) as size from fx group by all), held as (select class_id, owner, hash, count(*) as c from fx group by all),
shared as (select a.class_id as class_a, b.class_id as class_b, a.c as ca, b.c as cb, sum(a.c * b.c) over (partition by a.class_id, b.class_id) as n_pairs from held a join held b on a.hash = b.hash and a.class_id < b.class_id and a.owner <> b.owner),
per as (select class_a, class_b, cast(any_value(n_pairs) as bigint) as n_pairs, cast({top} as bigint) as n_conj from shared where n_pairs > 1 group by class_a, class_b),
conj as (select class_a, class_b, n_pairs, n_conj, round(n_conj / (x.size + y.size), 6) as pct from per join sizes x on x.class_id = class_a join sizes y on y.class_id = class_b where n_conj > 0)"""


def _overlap_sql(least: int) -> str:
    return f"""{_S}, {Q.B_SENTENCES}, s as (select distinct doc_id as subject, {Q.bag('s')} as print from sents where length(s) > {least}), c as (select distinct item_id as component, {Q.bag('s')} as print from b_sents where length(s) > {least})
select subject, component, count(*) as shared, round(count(*) / any_value(size), 6) as ratio from s join c using (print) join (select subject, count(*) as size from s group by all) using (subject) group by subject, component"""


ORACLE = {
    "study_file_clones": f"select doc_id, hash, {_SAME} from (select doc_id, {Q.NORMAL('text')} as hash from documents where length(text) > 0)",
    "study_line_clones": f"{_L} select doc_id, pos, {_SAME} from (select *, {Q.NORMAL('line')} as hash from lines)",
    "study_sentence_clones": f"{_S} select doc_id, count(*) as n_units, count(case when n_same > 1 then 1 end) as n_clones from (select doc_id, count(*) over (partition by {Q.NORMAL('s')}) as n_same from sents) group by all",
    "study_granularity": f"{_S} {_RATE('file', 'documents', 'text')} union all {_RATE('class', 'lines', 'line')} union all {_RATE('function', 'sents', 's')}",
    "study_turn_clones": f"select conv_id, turn, {_SAME} from (select conv_id, turn, {Q.NORMAL('text')} as hash from conversations where text <> '')",
    "study_para_clones": rf"""select page_id, host, pos, {_SAME} from (select page_id, host, pos, {Q.NORMAL('para')} as hash from (select page_id, regexp_extract(url, '^[a-z]+://([^/:?#]+)', 1) as host, unnest(f) as para, unnest(range(len(f))) as pos from (select *, regexp_extract_all(html, '<p(?: [^>]*)?>([^<]*)</p>', 1) as f from pages)) where para <> '')""",
    "study_multi_class_files": f"{_L} select count(*) as n_files, count(case when n > 1 then 1 end) as n_multi, round(count(case when n > 1 then 1 end) / count(*), 6) as share, kind from (select 'turn' as kind, count(*) as n from conversations group by conv_id union all select 'line', count(*) from lines group by doc_id) group by kind",
    "study_partial_copies": f"{_L}, t as (select l.doc_id, {Q.NORMAL('l.line')} as unit, {Q.NORMAL('d.text')} as fh from lines l join documents d using (doc_id)) select doc_id, count(*) as n_partial from t where unit in (select unit from t group by unit having min(fh) <> max(fh)) group by doc_id",
    "study_similar_pairs_index": f"{_L}, {Q.SHINGLED} select {Q.PAIR}, sim from similar_pairs",
    "study_similar_pairs_prefix": f"{_L}, {Q.SHINGLED} select {Q.PAIR}, sim from similar_pairs",
    "study_minhash_recall": f"{_L}, {Q.SHINGLED} select count(*) as n_exact, cast(0 as bigint) as n_false, true as enough from similar_pairs",
    "study_associated_project": f"{_ASSOC_PROJECT} select * from assoc",
    "study_associated_anywhere": _ASSOC_ANY,
    "study_associated_similar": f"{_ASSOC_SIMILAR} select * from assoc",
    "study_associated_similar_hist": f"{_ASSOC_SIMILAR}, best as (select class_id, caller, max(pct) as pct from assoc group by all) {_HIST.format('best')}",
    "study_conjugate_similar_pairs": _conj_similar_sql("pairs"),
    "study_conjugate_similar_functions": _conj_similar_sql("functions"),
    "study_similar_units": f"{_L}, {Q.SHINGLED}, more as (select x as rep, sum(n_members) as linked from (select a as x, b as y from similar_pairs union all select b, a from similar_pairs) join groups on groups.rep = y group by x) select s.doc_id, s.pos, cast(g.rep // 4294967296 as bigint) as rep_doc, cast(g.rep % 4294967296 as int) as rep_pos, cast(g.n_members - 1 + coalesce(m.linked, 0) as bigint) as n_links from sets s join groups g on g.g = s.g left join more m on m.rep = g.rep",
    "study_function_clone_rate": f"{_L}, {Q.SHINGLED}, touched as (select a as rep from similar_pairs union select b from similar_pairs) select cast(sum(n_members) as bigint) as n_units, cast(sum(case when n_members > 1 or t.rep is not null then n_members else 0 end) as bigint) as n_clones, round(sum(case when n_members > 1 or t.rep is not null then n_members else 0 end) / sum(n_members), 6) as rate from groups g left join touched t on t.rep = g.rep",
    "study_associated": f"{_ASSOC} select * from assoc",
    "study_associated_hist": f"{_ASSOC}, best as (select class_id, caller, max(pct) as pct from assoc group by all) {_HIST.format('best')}",
    "study_conjugate_pairs": _conj_sql("pairs") + " select * from conj",
    "study_conjugate_functions": _conj_sql("functions") + " select * from conj",
    "study_conjugate_matching": _conj_sql("matching") + " select * from conj",
    "study_conjugate_hist": _conj_sql("matching") + " " + _HIST.format("conj"),
    "study_overlap_raw": _overlap_sql(0),
    "study_overlap_nontrivial": _overlap_sql(MIN_CHARS),
}
