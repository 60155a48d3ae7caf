"""Extraction, refinement, recognition, baselines, ground truth and research questions on the given tables."""

from __future__ import annotations

from dataclasses import replace

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions import complexity as C
from ..functions import hashing as H
from ..functions import text as T
from ..operators import baselines as B
from ..operators import detect as D
from ..operators import extract as E
from ..operators import measures as M
from ..operators import recognize as N
from ..operators import refine as R
from ..operators import truth as G
from ..operators import units as U
from ..plans.store import Store
from ..sources.index_store import load_index, write_index
from . import sql as Q
from .tables import table

#: sentence length above which a unit is no trivial one, and the grid that accuracy is reported on
MIN_CHARS, LENGTHS, THETAS = 20, (0, 10, 20, 30, 60), (0.05, 0.1, 0.15, 0.2, 0.25, 0.5, 0.9)


def _lines(spark: SparkSession, d: str) -> DataFrame:
    return U.lines(table(spark, d, "documents", "doc_id", "source", "lang", "text"), "doc_id", "source", "lang")


def _class_lines(spark, d):
    return _lines(spark, d).withColumnRenamed("doc_id", "class_id")


def _functions(spark, d):
    return E.functions_of(_class_lines(spark, d))


def calls(spark, d):
    return E.call_edges(_functions(spark, d))


def _kept(spark, d):
    store = Store(spark, "extract")
    fns = store.keep(_functions(spark, d), "functions")
    return fns, store.keep(E.break_cycles(store.keep(E.call_edges(fns), "calls"), fns), "acyclic")


def acyclic(spark, d):
    return _kept(spark, d)[1]


def linked(spark, d):
    return E.link(*_kept(spark, d))


def linked_body(spark, d):
    """One placeholder for a recursive function's body, whatever the number of its calls."""
    return E.link(*_kept(spark, d), recursion="body")


def print_all_roots(spark, d):
    fns, calls_ = _kept(spark, d)
    return E.class_print(E.link(fns, calls_), calls_, "all")


def print_additive(spark, d):
    fns, calls_ = _kept(spark, d)
    return E.class_print(E.link(fns, calls_), calls_)


def print_mixed(spark, d):
    return E.mixed_print(_class_lines(spark, d))


def collisions(spark, d):
    """Documents beside themselves with their lines joined: the bag of labels is the same, the structure is not."""
    docs = table(spark, d, "documents", "doc_id", "text")
    joined = docs.select((-F.col("doc_id") - 1).alias("doc_id"), F.translate("text", "\n", " ").alias("text"))
    lines = U.lines(docs.unionByName(joined), F.col("doc_id").alias("class_id"))
    bag = E.functions_of(lines).groupBy("class_id").agg(H.total(F.col("own")).alias("print"))
    return E.collision_audit(bag, E.mixed_print(lines))


def print_shape(spark, d):
    return E.additive_print(_class_lines(spark, d), "line", "class_id", "pos", level="shape")


def _per_line(value):
    return lambda spark, d: _lines(spark, d).select("doc_id", "pos", F.round(value(F.col("line")), 6).alias("value"))


def trivial(spark, d):
    return R.drop_trivial(_lines(spark, d), "line").select("doc_id", "pos")


def empty(spark, d):
    docs = table(spark, d, "documents", "doc_id")
    return R.drop_empty(docs, _lines(spark, d), "doc_id")


def structural(spark, d):
    return table(spark, d, "part", "p_partkey", "p_name").select("p_partkey", R.is_structural(F.col("p_name")).alias("is_structural"))


def tests(spark, d):
    pages = table(spark, d, "pages", "page_id", "url").select("page_id", U.path("url").alias("path"))
    return pages.select("page_id", R.is_test(F.col("path")).alias("is_test"), R.is_test(F.col("path"), "literal").alias("is_test_literal"))


def funnel(spark, d):
    classes = table(spark, d, "documents", "doc_id", "source").select("doc_id", F.concat_ws("/", "source", "doc_id").alias("path"))
    return R.drop_supporting(classes, _lines(spark, d), "doc_id", "path", "line")[1]


def _released(spark, d, how="mono"):
    docs = table(spark, d, "documents", "doc_id", "source", "lang")
    when = table(spark, d, "events", F.col("event_id").alias("doc_id"), F.col("ts").alias("released_at")) if how == "mono" else table(spark, d, "orders", F.col("o_orderkey").alias("doc_id"), F.col("o_orderdate").alias("released_at"))
    return docs.join(when, "doc_id").select("doc_id", F.col("source").alias("group_id"), F.concat_ws(":", "source", "lang").alias("artifact_id"), F.col("doc_id").alias("version"), "released_at")


def _features(spark, d, how="mono"):
    prints = E.additive_print(_lines(spark, d), "line", "doc_id")
    return prints.join(_released(spark, d, how), "doc_id")


def _uses_text(spark, d):
    lines = _lines(spark, d).where(F.length("line") > MIN_CHARS).select("doc_id", "source", "line").distinct()
    timed = lines.join(_released(spark, d).select("doc_id", "released_at"), "doc_id")
    first = timed.groupBy("source", "line").agg(F.min(F.struct("released_at", "doc_id")).alias("f")).select("source", "line", F.col("f.doc_id").alias("src"))
    return timed.join(first, ["source", "line"]).where("doc_id <> src").select(F.col("source").alias("component"), "src", F.col("doc_id").alias("dst")).distinct()


def _uses_trade(spark, d):
    item = table(spark, d, "lineitem", "l_orderkey", "l_partkey").join(table(spark, d, "part", F.col("p_partkey").alias("l_partkey"), "p_brand"), "l_partkey").distinct()
    a, b = item.select("p_brand", "l_orderkey", F.col("l_partkey").alias("src")), item.select("p_brand", "l_orderkey", F.col("l_partkey").alias("dst"))
    return a.join(b, ["p_brand", "l_orderkey"]).where("src < dst").select(F.col("p_brand").alias("component"), "src", "dst").distinct()  # an order has at most seven lines


def _uses_links(spark, d):
    pages = table(spark, d, "pages", "page_id", "url", "html").select(U.host("url").alias("component"), F.col("page_id").alias("dst"), F.explode(F.regexp_extract_all("html", F.lit(r'href="([^"]+)"'), F.lit(1))).alias("src"))
    return pages.where("src like '/%'").select("component", "src", "dst").distinct()


def _ranked(edges):
    return lambda spark, d: R.pagerank(edges(spark, d)).select("component", "node", F.round("rank", 9).alias("rank"))


def percentile(spark, d):
    return R.centrality_percentile(R.pagerank(_uses_trade(spark, d))).select("component", "node", F.round("pct", 9).alias("pct"))


def central_half(spark, d):
    return R.keep_central(R.centrality_percentile(R.pagerank(_uses_trade(spark, d)))).groupBy("component").agg(F.count("*").alias("n_kept"))


def cutoff(spark, d):
    reused = table(spark, d, "part", F.col("p_brand").alias("component"), F.col("p_partkey").alias("node"), "p_size").where("p_size >= 25")
    return R.calibrate_cutoff(R.centrality_percentile(R.pagerank(_uses_trade(spark, d))), reused)


def merge_group(spark, d):
    merged = R.merge_in_group(_features(spark, d))
    text = F.array_join(F.transform("av", lambda v: F.concat(v["artifact_id"], F.lit("@"), v["version"].cast("string"))), ",")
    return merged.select("group_id", "print", F.size("av").cast("long").alias("n_av"), "first_at", F.md5(text).alias("av_digest"))


def _origin(how):
    def run(spark, d):
        per = _features(spark, d, how).groupBy("group_id", "print").agg(F.min("released_at").alias("first_at"))
        return R.origin_only(per)

    return run


def origin_flip(spark, d):
    seen = table(spark, d, "labels", "doc_id").distinct().withColumn("seen", F.lit(True))
    return R.origin_flip(_features(spark, d).join(seen, "doc_id", "left"), F.col("seen").isNotNull())


def _sentences(spark, d, least=MIN_CHARS):
    return U.sentences(_lines(spark, d), "doc_id", "source", "pos").where(F.length("sentence") > least)


def _items(spark, d, least=MIN_CHARS):
    return U.sentences(U.lines(table(spark, d, "benchmark", "item_id", "text"), "item_id"), "item_id").where(F.length("sentence") > least)


def _subject_prints(spark, d, least=MIN_CHARS):
    return E.additive_print(_sentences(spark, d, least), "sentence", F.col("doc_id").alias("subject"), F.col("doc_id").alias("class_id"))


def _component_prints(spark, d, least=MIN_CHARS):
    return E.additive_print(_items(spark, d, least), "sentence", F.col("item_id").alias("component"))


def _item_index(spark, d):
    """Each print's first item: items are released in the order of their ids."""
    return _component_prints(spark, d).groupBy("print").agg(F.min("component").alias("group_id"))


def match(spark, d):
    return N.match(_subject_prints(spark, d), _item_index(spark, d)).select("subject", "print", "group_id").distinct()


def flagship(spark, d):
    """Sentence prints of the benchmark, each kept for its first item, matched in all documents: one piece of evidence is reuse."""
    evidence = N.match(_subject_prints(spark, d), _item_index(spark, d), verdict_only=True)
    return N.recognize(evidence).withColumnRenamed("group_id", "component")


def _doc_evidence(spark, d):
    index = R.build_index(_features(spark, d))
    subject = E.additive_print(_lines(spark, d).where(F.length("line") > MIN_CHARS), "line", F.col("source").alias("subject"), F.col("doc_id").alias("class_id"))
    return N.match(subject, index, exclude_self=True)


def no_self(spark, d):
    return N.recognize(_doc_evidence(spark, d))


def versions(spark, d):
    return N.version_candidates(_doc_evidence(spark, d))


def outdated(spark, d):
    return N.outdated_copies(versions(spark, d), _released(spark, d))


def false_positives(spark, d):
    texts = table(spark, d, "documents", F.col("doc_id").alias("class_id"), "text")
    return N.explain_false_positives(N.match(_subject_prints(spark, d), _item_index(spark, d)), texts)


def reason(spark, d):
    comp = _component_prints(spark, d).distinct()
    evidence = _subject_prints(spark, d).join(comp, "print").select("subject", "component", "print")
    sizes = comp.groupBy("component").agg(F.count("*").alias("size"))
    # an item nobody released: the document that first holds it has no label
    first = _truth(spark, d).groupBy("component").agg(F.min("subject").alias("doc_id"))
    unpublished = first.join(table(spark, d, "labels", "doc_id"), "doc_id", "left_anti").select("component")
    return N.reuse_reason(evidence, sizes, truth_licence(spark, d), unpublished)


def top_evidence(spark, d):
    return N.top_evidence(flagship(spark, d), 1, "component").select("subject", "component", "n_evidence")


def function_ratio(spark, d):
    return B.function_ratio(_subject_prints(spark, d), _component_prints(spark, d))


def function_ratio_similar(spark, d):
    subject = _sentences(spark, d).select(F.col("doc_id").alias("subject"), F.col("sentence").alias("text"))
    return B.function_ratio_similar(subject, _items(spark, d).select(F.col("item_id").alias("component"), F.col("sentence").alias("text")))


def theta_sweep(spark, d):
    """Accuracy at every threshold, without any filter of trivial units."""
    found = B.theta_sweep(_subject_prints(spark, d, 0), _component_prints(spark, d, 0), list(THETAS))
    return M.prf(found, _truth(spark, d), ["theta"], spark.createDataFrame([(x,) for x in THETAS], "theta double"))


def function_db(spark, d):
    return B.build_function_db(E.additive_print(_sentences(spark, d), "sentence", F.col("source").alias("group_id")))


def file_hash(spark, d):
    docs = table(spark, d, "documents", F.col("source").alias("subject"), "text").where("text <> ''").select("subject", F.md5(T.normalize(F.col("text"))).alias("hash"))
    return B.file_hash_match(docs, docs.withColumnRenamed("subject", "component")).where("subject < component")


def file_path(spark, d):
    pages = table(spark, d, "pages", "url").select(U.host("url").alias("host"), U.path("url").alias("path"))
    return B.file_path_match(pages, "host", "path", 1)


MANIFESTS = (
    (-1, "<project><dependencies><dependency><groupId>org.a</groupId><artifactId>x</artifactId><version>1</version></dependency><dependency><groupId>org.b</groupId><artifactId>y</artifactId></dependency></dependencies></project>"),
    (-2, "<project><dependencies><dependency><groupId>org.c</groupId>"),
    (-3, "<project></project>"),
)


def manifest(spark, d):
    """A manifest per order, its lines as dependencies, beside broken and empty ones with negative ids."""
    tag = lambda name, v: F.concat(F.lit(f"<{name}>"), v, F.lit(f"</{name}>"))
    item = table(spark, d, "lineitem", "l_orderkey", "l_partkey", "l_linenumber", "l_linestatus").join(table(spark, d, "part", F.col("p_partkey").alias("l_partkey"), "p_brand"), "l_partkey")
    version = F.when(F.col("l_linestatus") == "F", tag("version", F.col("l_linenumber").cast("string"))).otherwise("")
    one = tag("dependency", F.concat(tag("groupId", F.col("p_brand")), tag("artifactId", F.concat(F.lit("p"), "l_partkey")), version))
    orders = item.groupBy(F.col("l_orderkey").alias("subject")).agg(F.concat(F.lit("<project><dependencies>"), F.array_join(F.collect_list(one), ""), F.lit("</dependencies></project>")).alias("xml"))
    return B.declared_from_manifest(orders.unionByName(spark.createDataFrame(list(MANIFESTS), "subject long, xml string")))


def _truth(spark, d):
    return B.contains_truth(table(spark, d, "documents", "doc_id", "text"), table(spark, d, "benchmark", "item_id", "text"), "doc_id", "item_id").select(F.col("doc_id").alias("subject"), F.col("item_id").alias("component"))


def truth_path(spark, d):
    pages = table(spark, d, "pages", "page_id", "url").select("page_id", U.path("url").alias("path"), G.vendor(U.host("url")).alias("owner"))
    return G.path_evidence(pages, "path", F.col("owner")).select("page_id", "owner", "in_group", "vendor")


#: change notes of our own, as the documents hold none; negative ids
NOTES = (
    (-1, "This class is based on the work of the tide group."), (-2, "Copied from the lamp project, then changed."), (-3, "A modified version of the grid reader."),
    (-4, "Written here from the start."), (-5, "copy from an old mail list"), (-6, "Forked from harbour."), (-7, "This package is based on the work done by the north team."), (-8, None),
)


def _noted(spark, d):
    notes = spark.createDataFrame(list(NOTES), "doc_id long, text string")
    return table(spark, d, "documents", "doc_id", "text").unionByName(notes)


def truth_phrase(spark, d):
    return G.phrase_evidence(_noted(spark, d), "doc_id", "text")


def truth_licence(spark, d):
    docs = table(spark, d, "documents", F.col("doc_id").alias("subject"), F.col("text").alias("subject_text"))
    # the licensed side is the document that first holds the passage, its copies are the subjects
    pairs = _truth(spark, d)
    first = pairs.groupBy("component").agg(F.min("subject").alias("origin"))
    held = pairs.join(first, "component").where("subject <> origin").join(docs, "subject")
    origin = docs.select(F.col("subject").alias("origin"), F.col("subject_text").alias("component_text"))
    return G.licence_evidence(held.join(origin, "origin"))


def licence_stripped(spark, d):
    """Copies of licensed passages that say nothing of a licence, among the pairs that the prints found."""
    evidence = flagship(spark, d).select("subject", F.col("subject").alias("class_id"), "component")
    texts = table(spark, d, "documents", F.col("doc_id").alias("class_id"), "text")
    first = _truth(spark, d).groupBy("component").agg(F.min("subject").alias("class_id"))
    origin = first.join(texts, "class_id").select("component", "text")
    return G.licence_stripped(evidence, texts, origin)


def truth_author(spark, d):
    docs = table(spark, d, "documents", F.col("doc_id").alias("subject"), G.affiliations(F.col("text")).alias("subject_authors")).where(F.size("subject_authors") > 0)
    each = docs.select("subject", F.explode("subject_authors").alias("author"))
    first = each.groupBy("author").agg(F.min("subject").alias("component"))
    pairs = each.join(first, "author").where("subject <> component").select("subject", "component").distinct()
    both = pairs.join(docs, "subject").join(docs.select(F.col("subject").alias("component"), F.col("subject_authors").alias("component_authors")), "component")
    return G.author_evidence(both)


def truth_union(spark, d):
    """Pairs by any rule; a path or a phrase tells of a copy in a page or text, not of whom, so its component is the vendor's name or null."""
    as_text = lambda df: df.select(F.col("subject").cast("string").alias("subject"), F.col("component").cast("string").alias("component"))
    path = truth_path(spark, d).where("in_group or vendor").select(F.concat(F.lit("page "), "page_id").alias("subject"), F.col("owner").alias("component"))
    phrase = truth_phrase(spark, d).select(F.col("doc_id").alias("subject"), F.col("phrase").alias("component"))
    return G.truth_from_rules(contains=as_text(_truth(spark, d)), licence=as_text(truth_licence(spark, d)), author=as_text(truth_author(spark, d)), path=path, phrase=as_text(phrase))


def curated(spark, d):
    """Components of part names without platform variants; subjects are sources with enough good documents and no copied first document."""
    part = table(spark, d, "part", "p_partkey", F.concat_ws("-", F.translate("p_name", " ", "-"), F.element_at(F.array(*[F.lit(x) for x in ("core", "win", "darwin-x64", "window", "linux", "wing", "arm64", "api")]), (F.col("p_size") % 8 + 1).cast("int"))).alias("artifact_id"))
    return G.curate_components(part)


def curated_subjects(spark, d):
    docs = table(spark, d, "documents", "doc_id", "source", F.md5(T.normalize(F.col("text"))).alias("hash"))
    first = docs.groupBy("hash").agg(F.min("doc_id").alias("first"))
    labels = table(spark, d, "labels", "doc_id", "quality").groupBy("doc_id").agg(F.max("quality").alias("quality"))
    own = docs.join(first, "hash").join(labels, "doc_id", "left")
    per = own.groupBy("source").agg(F.coalesce(F.sum("quality"), F.lit(0)).alias("stars"), (F.count_if(F.col("doc_id") != F.col("first")) * 5 > F.count("*")).alias("is_fork"), (F.count("quality") > 0).alias("builds"))
    return G.curate_subjects(per).select("source", "stars")


def _grid(spark, d):
    """Predictions of both methods under every filter, from one match: method, setting, subject, component.

    A print counts at a length if some unit of the subject and some unit of the component that have it are longer; so the longest of each is kept.
    """
    store = Store(spark, "grid")
    longest = lambda df, side: df.groupBy(side, "print").agg(F.max("k").alias("k"))
    s = longest(E.additive_print(_sentences(spark, d, -1), "sentence", F.col("doc_id").alias("subject"), F.length("sentence").alias("k")), "subject")
    c = store.keep(longest(E.additive_print(_items(spark, d, -1), "sentence", F.col("item_id").alias("component"), F.length("sentence").alias("k")), "component"), "c")
    over = lambda what: [F.count_if(F.col(what) > n).alias(f"n{n}") for n in LENGTHS]
    sizes = c.groupBy("component").agg(*over("k")).select("component", F.array(*[f"n{n}" for n in LENGTHS]).alias("sizes"))
    both = s.withColumnRenamed("k", "ks").join(c, "print").select("subject", "component", F.least("ks", "k").alias("k"))
    shared = both.groupBy("subject", "component").agg(*over("k")).select("subject", "component", F.array(*[f"n{n}" for n in LENGTHS]).alias("shared"))
    each = shared.join(sizes, "component").select("subject", "component", F.posexplode(F.arrays_zip("shared", "sizes")).alias("at", "v"))
    each = each.where("v.shared > 0").withColumn("least", F.element_at(F.array(*[F.lit(n) for n in LENGTHS]), F.col("at") + 1))
    each = store.keep(each.select("subject", "component", "least", F.round(F.col("v.shared") / F.col("v.sizes"), 6).alias("ratio")), "ratios")
    setting = F.concat(F.lit("length > "), F.col("least").cast("string"))
    prints = each.select(F.lit("class print").alias("method"), setting.alias("setting"), "subject", "component")
    thetas = each.withColumn("t", F.explode(F.filter(F.array(*[F.lit(x) for x in THETAS]), lambda x: F.col("ratio") >= x)))
    rates = thetas.select(F.lit("function ratio").alias("method"), F.concat(setting, F.lit(", theta "), F.format_number("t", 2)).alias("setting"), "subject", "component")
    return prints.unionByName(rates)


def _settings(spark):
    rows = [("class print", f"length > {n}") for n in LENGTHS] + [("function ratio", f"length > {n}, theta {x:.2f}") for n in LENGTHS for x in THETAS] + [("linked class print", "full")]
    return spark.createDataFrame(rows, "method string, setting string")


def accuracy(spark, d):
    linked_ = _variants(spark, d, "full").select(F.lit("linked class print").alias("method"), F.col("config").alias("setting"), "subject", "component")
    return M.prf(_grid(spark, d).unionByName(linked_), _truth(spark, d), ["method", "setting"], _settings(spark))


def accuracy_macro(spark, d):
    return M.macro_prf(_grid(spark, d), _truth(spark, d), ["method", "setting"])


#: the detector on passages: a line is a class, its sentences are functions; prose has a length in place of the complexity
PASSAGE = D.DetectConfig(min_unit_chars=MIN_CHARS)
VARIANTS = {
    "full": PASSAGE, "no linking": replace(PASSAGE, linking=False), "no trivial filter": replace(PASSAGE, min_unit_chars=None, complexity_cut=None),
    "no centrality": replace(PASSAGE, central_cut=None), "no origin": replace(PASSAGE, origin=False),
}


def _line_units(lines, key):
    """Lines as classes, and their sentences as functions: class_id, pos, line."""
    named = lines.select(F.concat_ws(":", key, "pos").alias("class_id"), "line")
    return U.sentences(named, "class_id").withColumnsRenamed({"s_pos": "pos", "sentence": "line"})


def _variants(spark, d, *names):
    """Pairs that the detector finds under each of ``VARIANTS``, or those named: config, subject, component."""
    store = Store(spark, "variants")
    items = U.lines(table(spark, d, "benchmark", "item_id", "text"), "item_id")
    subject, reference = _line_units(_lines(spark, d), "doc_id"), _line_units(items, "item_id")
    name = lambda c: F.concat_ws(":", "class_id", c)
    # a line of an item uses those whose first word it holds; items are released in the order of their ids
    uses = E.call_edges(E.functions_of(items.withColumnRenamed("item_id", "class_id"))).where("caller <> callee")
    uses = store.keep(uses.select(F.col("class_id").alias("component"), name("callee").alias("src"), name("caller").alias("dst")), "uses")
    at = items.select(F.concat_ws(":", "item_id", "pos").alias("class_id"), F.col("item_id").alias("component"), F.col("item_id").alias("group_id"), F.col("item_id").alias("artifact_id"), F.col("pos").alias("version"), F.concat_ws("/", "item_id", F.regexp_extract("line", T.WORD, 1)).alias("path"), F.col("item_id").alias("released_at"))
    made, out = {}, None
    for label, config in VARIANTS.items():
        if names and label not in names:
            continue
        kind = (config.linking, config.min_unit_chars)
        if kind not in made:
            one, two = (store.keep(D.class_prints(units, config), f"{side}-{len(made)}") for side, units in (("s", subject), ("r", reference)))
            made[kind] = one.select(F.split("class_id", ":")[0].cast("long").alias("subject"), "class_id", "print"), two
        prints, known = made[kind]
        verdict = D.detect(prints, D.reference_index(known, at, uses, config), config)
        part = verdict.select(F.lit(label).alias("config"), "subject", F.col("group_id").alias("component"))
        out = part if out is None else out.unionByName(part)
    return out


def detect_full(spark, d):
    """The detector on documents: a document is a class, its lines are functions, its source is the group; sources that copied it from the first are found."""
    store, config = Store(spark, "detect"), D.DetectConfig(exclude_self=True)
    lines = _class_lines(spark, d)
    prints = store.keep(D.class_prints(lines.select("class_id", "pos", "line"), config), "prints")
    first = F.regexp_extract("text", T.WORD, 1)
    path = table(spark, d, "documents", F.col("doc_id").alias("class_id"), F.col("source").alias("component"), F.concat_ws("/", "source", first).alias("path"))
    classes = path.join(_released(spark, d).withColumnRenamed("doc_id", "class_id"), "class_id")
    write_index(D.reference_index(prints, store.keep(classes, "classes"), store.keep(_uses_text(spark, d), "uses"), config), store.path("index"), config)
    index = load_index(spark, store.path("index"), config)
    subjects = prints.join(path.select("class_id", F.col("component").alias("owner")), "class_id").withColumn("subject", F.col("class_id"))
    return D.detect(subjects, index, config)


def ablation(spark, d):
    """The detector with one step left out at a time, and prints of units of another size."""
    store = Store(spark, "ablation")
    sent = _subject_prints(spark, d).join(_component_prints(spark, d).distinct(), "print").select("subject", "component")
    items = U.lines(table(spark, d, "benchmark", "item_id", "text"), "item_id")
    line = E.additive_print(_lines(spark, d), "line", F.col("doc_id").alias("subject")).join(E.additive_print(items, "line", F.col("item_id").alias("component")), "print").select("subject", "component")
    whole = lambda name, key, as_: table(spark, d, name, F.col(key).alias(as_), F.md5(T.normalize(F.lower("text"))).alias("hash")).where("hash is not null")
    file = whole("documents", "doc_id", "subject").join(whole("benchmark", "item_id", "component"), "hash").select("subject", "component")
    every = _variants(spark, d)
    names = [*VARIANTS, "sentences", "sentences, first origin", "unlinked lines", "whole texts"]
    for name, df in zip(names[len(VARIANTS) :], (sent, flagship(spark, d).select("subject", "component"), line, file), strict=True):
        every = every.unionByName(df.distinct().select(F.lit(name).alias("config"), "subject", "component"))
    return M.prf(store.keep(every, "all"), _truth(spark, d), ["config"], spark.createDataFrame([(n,) for n in names], "config string"))


def size_profile(spark, d):
    docs = table(spark, d, "documents", "doc_id", F.length("text").alias("size"))
    work = _sentences(spark, d, 0).groupBy("doc_id").agg(F.count("*").alias("work"))
    return M.size_profile(docs.join(work, "doc_id", "left").withColumn("work", F.coalesce("work", F.lit(0)).cast("double")), "size", "work", [100, 1000, 5000, 20000])


def _cc_pm(spark, d):
    """Found: sentence evidence. Declared: whole items in documents labelled as good."""
    cc = flagship(spark, d).select("subject", "component")
    pm = _truth(spark, d).join(table(spark, d, "labels", F.col("doc_id").alias("subject"), "quality").where("quality = 1").select("subject").distinct(), "subject", "left_semi")
    return cc, pm


def prevalence(spark, d):
    return M.prevalence(_cc_pm(spark, d)[0], table(spark, d, "documents", F.col("doc_id").alias("subject")))


def correlation(spark, d):
    docs = table(spark, d, "documents", F.col("doc_id").alias("subject"), F.length("text").alias("size"))
    stars = table(spark, d, "labels", F.col("doc_id").alias("subject"), "quality").groupBy("subject").agg(F.sum("quality").alias("stars"))
    return M.correlation(docs.join(stars, "subject", "left").withColumn("stars", F.coalesce("stars", F.lit(0))), _cc_pm(spark, d)[0], "stars", "size")


def improvement(spark, d):
    return M.improvement_rate(*_cc_pm(spark, d))


def _trade_sets(spark, d):
    item = table(spark, d, "lineitem", "l_orderkey", "l_partkey", "l_linestatus").join(table(spark, d, "part", F.col("p_partkey").alias("l_partkey"), F.col("p_brand").alias("component")), "l_partkey")
    item = item.join(table(spark, d, "orders", F.col("o_orderkey").alias("l_orderkey"), F.col("o_custkey").alias("subject")), "l_orderkey")
    pick = lambda s: item.where(F.col("l_linestatus") == s).select("subject", "component").distinct()
    return pick("O"), pick("F")


def improvement_trade(spark, d):
    return M.improvement_rate(*_trade_sets(spark, d))


def means_trade(spark, d):
    return M.mean_rates(improvement_trade(spark, d))


def correlation_trade(spark, d):
    subjects = table(spark, d, "customer", F.col("c_custkey").alias("subject"), F.col("c_acctbal").alias("balance"))
    orders = table(spark, d, "orders", F.col("o_custkey").alias("subject")).groupBy("subject").agg(F.count("*").alias("n_orders"))
    return M.correlation(subjects.join(orders, "subject", "left").withColumn("n_orders", F.coalesce("n_orders", F.lit(0))), _trade_sets(spark, d)[0], "balance", "n_orders")


def prevalence_trade(spark, d):
    return M.prevalence(_trade_sets(spark, d)[0], table(spark, d, "customer", F.col("c_custkey").alias("subject")))


def stat_sample_size(spark, d):
    lines = U.lines(table(spark, d, "documents", "source", "text"), "source")
    return R.sample_sizes(lines, "source", F.length("line") > MIN_CHARS, [(0.95, 0.05), (0.99, 0.05), (0.95, 0.03)])


def stat_sample(spark, d):
    return R.sample_exact(_lines(spark, d).select(F.concat_ws(":", "doc_id", "pos").alias("id")), "id", R.sample_size(), 7)


def missing_source(spark, d):
    seen = table(spark, d, "labels", "doc_id").distinct().withColumn("s", F.lit(1))
    return table(spark, d, "documents", "doc_id").join(seen, "doc_id", "left").agg(F.count("*").alias("n_versions"), F.count("s").alias("n_with_source")).withColumn("missing_share", F.round(1 - F.col("n_with_source") / F.col("n_versions"), 6))


QUERIES = {
    "extract_calls": calls, "extract_acyclic_calls": acyclic, "extract_linked": linked, "extract_linked_body": linked_body, "extract_print_all_roots": print_all_roots, "extract_print_additive": print_additive, "extract_print_mixed": print_mixed, "extract_print_shape": print_shape, "extract_collisions": collisions,
    "refine_complexity": _per_line(C.prose_complexity), "refine_complexity_linear": _per_line(lambda c: C.prose_complexity(c, "linear")), "refine_mi": _per_line(lambda c: C.maintainability(C.prose_complexity(c))),
    "refine_trivial": trivial, "refine_empty": empty, "refine_structural": structural, "refine_tests": tests, "refine_funnel": funnel,
    "refine_uses_text": _uses_text, "refine_uses_trade": _uses_trade, "refine_uses_links": _uses_links, "refine_pagerank_text": _ranked(_uses_text), "refine_pagerank_trade": _ranked(_uses_trade),
    "refine_percentile": percentile, "refine_central_half": central_half, "refine_cutoff_calibration": cutoff,
    "refine_merge_group": merge_group, "refine_origin_mono": _origin("mono"), "refine_origin_shuffled": _origin("shuffled"), "refine_origin_flip": origin_flip, "refine_missing_source": missing_source,
    "detect_match": match, "detect_flagship": flagship, "detect_full": detect_full, "detect_no_self": no_self, "detect_versions": versions, "detect_outdated": outdated, "detect_false_positives": false_positives, "detect_reuse_reason": reason, "detect_top_evidence": top_evidence,
    "base_function_ratio": function_ratio, "base_function_ratio_similar": function_ratio_similar, "base_theta_sweep": theta_sweep, "base_function_db": function_db, "base_file_hash": file_hash, "base_path": file_path, "base_manifest": manifest,
    "truth_contains": _truth, "truth_path": truth_path, "truth_phrase": truth_phrase, "truth_licence": truth_licence, "truth_author": truth_author, "truth_union": truth_union, "truth_licence_stripped": licence_stripped, "truth_curated_components": curated, "truth_curated_subjects": curated_subjects,
    "rq1_accuracy": accuracy, "rq1_accuracy_macro": accuracy_macro, "rq1_ablation": ablation, "rq2_size_profile": size_profile, "rq3_prevalence": prevalence, "rq3_correlation": correlation, "rq3_improvement": improvement,
    "rq3_improvement_trade": improvement_trade, "rq3_means_trade": means_trade, "rq3_correlation_trade": correlation_trade, "rq3_prevalence_trade": prevalence_trade, "stat_sample_size": stat_sample_size, "stat_sample": stat_sample,
}

_L, _S = f"with {Q.LINES}", f"with {Q.LINES}, {Q.SENTENCES}, {Q.B_SENTENCES}"
_X = f"with recursive {Q.LINES}, {Q.CALLS}, {Q.ACYCLIC}"
_MIXED = f"""node as (select doc_id, {Q.h("'FUNCTION:' || cast(" + Q.mod("coalesce(list_sum(list_transform(list_filter(string_split_regex(lower(line), '" + Q.END + "'), lambda s: trim(s) <> ''), lambda s: cast(" + Q.h("'STATEMENT:' || cast(" + Q.bag("s") + " as varchar)") + " as hugeint))), 0)") + " as varchar)")} as node from lines),
mixed as (select doc_id as class_id, {Q.h("'CLASS:' || cast(" + Q.mod("sum(node)") + " as varchar)")} as print from node group by doc_id)"""
_REL = lambda how: (
    "released as (select d.doc_id, d.source as group_id, d.source || ':' || d.lang as artifact_id, e.ts as released_at from documents d join events e on e.event_id = d.doc_id)" if how == "mono" else "released as (select d.doc_id, d.source as group_id, d.source || ':' || d.lang as artifact_id, o.o_orderdate as released_at from documents d join orders o on o.o_orderkey = d.doc_id)"
)
_FEAT = lambda how: f"{Q.LINES}, {_REL(how)}, feats as (select l.doc_id, {Q.bag('lower(line)')} as print, r.group_id, r.artifact_id, r.released_at from lines l join released r using (doc_id))"
_ORIGIN = "select print, arg_min(group_id, (first_at is null, first_at, group_id)) as group_id, min(first_at) as first_at, count(*) as n_groups from (select group_id, print, min(released_at) as first_at from {} group by all) group by print"
_UT = f"{Q.LINES}, {_REL('mono')}, tl as (select distinct l.doc_id, l.source, l.line, r.released_at from lines l join released r using (doc_id) where length(l.line) > {MIN_CHARS}), uses_text as (select distinct t.source as component, f.src, t.doc_id as dst from tl t join (select source, line, arg_min(doc_id, (released_at, doc_id)) as src from tl group by all) f using (source, line) where t.doc_id <> f.src)"
_TR = "it as (select distinct l_orderkey, l_partkey, p_brand from lineitem join part on p_partkey = l_partkey), uses_trade as (select distinct a.p_brand as component, a.l_partkey as src, b.l_partkey as dst from it a join it b on a.p_brand = b.p_brand and a.l_orderkey = b.l_orderkey and a.l_partkey < b.l_partkey)"
_PCT = f"with {_TR}, {Q.pagerank('uses_trade')}, pcts as (select component, node, percent_rank() over (partition by component order by round(rank, 12) desc) as pct from r20)"
_SP = lambda least: f"s as (select distinct doc_id as subject, {Q.bag('s')} as print from sents where length(s) > {least}), c as (select distinct item_id as component, {Q.bag('s')} as print from b_sents where length(s) > {least})"
_FLAG = f"{_SP(MIN_CHARS)}, idx as (select print, min(component) as component from c group by print), flag as (select subject, component, count(distinct print) as n_evidence from s join idx using (print) group by all)"
_TRUTH = "truth as (select d.doc_id as subject, b.item_id as component from documents d join benchmark b on b.text <> '' and contains(d.text, b.text))"
_DOC = f"{_FEAT('mono')}, origin as ({_ORIGIN.format('feats')}), subj as (select distinct source as subject, {Q.bag('lower(line)')} as print from lines where length(line) > {MIN_CHARS}), ev as (select s.subject, s.print, o.group_id from subj s join origin o using (print) where s.subject <> o.group_id)"
_VER = f"{_DOC}, sup as (select e.subject, e.group_id, f.artifact_id, f.doc_id as version, count(distinct e.print) as n_support from ev e join feats f on f.print = e.print and f.group_id = e.group_id group by all), vers as (select subject, group_id, artifact_id, version, n_support from sup qualify n_support = max(n_support) over (partition by subject, group_id))"
_PRF = lambda key, src, every: f"select {key}, count(t.subject) as tp, count(p.subject) - count(t.subject) as fp, any_value(z.n) - count(t.subject) as fn, round(count(t.subject) / nullif(count(p.subject), 0), 6) as precision, round(count(t.subject) / nullif(any_value(z.n), 0), 6) as recall, round(2 * count(t.subject) / nullif(count(p.subject) + any_value(z.n), 0), 6) as f1 from {every} left join (select distinct * from {src}) p using ({key}) left join truth t on t.subject = p.subject and t.component = p.component cross join (select count(*) as n from truth) z group by {key}"
_NAMES = lambda rows, key: "(select * from (values " + ", ".join("(" + ", ".join(f"'{v}'" for v in r) + ")" for r in rows) + f") as names({key}))"
_SETTINGS = _NAMES([("class print", f"length > {n}") for n in LENGTHS] + [("function ratio", f"length > {n}, theta {x:.2f}") for n in LENGTHS for x in THETAS] + [("linked class print", "full")], "method, setting")
_GRID = " union all ".join(
    [f"select 'class print' as method, 'length > {n}' as setting, subject, component from rr where n = {n}" for n in LENGTHS] + [f"select 'function ratio', 'length > {n}, theta {x:.2f}', subject, component from rr where n = {n} and ratio >= {x}" for n in LENGTHS for x in THETAS]
)
_GRID = f"grid as (select distinct * from ({_GRID}))"
_RR = f"sl as (select doc_id as subject, {Q.bag('s')} as print, length(s) as k from sents), cl as (select item_id as component, {Q.bag('s')} as print, length(s) as k from b_sents), ns as (select unnest({list(LENGTHS)}) as n), sd as (select distinct n, subject, print from sl join ns on k > n), cd as (select distinct n, component, print from cl join ns on k > n), rr as (select sd.n, subject, component, round(count(*) / any_value(z.size), 6) as ratio from sd join cd on cd.n = sd.n and cd.print = sd.print join (select n as zn, component as zc, count(*) as size from cd group by all) z on z.zn = sd.n and z.zc = component group by sd.n, subject, component)"
_LINEPAIR = f"select distinct l.doc_id as subject, b.item_id as component from lines l join b_lines b on {Q.bag('lower(l.line)')} = {Q.bag('lower(b.line)')}"
_IR = lambda cc, pm: f"select subject, n_cc, n_pm, n_new, n_cc - n_new as n_both, round(100 * case when n_pm = 0 then 1.0 else n_new / n_pm end, 6) as ir, round(100 * case when n_pm > 0 then (n_cc - n_new) / n_pm end, 6) as dr from (select subject, count(c) as n_cc, count(p) as n_pm, count(case when c = 1 and p is null then 1 end) as n_new from (select subject, component, 1 as c from {cc}) full join (select subject, component, 1 as p from {pm}) using (subject, component) group by subject) where n_cc > 0"
_TS = "tt as (select distinct o_custkey as subject, p_brand as component, l_linestatus as st from lineitem join part on p_partkey = l_partkey join orders on o_orderkey = l_orderkey), cct as (select subject, component from tt where st = 'O'), pmt as (select subject, component from tt where st = 'F')"
_STRONG = "case when abs(r) < 0.3 then 'weak' when abs(r) <= 0.6 then 'moderate' when abs(r) >= 0.8 then 'strong' else 'unnamed' end as strength"
_LIC = "regexp_matches(lower({}), 'licen[sc]e|copyright|all rights reserved')"
_LICENCE = f"licence as (select distinct t.subject, t.component from truth t join (select component, min(subject) as origin from truth group by all) f using (component) join documents d on d.doc_id = t.subject join documents o on o.doc_id = f.origin where t.subject <> f.origin and {_LIC.format('o.text')} and not {_LIC.format('d.text')})"
_AUTHOR = r"authors as (select distinct doc_id, unnest(regexp_extract_all(text, '[\w.]+@([\w.]+)', 1)) as author from documents), author as (select distinct a.doc_id as subject, f.component from authors a join (select author, min(doc_id) as component from authors group by all) f using (author) where a.doc_id <> f.component)"
_NW = lambda x: f"list_filter(string_split(lower(regexp_replace(regexp_replace({x}, '([a-z0-9])([A-Z])', '\\1 \\2', 'g'), '[^A-Za-z0-9]+', ' ', 'g')), ' '), lambda w: w <> '')"
_CX = Q.complexity("line")
_PARTS = "list_filter(string_split_regex(regexp_extract(url, '^[a-z]+://[^/?#]+([^?#]*)', 1), '[/.]'), lambda p: p <> '')"
_SHAPE = "case when regexp_matches(t, '^[0-9]+$') then 'NUM' when regexp_matches(t, '^[A-Z]') then 'CAP' when regexp_matches(t, '^\\w') then 'WORD' else t end"

_NOTED = "noted as (select doc_id, text from documents union all select * from (values " + ", ".join(f"({k}, {'null' if v is None else chr(39) + v + chr(39)})" for k, v in NOTES) + ") n(doc_id, text))"
_PHRASE = f"phrase as (select doc_id, phrase from (select doc_id, regexp_extract(lower(text), '({'|'.join(G.PHRASES)})', 1) as phrase from noted) where phrase <> '')"
_PATH = """path as (select page_id, owner, contains(lower(path || '/'), lower('/' || replace(owner, '.', '/') || '/')) as in_group, len(list_intersect(string_split(lower(path), '/'), ['shared', 'ext', 'jre'])) > 0 as vendor
from (select page_id, path, coalesce(hs[-3], hs[-2], host) as owner from (select page_id, regexp_extract(url, '^[a-z]+://[^/?#]+([^?#]*)', 1) as path, regexp_extract(url, '^[a-z]+://([^/:?#]+)', 1) as host, string_split(regexp_extract(url, '^[a-z]+://([^/:?#]+)', 1), '.') as hs from pages)))"""
_UNPUBLISHED = "unpublished as (select component from (select component, min(subject) as origin from truth group by all) where origin not in (select doc_id from labels where doc_id is not null))"
_STRUCT = lambda x: f"coalesce(list_contains({list(R.STRUCTURAL)}, {_NW(x)}[-1]), false)"
_TEST = lambda x: f"len(list_filter(list_filter(string_split_regex({x}, '[/.]'), lambda p: p <> ''), lambda p: coalesce({_NW('p')}[1] in ('test', 'tests'), false) or coalesce({_NW('p')}[-1] in ('test', 'tests'), false))) > 0"
_LAST = "string_split(path, '/')[-1]"
_UNITS = lambda name, src: f"{name} as materialized (select * from (select doc_id || ':' || pos as doc_id, unnest(range(len(p))) as pos, lower(trim(unnest(p))) as line from (select doc_id, pos, string_split_regex(line, '{Q.END}') as p from {src})) where line <> '')"


def _side(k: int, real: str, linking: bool, central: bool = True) -> str:
    """Prints of both sides under one way of extracting, and the reference's central classes."""
    return f"""{Q.detector(f's{k}_', 'su', real, linking)}, {Q.detector(f'r{k}_', 'ru', real, linking)},
c{k} as materialized (select cls.component, cls.class_id as node from cls where class_id in (select doc_id from r{k}_prints) and not {_STRUCT(_LAST)} and not {_TEST('path')}),
u{k} as (select component, src, dst from uses where src in (select node from c{k}) and dst in (select node from c{k})),
{Q.pagerank(f'u{k}', nodes=f'c{k}', pre=f'k{k}')}, {Q.central(f'k{k}')}"""


def _found(label: str, k: int, central: bool = True, origin: bool = True) -> str:
    kept = f"k{k}central" if central else f"c{k}"
    index = f"select p.print, c.component from r{k}_prints p join {kept} c on c.node = p.doc_id"
    if origin:
        index = f"select print, min(component) as component from ({index}) group by print"
    return f"select distinct '{label}' as config, cast(split_part(s.doc_id, ':', 1) as bigint) as subject, i.component from s{k}_prints s join ({index}) i using (print)"


_VARIANTS = f"""bl as materialized (select * from (select item_id as doc_id, unnest(string_split(text, chr(10))) as line, unnest(range(len(string_split(text, chr(10))))) as pos from benchmark) where line <> ''),
{_UNITS('su', 'lines')}, {_UNITS('ru', 'bl')}, {Q.calls('b', 'bl')},
uses as materialized (select doc_id as component, doc_id || ':' || callee as src, doc_id || ':' || caller as dst from bcalls where caller <> callee),
cls as materialized (select doc_id || ':' || pos as class_id, doc_id as component, doc_id || '/' || regexp_extract(line, '{Q.WORD}') as path from bl),
{_side(1, f'length(line) > {MIN_CHARS}', True)}, {_side(2, f'length(line) > {MIN_CHARS}', False)}, {_side(3, 'true', True)},
variants as materialized ({_found('full', 1)} union all {_found('no linking', 2)} union all {_found('no trivial filter', 3)} union all {_found('no centrality', 1, central=False)} union all {_found('no origin', 1, origin=False)})"""
_SR = f"with recursive {Q.LINES}, {Q.SENTENCES}, {Q.B_SENTENCES}"
_WHOLE = lambda t: f"md5(regexp_replace(lower({t}.text), '\\s+', '', 'g'))"
_ABLATION = f"""every as (select * from variants union all select distinct 'sentences' as config, subject, component from s join c using (print) union all select 'sentences, first origin', subject, component from flag
 union all select 'unlinked lines', subject, component from ({_LINEPAIR}) union all select distinct 'whole texts', d.doc_id, b.item_id from documents d join benchmark b on {_WHOLE('d')} = {_WHOLE('b')})"""
_ABLATED = _NAMES([(n,) for n in (*VARIANTS, "sentences", "sentences, first origin", "unlinked lines", "whole texts")], "config")
_DETECT = f"""with recursive {_UT}, {Q.detector('d_', 'lines', f'round({Q.complexity("line")}, 6) >= 60')},
cls as materialized (select d.doc_id, d.source as component, concat_ws('/', d.source, regexp_extract(d.text, '{Q.WORD}')) as path, r.released_at from documents d join released r using (doc_id) where d.doc_id in (select doc_id from d_prints)),
c as materialized (select component, doc_id as node, released_at from cls where not {_STRUCT(_LAST)} and not {_TEST('path')}),
u as materialized (select component, src, dst from uses_text where src in (select node from c) and dst in (select node from c)), {Q.pagerank('u', nodes='c', pre='k')}, {Q.central('k')},
idx as (select print, arg_min(component, (first_at is null, first_at, component)) as group_id from (select p.print, c.component, min(c.released_at) as first_at from d_prints p join c on c.node = p.doc_id join kcentral z on z.node = c.node and z.component = c.component group by all) group by print)
select p.doc_id as subject, i.group_id, count(distinct p.print) as n_evidence from d_prints p join documents d using (doc_id) join idx i using (print) where d.source <> i.group_id group by all"""

ORACLE = {
    "detect_full": _DETECT,
    "extract_linked_body": f"{_X}, {Q.linked(recursion='body')} select doc_id as class_id, fn, linked from linked",
    "extract_print_all_roots": f"{_X}, {Q.LINKED} select doc_id as class_id, {Q.CLASS_PRINT} as print from linked group by doc_id",
    "truth_licence_stripped": f"{_S}, {_FLAG}, {_TRUTH} select distinct f.subject, f.component from flag f join (select component, min(subject) as origin from truth group by all) o using (component) join documents d on d.doc_id = f.subject join documents x on x.doc_id = o.origin where {_LIC.format('x.text')} and not {_LIC.format('d.text')}",
    "truth_curated_components": f"select * from (select p_partkey, replace(p_name, ' ', '-') || '-' || ['core', 'win', 'darwin-x64', 'window', 'linux', 'wing', 'arm64', 'api'][p_size % 8 + 1] as artifact_id from part) where not regexp_matches(lower(artifact_id), '[-_.]({'|'.join(G.PLATFORMS)})([-_.]|$)')",
    "truth_curated_subjects": f"with own as (select d.source, d.doc_id, l.quality, min(d.doc_id) over (partition by {Q.NORMAL('d.text')}) as first from documents d left join (select doc_id, max(quality) as quality from labels group by all) l using (doc_id)) select source, cast(coalesce(sum(quality), 0) as bigint) as stars from own group by source having coalesce(sum(quality), 0) >= 20 and count(quality) > 0 and not count(case when doc_id <> first then 1 end) * 5 > count(*)",
    "rq1_accuracy_macro": f"""{_S}, {_TRUTH}, {_RR}, {_GRID}, sz as (select subject, count(*) as n_t from truth group by all), per as (select method, setting, g.subject, count(*) as n_p, count(t.subject) as hit, any_value(sz.n_t) as n_t from grid g left join truth t on t.subject = g.subject and t.component = g.component left join sz on sz.subject = g.subject group by all)
select method, setting, round(avg(hit / n_p), 6) as precision, round(coalesce(sum(hit / n_t), 0) / (select count(*) from sz), 6) as recall, round(coalesce(sum(2 * hit / (n_p + n_t)), 0) / (select count(*) from sz), 6) as f1 from per group by method, setting""",
    "extract_calls": f"with recursive {Q.LINES}, {Q.CALLS} select doc_id as class_id, caller, callee, n from calls",
    "extract_acyclic_calls": f"{_X} select doc_id as class_id, caller, callee, n, status from acyclic",
    "extract_linked": f"{_X}, {Q.LINKED} select doc_id as class_id, fn, linked from linked",
    "extract_print_additive": f"{_X}, {Q.LINKED} select doc_id as class_id, {Q.mod('sum(cast(linked as hugeint) + ' + Q.h(chr(39) + 'FUNCTION' + chr(39)) + ') + ' + Q.h(chr(39) + 'CLASS' + chr(39)))} as print from linked l where not exists (select 1 from kept k where k.doc_id = l.doc_id and k.callee = l.fn) group by doc_id",
    "extract_print_mixed": f"{_L}, {_MIXED} select * from mixed",
    "extract_print_shape": f"{_L} select doc_id as class_id, pos, {Q.bag('line').replace('md5(t)', 'md5(' + _SHAPE + ')')} as print from lines",
    "extract_collisions": f"with lines as (select * from (select doc_id, unnest(string_split(text, chr(10))) as line from (select doc_id, text from documents union all select -doc_id - 1, replace(text, chr(10), ' ') from documents)) where line <> ''), {_MIXED}, bags as (select doc_id as class_id, {Q.mod('sum(own)')} as print from (select doc_id, {Q.bag('lower(line)')} as own from lines) group by doc_id) select b.print, count(*) as n_classes, count(distinct m.print) as n_mixed from bags b join mixed m using (class_id) group by b.print having count(distinct m.print) > 1",
    "refine_complexity": f"{_L} select doc_id, pos, round({_CX}, 6) as value from lines",
    "refine_complexity_linear": f"{_L} select doc_id, pos, round({Q.complexity('line', 'linear')}, 6) as value from lines",
    "refine_mi": f"{_L} select doc_id, pos, round(171.0 - {_CX}, 6) as value from lines",
    "refine_trivial": f"{_L} select doc_id, pos from lines where round({_CX}, 6) >= 60",
    "refine_empty": f"{_L} select distinct doc_id from lines",
    "refine_structural": f"select p_partkey, coalesce(list_contains({list(R.STRUCTURAL)}, {_NW('p_name')}[-1]), false) as is_structural from part",
    "refine_tests": f"select page_id, len(list_filter({_PARTS}, lambda p: coalesce({_NW('p')}[1] in ('test', 'tests'), false) or coalesce({_NW('p')}[-1] in ('test', 'tests'), false))) > 0 as is_test, len(list_filter({_PARTS}, lambda p: regexp_matches(lower(p), '^test|tests?$'))) > 0 as is_test_literal from pages",
    "refine_funnel": f"{_L}, big as (select distinct doc_id from lines where round({_CX}, 6) >= 60) select '0 all' as rule, count(*) as n_left from documents union all select '1 empty', count(distinct doc_id) from lines union all select '2 trivial', count(*) from big union all select '3 structural', count(*) from big union all select '4 tests', count(*) from big",
    "refine_uses_text": f"with {_UT} select * from uses_text",
    "refine_uses_trade": f"with {_TR} select * from uses_trade",
    "refine_uses_links": "select distinct component, src, dst from (select regexp_extract(url, '^[a-z]+://([^/:?#]+)', 1) as component, page_id as dst, unnest(regexp_extract_all(html, 'href=\"([^\"]+)\"', 1)) as src from pages) where src like '/%'",
    "refine_pagerank_text": f"with {_UT}, {Q.pagerank('uses_text')} select component, node, round(rank, 9) as rank from r20",
    "refine_pagerank_trade": f"with {_TR}, {Q.pagerank('uses_trade')} select component, node, round(rank, 9) as rank from r20",
    "refine_percentile": f"{_PCT} select component, node, round(pct, 9) as pct from pcts",
    "refine_central_half": f"{_PCT} select component, count(*) as n_kept from pcts where pct <= 0.5 group by all",
    "refine_cutoff_calibration": f"{_PCT}, hit as (select pct from pcts join part on p_partkey = node and p_brand = component where p_size >= 25) select cast(floor(least(pct, 0.999999) * 10 + 1e-9) as int) as tenth, count(*) as n, (select round(count(case when pct <= 0.5 then 1 end) / count(*), 6) from hit) as share_in from hit group by 1",
    "refine_merge_group": f"with {_FEAT('mono')} select group_id, print, count(*) as n_av, min(released_at) as first_at, md5(string_agg(artifact_id || '@' || doc_id, ',' order by artifact_id, doc_id)) as av_digest from (select group_id, print, artifact_id, doc_id, min(released_at) as released_at from feats group by all) group by group_id, print",
    "refine_origin_mono": f"with {_FEAT('mono')} {_ORIGIN.format('feats')}",
    "refine_origin_shuffled": f"with {_FEAT('shuf')} {_ORIGIN.format('feats')}",
    "refine_origin_flip": f"with {_FEAT('mono')}, a as ({_ORIGIN.format('feats')}), b as ({_ORIGIN.format('(select * from feats where doc_id in (select doc_id from labels))')}) select a.print, a.group_id as true_group, b.group_id as seen_group from a join b using (print) where a.group_id <> b.group_id",
    "refine_missing_source": "select count(*) as n_versions, count(s) as n_with_source, round(1 - count(s) / count(*), 6) as missing_share from documents left join (select distinct doc_id, 1 as s from labels) using (doc_id)",
    "detect_match": f"{_S}, {_FLAG} select distinct subject, print, component as group_id from s join idx using (print)",
    "detect_flagship": f"{_S}, {_FLAG} select * from flag",
    "detect_no_self": f"with {_DOC} select subject, group_id, count(distinct print) as n_evidence from ev group by all",
    "detect_versions": f"with {_VER} select * from vers",
    "detect_outdated": f"with {_VER}, have as (select v.subject, v.group_id, v.artifact_id, max(r.released_at) as copied_at from vers v join released r on r.artifact_id = v.artifact_id and r.doc_id = v.version group by all), newest as (select artifact_id, max(released_at) as newest_at from released group by all) select subject, group_id, artifact_id, copied_at, newest_at, date_diff('day', cast(copied_at as date), cast(newest_at as date)) as days_behind from have join newest using (artifact_id) where newest_at > copied_at",
    "detect_false_positives": f"{_S}, {_FLAG} select distinct s.subject, s.subject as class_id, regexp_matches(lower(d.text), 'generated by|do not edit') as generated, regexp_matches(lower(d.text), 'https?://|stack ?overflow') as from_web from s join idx using (print) join documents d on d.doc_id = s.subject",
    "detect_reuse_reason": f"{_S}, {_SP(MIN_CHARS)}, {_TRUTH}, {_LICENCE}, {_UNPUBLISHED} select p.subject, p.component, share, case when l.subject is not null then 'licence stripped' when u.component is not null then 'off repository' when share >= 1 then 'whole copy' else 'partial copy' end as reason from (select subject, component, round(count(distinct print) / any_value(size), 6) as share from s join c using (print) join (select component, count(*) as size from c group by all) using (component) group by subject, component) p left join licence l on l.subject = p.subject and l.component = p.component left join unpublished u on u.component = p.component",
    "detect_top_evidence": f"{_S}, {_FLAG} select subject, component, n_evidence from flag qualify row_number() over (partition by subject order by n_evidence desc, component) <= 1",
    "base_function_ratio": f"{_S}, {_SP(MIN_CHARS)} select subject, component, count(*) as shared, round(count(*) / any_value(size), 6) as ratio from s join c using (print) join (select component, count(*) as size from c group by all) using (component) group by subject, component having round(count(*) / any_value(size), 6) >= 0.15",
    "base_function_ratio_similar": rf"""{_S}, sw as (select doc_id as subject, regexp_extract_all(s, '{Q.WORD}') as w from sents where length(s) > {MIN_CHARS}), cw as (select item_id as component, regexp_extract_all(s, '{Q.WORD}') as w from b_sents where length(s) > {MIN_CHARS}),
sg as materialized (select distinct subject, {Q.grams('w')} as g from sw where len(w) >= 3), cg as materialized (select distinct component, {Q.grams('w')} as g from cw where len(w) >= 3),
sp as (select g, unnest(g) as x from (select distinct g from sg)), cp as (select g, unnest(g) as x from (select distinct g from cg)),
near as (select sp.g as a, cp.g as b from sp join cp using (x) group by sp.g, cp.g having round(count(*) / (len(sp.g) + len(cp.g) - count(*)), 6) >= 0.7)
select subject, component, count(*) as shared, round(count(*) / any_value(size), 6) as ratio from (select distinct subject, component, cg.g from sg join near on a = sg.g join cg on cg.g = b) join (select component, count(*) as size from cg group by all) using (component) group by subject, component having round(count(*) / any_value(size), 6) >= 0.15""",
    "base_theta_sweep": f"{_S}, {_TRUTH}, {_SP(0)}, r as (select subject, component, round(count(*) / any_value(size), 6) as ratio from s join c using (print) join (select component, count(*) as size from c group by all) using (component) group by subject, component), ths as (select cast(unnest({list(THETAS)}) as double) as theta), found as (select theta, subject, component from r join ths on ratio >= theta) {_PRF('theta', 'found', 'ths')}",
    "base_function_db": f"{_S}, p as (select source as group_id, {Q.bag('s')} as print from sents where length(s) > {MIN_CHARS}) select print, count(distinct group_id) as n_groups, min(group_id) as group_id from p group by print",
    "base_file_hash": f"with f as (select distinct source, {Q.NORMAL('text')} as hash from documents where text <> '') select distinct a.source as subject, b.source as component from f a join f b using (hash) where a.source < b.source",
    "base_path": r"select suffix, count(*) as n_files, count(distinct host) as n_owners from (select regexp_extract(url, '^[a-z]+://([^/:?#]+)', 1) as host, coalesce(list_filter(string_split(lower(regexp_extract(url, '^[a-z]+://[^/?#]+([^?#]*)', 1)), '/'), lambda p: p <> '')[-1], '') as suffix from pages) where suffix <> '' group by suffix having count(distinct host) > 1",
    "base_manifest": "select l_orderkey as subject, p_brand as group_id, 'p' || l_partkey as artifact_id, case when l_linestatus = 'F' then cast(l_linenumber as varchar) end as version, false as malformed from lineitem join part on p_partkey = l_partkey union all select * from (values (-1, 'org.a', 'x', '1', false), (-1, 'org.b', 'y', null, false), (-2, null, null, null, true), (-3, null, null, null, false)) t(subject, group_id, artifact_id, version, malformed)",
    "truth_contains": f"with {_TRUTH} select * from truth",
    "truth_path": f"with {_PATH} select * from path",
    "truth_phrase": f"with {_NOTED}, {_PHRASE} select * from phrase",
    "truth_licence": f"with {_TRUTH}, {_LICENCE} select * from licence",
    "truth_author": f"with {_AUTHOR} select * from author",
    "truth_union": f"with {_TRUTH}, {_LICENCE}, {_AUTHOR}, {_NOTED}, {_PHRASE}, {_PATH} select subject, component, string_agg(rule, ',' order by rule) as rules from (select cast(subject as varchar) as subject, cast(component as varchar) as component, 'contains' as rule from truth union all select cast(subject as varchar), cast(component as varchar), 'licence' from licence union all select cast(subject as varchar), cast(component as varchar), 'author' from author union all select 'page ' || page_id, owner, 'path' from path where in_group or vendor union all select cast(doc_id as varchar), phrase, 'phrase' from phrase) group by subject, component",
    "rq1_accuracy": f"{_SR}, {_TRUTH}, {_RR}, {_GRID}, {_VARIANTS}, preds as (select * from grid union all select 'linked class print', config, subject, component from variants where config = 'full') {_PRF('method, setting', 'preds', _SETTINGS)}",
    "rq1_ablation": f"{_SR}, {_TRUTH}, {_FLAG}, {_VARIANTS}, {_ABLATION} {_PRF('config', 'every', _ABLATED)}",
    "rq2_size_profile": f"{_S}, w as (select d.doc_id, length(d.text) as size, cast(coalesce(k, 0) as double) as work from documents d left join (select doc_id, count(*) as k from sents group by all) using (doc_id)) select cast((size >= 100)::int + (size >= 1000)::int + (size >= 5000)::int + (size >= 20000)::int as int) as bucket, count(*) as n, round(avg(work), 4) as mean_work, round(var_samp(work), 4) as var_work from w group by 1",
    "rq3_prevalence": f"{_S}, {_FLAG} select count(*) as n_subjects, count(k) as n_with, cast(coalesce(sum(k), 0) as bigint) as n_cc, round(count(k) / count(*), 6) as share from documents left join (select subject as doc_id, count(distinct component) as k from flag group by all) using (doc_id)",
    "rq3_correlation": f"{_S}, {_FLAG}, b as (select cast(coalesce(k, 0) as double) as k, length(text) as size, coalesce(stars, 0) as stars from documents left join (select subject as doc_id, count(distinct component) as k from flag group by all) using (doc_id) left join (select doc_id, sum(quality) as stars from labels group by all) using (doc_id)) select attribute, r, {_STRONG} from (select 'stars' as attribute, round(corr(k, stars), 6) as r from b union all select 'size', round(corr(k, size), 6) from b)",
    "rq3_improvement": f"{_S}, {_FLAG}, {_TRUTH}, pm as (select * from truth where subject in (select doc_id from labels where quality = 1)) {_IR('flag', 'pm')}",
    "rq3_improvement_trade": f"with {_TS} {_IR('cct', 'pmt')}",
    "rq3_means_trade": f"with {_TS} select count(*) as n_subjects, round(avg(ir), 4) as mean_ir, round(avg(dr), 4) as mean_dr from ({_IR('cct', 'pmt')})",
    "rq3_correlation_trade": f"with {_TS}, b as (select cast(coalesce(k, 0) as double) as k, c_acctbal as balance, coalesce(n_orders, 0) as n_orders from customer left join (select subject as c_custkey, count(distinct component) as k from cct group by all) using (c_custkey) left join (select o_custkey as c_custkey, count(*) as n_orders from orders group by all) using (c_custkey)) select attribute, r, {_STRONG} from (select 'balance' as attribute, round(corr(k, balance), 6) as r from b union all select 'n_orders', round(corr(k, n_orders), 6) from b)",
    "rq3_prevalence_trade": f"with {_TS} select count(*) as n_subjects, count(k) as n_with, cast(coalesce(sum(k), 0) as bigint) as n_cc, round(count(k) / count(*), 6) as share from customer left join (select subject as c_custkey, count(distinct component) as k from cct group by all) using (c_custkey)",
    "stat_sample_size": f"with {Q.LINES}, per as (select source, count(*) as n_units, count(case when length(line) > {MIN_CHARS} then 1 end) / count(*) as p from lines group by source) select source, n_units, round(p, 6) as share, confidence, margin, cast(ceil(z * z * p * (1 - p) / (margin * margin)) as bigint) as n from per, (values (cast(0.95 as double), cast(0.05 as double), cast(1.96 as double)), (0.99, 0.05, 2.58), (0.95, 0.03, 1.96)) t(confidence, margin, z)",
    "stat_sample": f"{_L} select id from (select doc_id || ':' || pos as id from lines) order by md5('7:' || id), id limit 385",
}
