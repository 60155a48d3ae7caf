"""Class prints: internal calls, loop cutting, linking, and order-insensitive hashes.

Trees are never built. With sums of hashes, the print of a tree with callee bodies put in at each call is the sum of own hashes,
each times the number of ways it is reached; so linking is a few rounds of join and sum over call edges.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.types import BooleanType, LongType, StructField, StructType

from ..functions import hashing as H
from ..functions import text as T
from ..plans.groups import by_group, strongly_connected
from ..plans.store import Store

#: rows of one class that a task may hold at once; larger classes go by rounds of joins
LOCAL_ROWS = 500_000

EXTERNAL, RECURSIVE, CLASS, FUNCTION, STATEMENT = "EXTERNAL", "RECURSIVE", "CLASS", "FUNCTION", "STATEMENT"


def functions_of(lines: DataFrame, level: str = "exact", kind: str = "portable") -> DataFrame:
    """Function rows of line units (class_id, pos, line): fn, name, loc, own (hash of the label bag)."""
    from ..functions.complexity import prose_loc

    source = F.col("line") if level != "exact" else F.lower("line")
    return lines.select("class_id", F.col("pos").alias("fn"), "line", T.declared_name(F.col("line")).alias("name"), prose_loc(F.col("line")).alias("loc"), H.bag_hash(T.labels(source, level), kind).alias("own"))


def call_edges(functions: DataFrame) -> DataFrame:
    """class_id, caller, callee, n: words after a function's first that name a function of the same class.

    A name declared twice stands for its first function. caller = callee is recursion.
    """
    named = functions.where("name is not null").groupBy("class_id", "name").agg(F.min("fn").alias("callee"))
    later = functions.select("class_id", F.col("fn").alias("caller"), F.explode(F.slice(T.words(F.col("line")), 2, 1 << 30)).alias("name"))
    # counted per word before the join, so that only words of declared length travel, once each
    uses = later.where(F.length("name") >= 4).groupBy("class_id", "caller", "name").agg(F.count("*").alias("k"))
    return uses.join(named, ["class_id", "name"]).groupBy("class_id", "caller", "callee").agg(F.sum("k").alias("n"))


def reachable(edges: DataFrame, store: Store) -> DataFrame:
    """All (class_id, a, b) with a path from a to b: paths double until none is new, so rounds are few even for long chains."""
    reach, before, step = store.keep(edges.select("class_id", F.col("caller").alias("a"), F.col("callee").alias("b")).distinct(), "reach-0"), -1, 0
    n = reach.count()
    while n != before:
        step += 1
        hop = reach.select("class_id", F.col("a").alias("b"), F.col("b").alias("c"))
        longer = reach.join(hop, ["class_id", "b"]).select("class_id", "a", F.col("c").alias("b"))
        reach, before = store.keep(reach.unionByName(longer).distinct(), f"reach-{step}"), n
        n = reach.count()
        store.drop(f"reach-{step - 1}")
    return reach


def _loop_edges(rows):
    """Rows (class_id, caller, callee, n) of a class, each with the number of its caller's callees and whether it lies in a loop, then the callee's number."""
    of = strongly_connected((r[1], r[2]) for r in rows)
    degree: dict = {}
    for r in rows:
        degree[r[1]] = degree.get(r[1], 0) + 1
    return [(*r, of[r[1]] == of[r[2]], degree[r[1]], degree.get(r[2], 0)) for r in rows]


def _split(df: DataFrame, key: str, store: Store, name: str) -> tuple[DataFrame, DataFrame | None]:
    """Rows of keys with at most ``LOCAL_ROWS`` of them, which a task takes whole, and the others, if there are any."""
    large = store.keep(df.groupBy(key).agg(F.count("*").alias("rows")).where(F.col("rows") > LOCAL_ROWS).select(key), f"{name}-large")
    return (df, None) if large.isEmpty() else (df.join(large, key, "left_anti"), df.join(large, key, "left_semi"))


def break_cycles(calls: DataFrame, functions: DataFrame, scope: str = "scc") -> DataFrame:
    """Calls with a flag ``status``: keep, cut or recursive.

    In a loop an edge stays if its caller comes first by distinct callees (more), length (more), position (less). ``all`` puts every edge under that order. Loops
    are found class by class in one pass; a class too large for a task goes by paths that double.
    """
    if scope not in ("scc", "all"):
        raise ValueError(f"no scope {scope!r}")
    store = Store(calls.sparkSession, "calls")
    plain = store.keep(calls.where("caller <> callee").select("class_id", "caller", "callee", "n"), "plain")
    small, large = _split(plain, "class_id", store, "calls")
    added = StructType([*small.schema.fields, StructField("loop", BooleanType()), StructField("d1", LongType()), StructField("d2", LongType())])
    looped = by_group(small, ["class_id"], _loop_edges, added)
    if large is not None:
        degree = large.groupBy("class_id", F.col("caller").alias("fn")).agg(F.count("*").alias("deg"))
        back = reachable(large, store).select("class_id", F.col("a").alias("callee"), F.col("b").alias("caller"), F.lit(True).alias("loop"))
        end = lambda side, name: degree.select("class_id", F.col("fn").alias(side), F.col("deg").alias(name))
        more = large.join(back, ["class_id", "caller", "callee"], "left").join(end("caller", "d1"), ["class_id", "caller"]).join(end("callee", "d2"), ["class_id", "callee"], "left")
        looped = looped.unionByName(more.select("class_id", "caller", "callee", "n", F.coalesce("loop", F.lit(False)).alias("loop"), "d1", F.coalesce("d2", F.lit(0)).alias("d2")))
    looped = store.keep(looped, "looped")
    within = F.col("loop") | F.lit(scope == "all")
    # lengths are looked up for edges in loops only, which are few
    length = lambda side, name: functions.select("class_id", F.col("fn").alias(side), F.col("loc").alias(name))
    ranked = looped.where(within).join(length("caller", "l1"), ["class_id", "caller"]).join(length("callee", "l2"), ["class_id", "callee"])
    behind = F.struct("d1", "l1", -F.col("caller")) < F.struct("d2", "l2", -F.col("callee"))
    ranked = ranked.select("class_id", "caller", "callee", "n", F.when(behind, "cut").otherwise("keep").alias("status"))
    out = ranked.unionByName(looped.where(~within).select("class_id", "caller", "callee", "n", F.lit("keep").alias("status")))
    return out.unionByName(calls.where("caller = callee").select("class_id", "caller", "callee", "n", F.lit("recursive").alias("status")))


def _substitute(rows):
    """Rows (class_id, fn, callee, n, part) of a class, functions with a part and calls with a callee, to the linked sum of each function."""
    part = {r[1]: r[4] for r in rows if r[2] is None}
    after: dict = {}
    for _, fn, callee, n, _ in rows:
        if callee is not None:
            after.setdefault(fn, []).append((callee, n))
    done: dict = {}
    for start in part:
        walk = [start]
        while walk:
            fn = walk[-1]
            waiting = [g for g, _ in after.get(fn, ()) if g not in done and g in part] if fn not in done else []
            if waiting:
                walk.extend(waiting)
                continue
            walk.pop()
            if fn not in done:
                done[fn] = (part[fn] + sum(n * done.get(g, 0) for g, n in after.get(fn, ()))) % H.MODULUS
    key = rows[0][0]
    return [(key, fn, done[fn]) for fn in part]


def link(functions: DataFrame, acyclic: DataFrame, kind: str = "portable", recursion: str = "site") -> DataFrame:
    """class_id, fn, linked: own hash with callee trees put in at each call, modulo the hash's modulus.

    Cut calls and calls that leave the class (status ``external``) become placeholders. A recursive function has one at each call of
    itself (``site``) or one for its body (``body``). Classes are linked one by one in a single pass over those that have calls; a class
    too large for a task takes a round of join and sum for each step of its longest path.
    """
    if recursion not in ("site", "body"):
        raise ValueError(f"no recursion {recursion!r}")
    store = Store(functions.sparkSession, "link")
    own_calls = F.col("status") == "recursive"
    place = F.when(own_calls, H.own_hash(F.lit(RECURSIVE), kind)).otherwise(H.own_hash(F.lit(EXTERNAL), kind)).cast("decimal(19,0)")
    times = F.when(own_calls & F.lit(recursion == "body"), F.lit(1)).otherwise(F.col("n")).cast("decimal(18,0)")
    marks = acyclic.where("status <> 'keep'").groupBy("class_id", F.col("caller").alias("fn")).agg(H.reduced(F.sum(times * place)).alias("marks"))
    own = functions.select("class_id", "fn", "own").join(marks, ["class_id", "fn"], "left")
    own = store.keep(own.select("class_id", "fn", H.added(F.col("own"), F.coalesce("marks", F.lit(0))).alias("part")), "own")
    edges = store.keep(acyclic.where("status = 'keep'").select("class_id", F.col("caller").alias("fn"), "callee", "n"), "edges")
    calling = edges.select("class_id").distinct()
    rows = own.join(calling, "class_id", "left_semi").select("class_id", "fn", F.lit(None).cast(edges.schema["callee"].dataType).alias("callee"), F.lit(None).cast("long").alias("n"), "part")
    rows = rows.unionByName(edges.select("class_id", "fn", "callee", F.col("n").cast("long").alias("n"), F.lit(None).cast("long").alias("part")))
    small, large = _split(rows, "class_id", store, "rows")
    out = by_group(small, ["class_id"], _substitute, StructType([own.schema["class_id"], own.schema["fn"], StructField("linked", LongType())]))
    out = out.unionByName(own.join(calling, "class_id", "left_anti").select("class_id", "fn", F.col("part").alias("linked")))
    if large is not None:
        out = out.unionByName(_link_rounds(large.where("callee is null").select("class_id", "fn", "part"), large.where("callee is not null").select("class_id", F.col("fn").alias("caller"), F.col("callee").alias("fn"), "n"), store))
    return out


def _link_rounds(own: DataFrame, edges: DataFrame, store: Store) -> DataFrame:
    """Linking by one join and sum for each step of the longest path, whatever the size of a class."""
    layer, layers, step = own, [own], 0
    while True:
        step += 1
        grown = edges.join(layer, ["class_id", "fn"]).groupBy("class_id", "caller").agg(H.reduced(F.sum(F.col("n").cast("decimal(18,0)") * F.col("part").cast("decimal(19,0)"))).alias("part"))
        layer = store.keep(grown.select("class_id", F.col("caller").alias("fn"), "part"), f"layer-{step}")
        if layer.isEmpty():  # no path is longer
            break
        layers.append(layer)
    total = layers[0]
    for more in layers[1:]:
        total = total.unionByName(more)
    return total.groupBy("class_id", "fn").agg(H.total(F.col("part")).alias("linked"))


def class_print(linked: DataFrame, acyclic: DataFrame, roots: str = "entry", kind: str = "portable") -> DataFrame:
    """class_id, print: the class node over its starting functions (those no kept call reaches), or over all."""
    top = linked
    if roots == "entry":
        top = linked.join(acyclic.where("status = 'keep'").select("class_id", F.col("callee").alias("fn")), ["class_id", "fn"], "left_anti")
    elif roots != "all":
        raise ValueError(f"no roots {roots!r}")
    node = F.col("linked").cast("decimal(38,0)") + H.own_hash(F.lit(FUNCTION), kind).cast("decimal(38,0)")
    whole = top.groupBy("class_id").agg(F.sum(node.cast("decimal(38,0)")).alias("s"))
    return whole.select("class_id", H.reduced(F.col("s") + H.own_hash(F.lit(CLASS), kind).cast("decimal(38,0)")).alias("print"))


def additive_print(units: DataFrame, text: str, *keep: str, level: str = "exact", kind: str = "portable") -> DataFrame:
    """Units without calls: the kept columns and the label bag's hash."""
    source = F.col(text) if level != "exact" else F.lower(F.col(text))
    return units.select(*keep, H.bag_hash(T.labels(source, level), kind).alias("print"))


def mixed_print(lines: DataFrame, kind: str = "portable") -> DataFrame:
    """class_id, print: hashed again at sentence, function and class level, so that labels cannot change places between them."""
    sentence = F.filter(F.split(F.lower("line"), T.SENTENCE_END), lambda s: F.trim(s) != "")
    nodes = F.transform(sentence, lambda s: H.node_hash(STATEMENT, H.bag_hash(T.tokens(s), kind), kind))
    body = F.aggregate(nodes, F.lit(0).cast("bigint"), H.added)
    per = lines.select("class_id", H.node_hash(FUNCTION, body, kind).alias("node"))
    return per.groupBy("class_id").agg(H.total(F.col("node")).alias("s")).select("class_id", H.node_hash(CLASS, F.col("s"), kind).alias("print"))


def collision_audit(additive: DataFrame, mixed: DataFrame) -> DataFrame:
    """Additive prints whose classes differ by the mixed print: print, n_classes, n_mixed."""
    both = additive.join(mixed.select("class_id", F.col("print").alias("mixed")), "class_id")
    return both.groupBy("print").agg(F.count("*").alias("n_classes"), F.count_distinct("mixed").alias("n_mixed")).where("n_mixed > 1")
