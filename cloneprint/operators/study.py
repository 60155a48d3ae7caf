"""How reuse looks at file, class and function granularity; associated and conjugate clones; overlap with a component."""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..functions import text as T
from ..plans.groups import runs
from ..plans.store import Store
from . import units as U

#: classes of a block; shared functions of class pairs that are looked at together, which bounds a worker's memory: two of them stand beside an executor's heap
CELL, STEP = 4000, 500_000


def file_clones(docs: DataFrame, *keep: str, lang: str = "prose", text: str = "text") -> DataFrame:
    """Files with the hash of their normalised text, how many share it, and whether any other does."""
    hashed = docs.where(F.length(text) > 0).select(*keep, F.md5(T.normalize(F.col(text), lang)).alias("hash"))
    return U.with_count(hashed, "hash")


def unit_clones(units: DataFrame, text: str, *keep: str) -> DataFrame:
    """The same for classes or functions."""
    return U.with_count(units.select(*keep, F.md5(T.normalize(F.col(text))).alias("hash")), "hash")


def granularity_report(files: DataFrame, classes: DataFrame, functions: DataFrame) -> DataFrame:
    """Clone rates of three levels; each input has a column ``hash``."""
    out = U.clone_rate(files, "hash", "file")
    return out.unionByName(U.clone_rate(classes, "hash", "class")).unionByName(U.clone_rate(functions, "hash", "function"))


def multi_class_share(classes: DataFrame, file: str) -> DataFrame:
    """One row: n_files, n_multi (files with several classes), share."""
    per = classes.groupBy(file).agg(F.count("*").alias("n"))
    return per.agg(F.count("*").alias("n_files"), F.count_if(F.col("n") > 1).alias("n_multi")).withColumn("share", F.round(F.try_divide("n_multi", "n_files"), 6))


def partial_copies(files: DataFrame, classes: DataFrame, file: str) -> DataFrame:
    """Per file: classes that also stand in a file of another hash, which whole-file comparison misses.

    A class hash with two file hashes is such a class wherever it stands, so no pairs are made.
    """
    tagged = classes.select(file, F.col("hash").alias("unit")).join(files.select(file, F.col("hash").alias("file_hash")), file)
    spread = tagged.groupBy("unit").agg(F.min("file_hash").alias("lo"), F.max("file_hash").alias("hi")).where("lo <> hi").select("unit")
    return tagged.join(spread, "unit", "left_semi").groupBy(file).agg(F.count("*").alias("n_partial"))


def associated_pct(calls: DataFrame, functions: DataFrame, scope: str = "class", near: DataFrame | None = None) -> DataFrame:
    """Share of a caller's callees that are cloned where the caller is.

    calls: class_id, caller, callee; functions: class_id, owner, fn, hash (trivial ones left out). Clones are functions of equal hash or, with ``near``
    (hash, other: similar hashes both ways, each beside itself), of similar ones; they count if their owner is another. Where the callees must be cloned
    is the ``scope``: the class of the caller's clone (``class``), any class of its owner (``project``), or anywhere. Result per (class_id, caller, other): n_callees,
    n_cloned, pct; ``other`` is that class or owner, and null for anywhere.
    """
    own = functions.select("class_id", "owner", "fn", "hash")
    edge = calls.where("caller <> callee").select("class_id", "caller", "callee").distinct()
    edge = edge.join(own.select("class_id", F.col("fn").alias("caller"), "owner", F.col("hash").alias("caller_hash")), ["class_id", "caller"])
    edge = edge.join(own.select("class_id", F.col("fn").alias("callee"), F.col("hash").alias("callee_hash")), ["class_id", "callee"])
    held = functions.select("hash", "class_id", "owner")
    if near is not None:
        held = near.join(held.distinct().withColumnRenamed("hash", "other"), "other").select("hash", "class_id", "owner")
    if scope == "anywhere":
        # a hash is cloned for an owner if it has another owner: its smallest and largest tell
        ends = held.groupBy("hash").agg(F.min("owner").alias("lo"), F.max("owner").alias("hi"))
        end = lambda side: ends.select(F.col("hash").alias(f"{side}_hash"), F.col("lo").alias(f"{side}_lo"), F.col("hi").alias(f"{side}_hi"))
        cloned = lambda side: (F.col(f"{side}_lo") != F.col("owner")) | (F.col(f"{side}_hi") != F.col("owner"))
        found = edge.join(end("caller"), "caller_hash").join(end("callee"), "callee_hash").where(cloned("caller"))
        found = found.withColumns({"other": F.lit(None).cast("string"), "hit": F.when(cloned("callee"), 1)})
    elif scope in ("class", "project"):
        place = "class_id" if scope == "class" else "owner"
        spots = held.select("hash", F.col(place).alias("other"), F.col("owner").alias("other_owner")).distinct()
        beside = edge.join(spots.withColumnRenamed("hash", "caller_hash"), "caller_hash").where("owner <> other_owner")
        there = spots.select(F.col("hash").alias("callee_hash"), "other").withColumn("hit", F.lit(1))
        found = beside.join(there, ["callee_hash", "other"], "left")
    else:
        raise ValueError(f"no scope {scope!r}")
    return found.groupBy("class_id", "caller", "other").agg(F.count("*").alias("n_callees"), F.count("hit").alias("n_cloned")).withColumn("pct", F.round(F.col("n_cloned") / F.col("n_callees"), 6))


def pct_histogram(df: DataFrame, column: str = "pct", bins: int = 10) -> DataFrame:
    """bin (0..bins, the last for exactly 1), n."""
    return df.groupBy(F.floor(F.least(F.col(column), F.lit(1.0)) * bins + 1e-9).cast("int").alias("bin")).agg(F.count("*").alias("n"))


def conjugate_pct(functions: DataFrame, variant: str = "matching") -> DataFrame:
    """Conjugate clone percentage of class pairs (class_a < class_b) of different owners with exact function clones.

    functions: class_id, owner, hash. A pair of classes counts if two of its clone pairs differ on both sides, which is so if the smaller counts of its shared hashes add up to
    two or more; then every clone pair has such a partner. So classes with a single shared function are left out, the others meet block by block, and
    only pairs that count leave a block: those of one frequent hash alone are never written.
    """
    if variant not in ("pairs", "functions", "matching"):
        raise ValueError(f"no variant {variant!r}")
    store = Store(functions.sparkSession, "conjugate")
    held = store.keep(functions.groupBy("class_id", "owner", "hash").agg(F.count("*").alias("c")), "held")
    shared = held.groupBy("hash").agg(F.min("owner").alias("lo"), F.max("owner").alias("hi")).where("lo <> hi").select("hash", F.monotonically_increasing_id().alias("h"))
    shared = store.keep(shared, "shared")
    rows = store.keep(_rows(held, shared), "rows")
    blocks = max(1, -(-rows.count() // CELL))
    own = F.pmod(F.xxhash64("class_id"), F.lit(blocks)).cast("int")
    kind = lambda c: functions.schema[c].dataType.simpleString()
    return _dealt(_cells(rows, own, blocks), blocks).mapInArrow(_conjugate(variant), f"class_a {kind('class_id')}, class_b {kind('class_id')}, n_pairs long, n_conj long, pct double")


def _rows(held: DataFrame, numbers: DataFrame) -> DataFrame:
    """(class_id, owners, size, e) of classes with two functions or more among the numbered hashes (hash, h); e: h, count, place in owners."""
    sizes = held.groupBy("class_id").agg(F.sum("c").alias("size"))
    rows = held.where("owner is not null").join(numbers, "hash").groupBy("class_id").agg(F.collect_list(F.struct("h", "c", "owner")).alias("e"), F.collect_set("owner").alias("owners"), F.sum("c").alias("all")).where("all > 1")
    entry = F.transform("e", lambda x: F.struct(x["h"].alias("h"), x["c"].alias("c"), (F.array_position("owners", x["owner"]) - 1).alias("o")))
    return rows.join(sizes, "class_id").select("class_id", "owners", "size", entry.alias("e"))


def _cells(rows: DataFrame, own, blocks: int) -> DataFrame:
    """Rows once for each cell of their block and another one."""
    spread = rows.withColumn("own", own).withColumn("other", F.explode(F.sequence(F.lit(0), F.lit(blocks - 1))))
    return spread.withColumns({"x": F.least("own", "other"), "y": F.greatest("own", "other"), "right": F.col("own") > F.col("other")}).select("x", "y", "right", "class_id", "owners", "size", "e")


def _dealt(cells: DataFrame, blocks: int) -> DataFrame:
    return cells.repartition(max(cells.sparkSession.sparkContext.defaultParallelism, blocks * (blocks + 1) // 2), "x", "y").sortWithinPartitions("x", "y")


def _sides(table):
    """Of a cell: its rows' rank and size; its entries' row, hash, count, owner, whether they are on the right; and which are on the left (on the diagonal, all are on both)."""
    import pyarrow.compute as pc

    rank = np.empty(len(table), np.int64)
    rank[:] = pc.rank(table.column("class_id"), tiebreaker="dense").to_numpy()
    owners, lists = table.column("owners").combine_chunks(), table.column("e").combine_chunks()
    entries, row = lists.flatten(), np.repeat(np.arange(len(table)), np.diff(lists.offsets.to_numpy()))
    hashes, counts, place = (entries.field(k).to_numpy() for k in ("h", "c", "o"))
    owner = pc.rank(owners.flatten(), tiebreaker="dense").to_numpy().astype(np.int64)[(owners.offsets.to_numpy()[:-1] - owners.offsets.to_numpy()[0])[row] + place]
    size, right = table.column("size").to_numpy(), table.column("right").to_numpy(zero_copy_only=False).astype(bool)
    whole = table.column("x")[0].as_py() == table.column("y")[0].as_py()
    side = np.ones(len(row), bool) if whole else right[row]
    return rank, size, row, hashes, counts, owner, side, np.arange(len(row)) if whole else np.flatnonzero(~side)


def _steps(row: np.ndarray, lo: np.ndarray, hi: np.ndarray):
    """(k, j): each place k beside its range of places j, a few rows at a time; a row is not cut, as its sums are made at once."""
    many, ends = hi - lo, np.append(np.flatnonzero(np.diff(row)) + 1, len(row))
    total, begin = np.cumsum(many), 0
    while begin < len(row):
        fit = np.searchsorted(total, (total[begin - 1] if begin else 0) + STEP, "right")
        end = int(ends[min(max(np.searchsorted(ends, fit, "right") - 1, np.searchsorted(ends, begin, "right")), len(ends) - 1)])
        n = many[begin:end]
        yield np.repeat(np.arange(begin, end), n), np.repeat(lo[begin:end] - (np.cumsum(n) - n), n) + np.arange(n.sum())
        begin = end


def _several(a: np.ndarray, b: np.ndarray, weight: np.ndarray, rows: int) -> np.ndarray:
    """Which places belong to pairs (a, b) whose weights add up to two or more; all of them where counting them would take more room than they do."""
    if not len(a) or (span := int(a.max() - a.min() + 1) * rows) > 16 * len(a):
        return np.ones(len(a), bool)
    key = (a - a.min()) * rows + b
    return np.bincount(key, weight, span)[key] >= 2


def _conjugate(variant: str):
    """Pairs of a cell's two sides (of one side with itself on the diagonal), a few rows of the left side at a time."""

    def cell(table):
        import pyarrow as pa
        import pyarrow.compute as pc

        rank, size, row, hashes, counts, owner, side, left = _sides(table)
        whole = len(left) == len(row)
        order = np.argsort(hashes[side], kind="stable")
        rh, rr, rc, ro = hashes[side][order], row[side][order], counts[side][order], owner[side][order]
        lo, hi = np.searchsorted(rh, hashes[left], "left"), np.searchsorted(rh, hashes[left], "right")
        for k, j in _steps(row[left], lo, hi):
            i = left[k]
            a, b, ca, cb = row[i], rr[j], counts[i], rc[j]
            fits = owner[i] != ro[j]
            fits &= (rank[a] < rank[b]) if whole else (rank[a] != rank[b])
            a, b, ca, cb = a[fits], b[fits], ca[fits], cb[fits]
            fits = _several(a, b, np.minimum(ca, cb), len(table))
            a, b, ca, cb = a[fits], b[fits], ca[fits], cb[fits]
            if not len(a):
                continue
            order = np.argsort(a * len(table) + b, kind="stable")
            a, b, ca, cb = a[order], b[order], ca[order], cb[order]
            at = np.flatnonzero(np.concatenate([[True], (a[1:] != a[:-1]) | (b[1:] != b[:-1])]))
            add = lambda v: np.add.reduceat(v, at)  # noqa: B023, E731
            pairs, least = add(ca * cb), add(np.minimum(ca, cb))
            top = 2 * pairs if variant == "pairs" else add(ca + cb) if variant == "functions" else 2 * least
            keep = least >= 2
            if keep.any():
                a, b = a[at][keep], b[at][keep]
                a, b = np.where(rank[a] < rank[b], a, b), np.where(rank[a] < rank[b], b, a)
                yield pa.table({"class_a": table.column("class_id").take(pa.array(a)), "class_b": table.column("class_id").take(pa.array(b)), "n_pairs": pairs[keep], "n_conj": top[keep], "part": top[keep] / (size[a] + size[b])})

    def run(batches):
        import pyarrow as pa
        import pyarrow.compute as pc

        for table in runs(batches, ("x", "y")):
            for out in cell(table):
                yield from out.drop_columns(["part"]).append_column("pct", pc.round(out.column("part"), 6, "half_towards_infinity")).combine_chunks().to_batches()

    return run


def conjugate_pct_similar(functions: DataFrame, near: DataFrame, variant: str = "functions") -> DataFrame:
    """The same percentage when clones are similar hashes: near (hash, other, both ways, each beside itself; for ``matching`` also sim).

    Similar hashes are not transitive, so a pair's ends are counted apart: a pair has a partner on both sides if all pairs outnumber those at either end.
    ``matching`` takes pairs one to one in the order of their similarity, at least half of the best matching. Classes meet block by block, beside those similar hashes that
    both sides hold; class pairs with a single pair of clones are never written.
    """
    if variant not in ("pairs", "functions", "matching"):
        raise ValueError(f"no variant {variant!r}")
    store = Store(functions.sparkSession, "conjugate")
    held = store.keep(functions.groupBy("class_id", "owner", "hash").agg(F.count("*").alias("c")), "held")
    ends = held.groupBy("hash").agg(F.min("owner").alias("lo"), F.max("owner").alias("hi"))
    links = near.join(ends, "hash").join(ends.select(F.col("hash").alias("other"), F.col("lo").alias("lo_b"), F.col("hi").alias("hi_b")), "other")
    sim = F.col("sim") if "sim" in near.columns else F.lit(1.0)
    links = store.keep(links.where(F.least("lo", "lo_b") != F.greatest("hi", "hi_b")).select("hash", "other", sim.alias("sim")).distinct(), "links")
    # numbers in the order of the hashes, by which equal similarities are taken
    numbers = store.keep(links.select("hash").union(links.select("other")).distinct().orderBy("hash").select("hash", F.monotonically_increasing_id().alias("h")), "numbers")
    rows = store.keep(_rows(held, numbers), "rows")
    blocks = max(1, -(-rows.count() // CELL))
    own = F.pmod(F.xxhash64("class_id"), F.lit(blocks)).cast("int")
    places = rows.select(own.alias("x"), F.explode("e.h").alias("ha")).distinct()
    pairs = links.join(numbers.withColumnRenamed("h", "ha"), "hash").select("other", "ha", "sim").join(numbers.select(F.col("hash").alias("other"), F.col("h").alias("hb")), "other")
    pairs = pairs.select("ha", "hb", "sim").join(places, "ha").join(places.select(F.col("x").alias("y"), F.col("ha").alias("hb")), "hb").where("x <= y")
    cells = _cells(rows, own, blocks).unionByName(pairs.select("x", "y", "ha", "hb", "sim"), allowMissingColumns=True)
    kind = lambda c: functions.schema[c].dataType.simpleString()
    out = _dealt(cells, blocks).mapInArrow(_conjugate_similar(variant), f"class_a {kind('class_id')}, class_b {kind('class_id')}, n_pairs long, n_conj long, size long")
    return out.select("class_a", "class_b", "n_pairs", "n_conj", F.round(F.col("n_conj") / F.col("size"), 6).alias("pct"))


def _conjugate_similar(variant: str):
    def cell(table):
        import pyarrow as pa
        import pyarrow.compute as pc

        links, table = table.filter(pc.is_valid(table.column("ha"))), table.filter(pc.is_null(table.column("ha")))
        if not len(links) or not len(table):
            return
        rank, size, row, hashes, counts, owner, side, left = _sides(table)
        kinds, hashes = np.unique(hashes, return_inverse=True)
        la, lb = (np.searchsorted(kinds, links.column(c).to_numpy()) for c in ("ha", "hb"))
        order = np.argsort(la, kind="stable")
        la, lb, ls = la[order], lb[order], links.column("sim").to_numpy()[order]
        right = np.flatnonzero(side)
        right = right[np.argsort(hashes[right], kind="stable")]
        # entries of the left side beside each hash that is similar to theirs
        at, many = np.searchsorted(la, hashes[left], "left"), np.searchsorted(la, hashes[left], "right")
        many = many - at
        e, k = np.repeat(left, many), np.repeat(at - (np.cumsum(many) - many), many) + np.arange(many.sum())
        if not len(e):
            return
        to, sim = lb[k], ls[k]
        whole = len(left) == len(row)
        for k, j in _steps(row[e], np.searchsorted(hashes[right], to, "left"), np.searchsorted(hashes[right], to, "right")):
            i, j = e[k], right[j]
            fits = owner[i] != owner[j]
            fits &= (rank[row[i]] < rank[row[j]]) if whole else (rank[row[i]] != rank[row[j]])
            i, j, s = i[fits], j[fits], sim[k[fits]]
            fits = _several(row[i], row[j], counts[i] * counts[j], len(table))
            i, j, s = i[fits], j[fits], s[fits]
            if not len(i):
                continue
            turned = rank[row[i]] > rank[row[j]]
            i, j = np.where(turned, j, i), np.where(turned, i, j)
            order = np.argsort(row[i] * len(table) + row[j], kind="stable")
            i, j, s = i[order], j[order], s[order]
            a, b, ha, hb, ca, cb = row[i], row[j], hashes[i], hashes[j], counts[i], counts[j]
            new = np.concatenate([[True], (a[1:] != a[:-1]) | (b[1:] != b[:-1])])
            p, a, b = np.cumsum(new) - 1, a[new], b[new]
            pairs, conj = _tops(variant, p, ha, hb, ca, cb, s, len(kinds))
            keep = conj > 0
            if keep.any():
                a, b = a[keep], b[keep]
                yield pa.table({"class_a": table.column("class_id").take(pa.array(a)), "class_b": table.column("class_id").take(pa.array(b)), "n_pairs": pairs[keep], "n_conj": conj[keep], "size": size[a] + size[b]})

    def run(batches):
        for table in runs(batches, ("x", "y")):
            for out in cell(table):
                yield from out.combine_chunks().to_batches()

    return run


def _tops(variant: str, p, ha, hb, ca, cb, sim, kinds: int) -> tuple:
    """Pairs and conjugate ones of each class pair p, whose rows lie side by side."""
    add = lambda where, v: np.bincount(where, v, int(p[-1]) + 1).astype(np.int64)
    total = add(p, ca * cb)
    at = [np.unique(p * kinds + h, return_inverse=True)[1] for h in (ha, hb)]
    if variant == "matching":
        # where no function is in two pairs, all are taken
        matched, several = add(p, np.minimum(ca, cb)), np.zeros(len(total), bool)
        for side in at:
            several[p[np.bincount(side)[side] > 1]] = True
        starts = np.searchsorted(p, np.arange(len(total) + 1))
        for k in np.flatnonzero(several):
            cut = slice(starts[k], starts[k + 1])
            matched[k] = _greedy(*(v[cut].tolist() for v in (sim, ha, hb, ca, cb)))
        return total, np.where(matched > 1, 2 * matched, 0)
    others = total[p] - np.bincount(at[0], cb)[at[0]].astype(np.int64) - np.bincount(at[1], ca)[at[1]].astype(np.int64) + 1
    kept = others >= 1
    if variant == "pairs":
        return total, 2 * add(p[kept], (ca * cb)[kept])
    out = np.zeros(len(total), np.int64)
    for side, c in zip(at, (ca, cb), strict=True):
        # a hash that a class holds under two owners counts once for each number of them
        side, c, q = side[kept], c[kept], p[kept]
        order = np.lexsort((c, side))
        side, c, q = side[order], c[order], q[order]
        new = np.ones(len(q), bool)
        new[1:] = (side[1:] != side[:-1]) | (c[1:] != c[:-1])
        out += add(q[new], c[new])
    return total, out


def _greedy(sim: list, ha: list, hb: list, ca: list, cb: list) -> int:
    """One-to-one pairs of a class pair, most similar first; equal hashes of a side are as many functions as they count."""
    left: dict = {}
    matched = 0
    for _, x, y, n, m in sorted(zip([-s for s in sim], ha, hb, ca, cb, strict=True)):
        a, b = left.setdefault(("a", x), n), left.setdefault(("b", y), m)
        take = min(a, b)
        left["a", x], left["b", y] = a - take, b - take
        matched += take
    return matched


def overlap_ratio(subject: DataFrame, component: DataFrame, denominator: str = "component") -> DataFrame:
    """Per (subject, component) with a shared print: shared, ratio to the chosen side's distinct prints."""
    s, c = subject.select("subject", "print").distinct(), component.select("component", "print").distinct()
    size = (c.groupBy("component") if denominator == "component" else s.groupBy("subject")).agg(F.count("*").alias("size"))
    shared = s.join(c, "print").groupBy("subject", "component").agg(F.count("*").alias("shared"))
    return shared.join(size, denominator).select("subject", "component", "shared", F.round(F.col("shared") / F.col("size"), 6).alias("ratio"))
