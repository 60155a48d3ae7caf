"""MinHash near-duplicates with HyperMinHash registers.

Each document's distinct five-word shingles fill 256 registers: the register is chosen
by eight hash bits, and keeps the smallest remaining value as a leading-zero count and ten
mantissa bits. Runs of five registers are band keys. In each bucket every member is paired with
one leader (drawn by hash, so that bands differ), the pair's registers give a
collision-corrected Jaccard estimate, and what may reach the threshold is confirmed on the
full shingle sets. Members of a bucket that still lie in different components are then compared across
those components: block by block against large components, where a member is done with its first link, and block by block within the
bucket for the rest. So no link that a band shows is lost, yet a group of copies never expands to all its pairs.

Equal shingle sets are one class from the start: they have Jaccard 1, and only the class is compared further, under a number of its own.

Defined cases: null or empty texts (or texts without words) have no set and link with nothing;
rows with a null doc_id do likewise, with a null component. A repeated row is returned as often as it
occurs. doc_id names a document: if one id comes with several texts, each of their sets is compared, and what any of them links
with is in the id's component. An empty table gives an empty result. Other columns are ignored.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import common, words

REGISTERS, MANTISSA, ROWS = 256, 10, 5
BANDS = REGISTERS // ROWS
SMALL, LEADERS = 8, 6  # a small bucket's members; leaders that a member of larger ones is compared with first
LARGE, BLOCK, BLOCK_BYTES = 32, 256, 1 << 19  # members of a large component; rows and bytes of a block
SIGMAS = 4.0  # an estimate this many standard deviations under the threshold is still confirmed


_LENDER = np.random.default_rng(9).random((REGISTERS, REGISTERS)).astype(np.float32)


def registers(shingles: np.ndarray) -> np.ndarray:
    """Sorted distinct 64-bit shingles to 256 16-bit registers.

    An empty register borrows the value of the filled one that comes first in an order of its own, so that
    any two sets agree on each register with about their Jaccard similarity, however small they are.
    """
    out = np.zeros(REGISTERS, ">u2")
    if not len(shingles):
        return out
    bucket = (shingles >> np.uint64(56)).astype(np.int64)
    first = np.concatenate(([0], np.flatnonzero(bucket[1:] != bucket[:-1]) + 1))
    low = shingles[first] & np.uint64((1 << 56) - 1)
    bits = np.frexp(np.maximum(low, 1).astype(np.float64))[1].astype(np.int64)
    zeros = np.clip(56 - bits, 0, 55)
    mantissa = ((low << zeros.astype(np.uint64)) >> np.uint64(55 - MANTISSA)) & np.uint64((1 << MANTISSA) - 1)
    filled = bucket[first]
    out[filled] = (zeros << MANTISSA) + mantissa.astype(np.int64) + 1
    if len(filled) < REGISTERS:
        empty = np.flatnonzero(out == 0)
        out[empty] = out[filled[_LENDER[empty][:, filled].argmin(axis=1)]]
    return out


def estimate(a: np.ndarray, b: np.ndarray, n: np.ndarray, m: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Jaccard estimates of register rows, corrected for chance matches, and their standard deviation at 0.75."""
    ratio = np.maximum(n, m) / np.maximum(1.0, np.minimum(n, m))
    # Fixed value: the published constant of chance matches of two registers, for equal sizes and no mantissa
    chance = 0.169919487159739 * 2.0**-MANTISSA * 4 * ratio / (1 + ratio) ** 2
    own = REGISTERS * (1 - np.exp(-np.minimum(n, m) / REGISTERS))  # registers with a value of their own
    return ((a == b).mean(axis=1) - chance) / (1 - chance), np.sqrt(0.1875 / np.maximum(1.0, own))


def _sketches(batches):
    for batch in batches:
        n, x, y, regs = [], [], [], []
        for text in words.text_bytes(batch.column(1)):
            s = words.shingle_set(text)
            n.append(len(s))
            x.append(int(s.sum(dtype=np.uint64).view(np.int64)) if len(s) else 0)
            y.append(int(np.bitwise_xor.reduce(words.mix(s)).view(np.int64)) if len(s) else 0)
            regs.append(registers(s).tobytes() if len(s) else None)
        yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(2), pa.array(n, pa.int64()), pa.array(x, pa.int64()), pa.array(y, pa.int64()), pa.array(regs, pa.binary())], ["doc_id", "th", "n", "fx", "fy", "regs"])


def _sets(batches):
    """Rows (id, text), repeated ones side by side, to each class's set once."""
    last = None
    for batch in batches:
        ids = batch.column(0).to_pylist()
        new = [k for k, i in enumerate(ids) if i != (ids[k - 1] if k else last)]
        last = ids[-1] if ids else last
        part = batch.take(pa.array(new, pa.int64()))
        packed = [words.shingle_set(t).tobytes() for t in words.text_bytes(part.column(1))]
        yield pa.RecordBatch.from_arrays([part.column(0), pa.array(packed, pa.binary())], ["id", "items"])


def _promising(percent: int):
    def run(batches):
        for batch in batches:
            n, m = (batch.column(k).to_numpy(zero_copy_only=False).astype(float) for k in (2, 3))
            x, y = (np.frombuffer(b"".join(batch.column(k).to_pylist()), ">u2").reshape(-1, REGISTERS) for k in (4, 5))
            est, sd = estimate(x, y, n, m)
            out = pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), pa.array(est)], ["a", "b", "est"])
            yield out.filter(pa.array(est >= percent / 100 - SIGMAS * sd))

    return run


def _confirmed(percent: int):
    def run(batches):
        for batch in batches:
            x, y = batch.column(2).to_pylist(), batch.column(3).to_pylist()
            keep = []
            for p, q in zip(x, y, strict=True):
                p, q = np.frombuffer(p, np.uint64), np.frombuffer(q, np.uint64)
                shared = len(np.intersect1d(p, q, assume_unique=True))
                keep.append(shared > 0 and 100 * shared >= percent * (len(p) + len(q) - shared))
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1)], ["a", "b"]).filter(pa.array(keep, pa.bool_()))

    return run


def near_duplicates(docs: DataFrame, percent: int = 75, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """(doc_id, n_shingles, component_id, kept) per row of ``docs``; links at Jaccard >= percent/100."""
    spark = docs.sparkSession
    scratch = common.Scratch(spark, "minhash")
    text = F.col(text_col).cast("string")
    base = docs.select(F.col(id_col).cast("long").alias("doc_id"), text.alias("text"), F.xxhash64(text).alias("th"))
    sketched = base.mapInArrow(common.lean(_sketches), "doc_id long, th long, n long, fx long, fy long, regs binary")
    sketch = scratch.keep(sketched.withColumn("row", F.monotonically_increasing_id()), "sketch", batch=2000)

    # classes of equal sets; an id may have several texts, so a class goes by the number of one of its rows
    full = sketch.where("n > 0 and doc_id is not null")
    classes = full.groupBy("n", "fx", "fy").agg(F.min(F.struct("doc_id", "th", "row")).alias("o"), F.first("regs").alias("regs"))
    classes = scratch.keep(classes.select("n", "fx", "fy", F.col("o.doc_id").alias("first"), F.col("o.th").alias("th"), F.col("o.row").alias("rep"), "regs"), "classes")
    reps = classes.select("rep", "n", "regs")

    def bands() -> DataFrame:
        slot = F.explode(F.sequence(F.lit(0), F.lit(BANDS - 1))).alias("band")
        cut = F.expr(f"substring(regs, band * {2 * ROWS} + 1, {2 * ROWS})")
        return reps.select("rep", "regs", slot).select("rep", F.xxhash64("band", cut).alias("key"))

    leaders = scratch.keep(
        bands().groupBy("key").agg(F.min_by("rep", F.xxhash64("rep", "key")).alias("leader"), F.count("*").alias("size")).where("size > 1"), "leaders"
    )
    member = scratch.keep(bands().join(leaders, "key").select("key", "rep", "leader", "size"), "members")
    # buckets beyond SMALL give each member a few of their leaders, which only hastens what the blocks below make complete
    few = F.slice(F.array_sort(F.collect_set(F.struct(F.xxhash64("rep", "leader").alias("h"), "leader"))), 1, LEADERS)
    from_large = member.where(F.col("size") > SMALL).where("rep <> leader").groupBy("rep").agg(few.alias("few")).select(F.col("rep").alias("a"), F.explode("few.leader").alias("b"))
    pairs = member.where(F.col("size") <= SMALL).where("rep <> leader").select(F.col("rep").alias("a"), F.col("leader").alias("b")).union(from_large).distinct()
    sized = _with_registers(scratch.keep(pairs, "pairs"), reps, percent)
    likely = scratch.keep(sized.mapInArrow(common.lean(_promising(percent)), "a long, b long, est double"), "likely", batch=4000)
    wanted = likely.select(F.col("a").alias("rep")).union(likely.select("b")).union(member.where("size > 2").select("rep")).distinct()
    wanted = classes.select("rep", F.col("first").alias("doc_id"), "th").join(wanted, "rep", "left_semi")
    sets = scratch.keep(_shingle_sets(base, wanted), "sets", batch=2000)

    # first each member with its likeliest leader, then what that leaves in different components
    best = likely.groupBy("a").agg(F.max_by("b", F.struct("est", "b")).alias("b"))
    links = scratch.keep(_confirm(scratch.keep(_once(best), "best"), sets, percent), "links1", batch=256)
    label = common.connected_components(links, scratch, "c1", rounds=1)  # only saves comparisons, so need not be complete
    rest = scratch.keep(_apart(likely.select("a", "b"), label), "rest")
    more = scratch.keep(_confirm(rest, sets, percent), "links2", batch=256)
    links = links.unionByName(more)
    label = common.connected_components(links, scratch, "c2")
    scratch.drop("best", "rest", "pairs")

    # members of one bucket in different components that were not compared yet: in a small bucket all but its leader
    unsettled = (F.col("size") > SMALL) | ((F.col("size") > 2) & (F.col("rep") != F.col("leader")))
    mine = member.where(unsettled).join(label.withColumnRenamed("node", "rep"), "rep", "left").select("key", "rep", F.coalesce("label", "rep").alias("label"))
    mine = scratch.keep(mine, "mine")
    split = scratch.keep(mine.groupBy("key").agg(F.min("label").alias("lo"), F.max("label").alias("hi")).where("lo < hi").select("key"), "split")
    open_ = scratch.keep(mine.join(split, "key").select("key", "rep", "label"), "open")
    large = scratch.keep(open_.select("rep", "label").distinct().groupBy("label").agg(F.count("*").alias("size")).where(F.col("size") >= LARGE), "large")
    late = scratch.keep(_against_large(open_, large, reps, sets, percent, scratch), "links3", batch=8)
    late = late.unionByName(scratch.keep(_among_small(open_, large, reps, sets, likely, percent, scratch), "links4", batch=256))
    # an id with several texts joins their classes
    of = sketch.select("doc_id", "n", F.when(F.col("n") > 0, F.col("fx")).alias("fx"), "fy").join(classes.select("n", "fx", "fy", "rep", "first"), ["n", "fx", "fy"], "left")
    of = scratch.keep(of.select("doc_id", "n", F.when(F.col("doc_id").isNotNull(), F.col("rep")).alias("rep"), "first"), "of")
    several = of.where("rep is not null").groupBy("doc_id").agg(F.min("rep").alias("a"), F.max("rep").alias("z")).where("a < z").select("doc_id", "a")
    several = of.join(several, "doc_id").where("rep <> a").select("a", F.col("rep").alias("b")).distinct()
    label = common.connected_components(links.unionByName(late).unionByName(several), scratch, "c3")
    root = classes.select(F.col("rep").alias("node"), "first").join(label, "node").groupBy("label").agg(F.min("first").alias("root"))
    root = scratch.keep(label.join(root, "label").select(F.col("node").alias("rep"), "root"), "root")
    scratch.drop("sketch", "classes", "members", "mine", "split", "open", "large", "sets", "likely", "leaders", "inside", "outside", "small", "near", "links1", "links2", "links3", "links4")

    component = F.when(F.col("doc_id").isNotNull(), F.coalesce("root", "first", "doc_id"))
    out = of.join(root, "rep", "left")
    return out.select("doc_id", F.col("n").alias("n_shingles"), component.alias("component_id"), F.coalesce(component == F.col("doc_id"), F.lit(True)).alias("kept"))


def _once(pairs: DataFrame) -> DataFrame:
    return pairs.select(F.least("a", "b").alias("a"), F.greatest("a", "b").alias("b")).distinct()


def _with_registers(pairs: DataFrame, reps: DataFrame, percent: int) -> DataFrame:
    """Pairs whose set sizes allow the threshold, with both register rows."""
    one = reps.select(F.col("rep").alias("a"), F.col("n").alias("n"), F.col("regs").alias("x"))
    two = reps.select(F.col("rep").alias("b"), F.col("n").alias("m"), F.col("regs").alias("y"))
    fits = F.least("n", "m") * 100 >= F.greatest("n", "m") * percent
    return pairs.join(one, "a").join(two, "b").where(fits).select("a", "b", "n", "m", "x", "y")


def _shingle_sets(base: DataFrame, wanted: DataFrame) -> DataFrame:
    """Full shingle sets of the classes in ``wanted`` (rep, doc_id, th); sorted and merged whatever the size, as texts are the larger side.

    Where the join splits a hot id, a set may come once from each part; links are made distinct after.
    """
    return base.join(wanted.hint("merge"), ["doc_id", "th"]).select("rep", "text").mapInArrow(common.lean(_sets), "id long, items binary")


_BLOCK = "key long, first long, ids binary, labels binary, sizes binary, regs binary, items binary"


def _blocks(batches):
    """Rows (key, id, label, n, regs, items) to blocks of one key."""
    held: dict[int, list] = {}
    names = [c.split()[0] for c in _BLOCK.split(", ")]

    def out(key):
        rows = held.pop(key)
        ids, labels, sizes = (np.array([r[k] for r in rows], "<i8").tobytes() for k in range(3))
        columns = [key, rows[0][0], ids, labels, sizes, b"".join(r[3] for r in rows), b"".join(r[4] or b"" for r in rows)]
        kinds = [pa.int64(), pa.int64()] + [pa.binary()] * 5
        return pa.RecordBatch.from_arrays([pa.array([c], t) for c, t in zip(columns, kinds, strict=True)], names)

    total, size = 0, {}
    for batch in batches:
        for key, *row in zip(*(batch.column(k).to_pylist() for k in range(6)), strict=True):
            held.setdefault(key, []).append(row)
            more = 600 + len(row[4] or b"")
            size[key], total = size.get(key, 0) + more, total + more
            if len(held[key]) >= BLOCK or size[key] >= BLOCK_BYTES:
                total -= size.pop(key)
                yield out(key)
            elif total > 32 * BLOCK_BYTES:
                for k in list(held):
                    yield out(k)
                total, size = 0, {}
    for k in list(held):
        yield out(k)


def _unpacked(row: dict, side: str):
    ids, labels, sizes = (np.frombuffer(row[f"{side}_{c}"], "<i8") for c in ("ids", "labels", "sizes"))
    return ids, labels, sizes, np.frombuffer(row[f"{side}_regs"], ">u2").reshape(-1, REGISTERS)


def _reaches_large(percent: int):
    """Blocks of outsiders (p) and of a component's members (q): each outsider's first confirmed link."""

    def run(batches):
        for batch in batches:
            a, b = [], []
            for row in batch.to_pylist():
                (p, _, n, x), (q, _, m, y) = _unpacked(row, "p"), _unpacked(row, "q")
                p_at, q_at = np.concatenate(([0], np.cumsum(n))), np.concatenate(([0], np.cumsum(m)))
                one, two = np.frombuffer(row["p_items"], np.uint64), np.frombuffer(row["q_items"], np.uint64)
                for i in range(len(p)):
                    est, sd = estimate(x[i], y, np.full(len(m), float(n[i])), m.astype(float))
                    fits = (np.minimum(n[i], m) * 100 >= np.maximum(n[i], m) * percent) & (est >= percent / 100 - SIGMAS * sd)
                    for j in sorted(np.flatnonzero(fits).tolist(), key=lambda j: -est[j]):
                        shared = len(np.intersect1d(one[p_at[i] : p_at[i + 1]], two[q_at[j] : q_at[j + 1]], assume_unique=True))
                        if 100 * shared >= percent * (n[i] + m[j] - shared):
                            a.append(int(p[i]))
                            b.append(int(q[j]))
                            break
            yield pa.RecordBatch.from_arrays([pa.array(a, pa.int64()), pa.array(b, pa.int64())], ["a", "b"])

    return run


def _promising_blocks(percent: int):
    """Two blocks of a bucket, or one with itself: pairs of different components that may reach the threshold."""

    def run(batches):
        for batch in batches:
            a, b = [], []
            for row in batch.to_pylist():
                (p, k, n, x), (q, c, m, y) = _unpacked(row, "p"), _unpacked(row, "q")
                for i in range(len(p)):
                    est, sd = estimate(x[i], y, np.full(len(m), float(n[i])), m.astype(float))
                    fits = (c != k[i]) & (np.minimum(n[i], m) * 100 >= np.maximum(n[i], m) * percent) & (est >= percent / 100 - SIGMAS * sd)
                    if row["p_first"] == row["q_first"]:
                        fits &= q > p[i]
                    hit = np.flatnonzero(fits)
                    a += [int(p[i])] * len(hit)
                    b += q[hit].tolist()
            yield pa.RecordBatch.from_arrays([pa.array(a, pa.int64()), pa.array(b, pa.int64())], ["a", "b"])

    return run


def _side(blocks: DataFrame, name: str) -> DataFrame:
    return blocks.select("key", *[F.col(c.split()[0]).alias(f"{name}_{c.split()[0]}") for c in _BLOCK.split(", ")[1:]])


def _against_large(open_: DataFrame, large: DataFrame, reps: DataFrame, sets: DataFrame, percent: int, scratch: common.Scratch) -> DataFrame:
    """Links from large components to others that share a bucket with them; sets travel in blocks, and pairs are never listed."""
    inside = open_.join(large, "label", "left_semi").select(F.col("label").alias("key"), "rep", "label").distinct()
    there = open_.join(large, "label").select("key", F.col("label").alias("of"), F.col("size").alias("of_size")).distinct()
    # of two large components the smaller is the outsider
    sized = open_.join(large, "label", "left").select("key", "rep", "label", F.coalesce("size", F.lit(0)).alias("size"))
    outside = sized.join(there, "key").where("struct(size, label) < struct(of_size, of)").select(F.col("of").alias("key"), "rep", "label").distinct()
    whole = reps.join(sets.withColumnRenamed("id", "rep"), "rep")
    tables = []
    for name, rows in (("inside", inside), ("outside", outside)):
        full = rows.join(whole, "rep").select("key", "rep", "label", "n", "regs", "items")
        tables.append(scratch.keep(full.mapInArrow(common.lean(_blocks), _BLOCK), name, batch=256))
    pairs = _side(tables[1], "p").join(_side(tables[0], "q"), "key").drop("key")
    return pairs.mapInArrow(common.lean(_reaches_large(percent)), "a long, b long")


def _among_small(open_: DataFrame, large: DataFrame, reps: DataFrame, sets: DataFrame, likely: DataFrame, percent: int, scratch: common.Scratch) -> DataFrame:
    """Links between small components that share a bucket: registers are compared in blocks, what may reach the threshold is confirmed."""
    rest = open_.join(large, "label", "left_anti")
    split = rest.groupBy("key").agg(F.min("label").alias("lo"), F.max("label").alias("hi"), F.count("*").alias("members")).where("lo < hi")
    # a large bucket's members are dealt to parts of about a block, so that no task gathers the whole bucket
    part = F.pmod(F.xxhash64("rep"), F.ceil(F.col("members") / BLOCK)).alias("part")
    full = rest.join(split, "key").select("key", "rep", "label", part).join(reps, "rep").select("key", "rep", "label", "n", "regs", F.lit(None).cast("binary").alias("items"), "part")
    blocks = full.repartition("key", "part").sortWithinPartitions("key", "part", "rep").drop("part")
    blocks = scratch.keep(blocks.mapInArrow(common.lean(_blocks), _BLOCK), "small", batch=1000)
    pairs = _side(blocks, "p").join(_side(blocks, "q"), "key").where("p_first <= q_first").drop("key", "p_items", "q_items")
    near = _once(pairs.mapInArrow(common.lean(_promising_blocks(percent)), "a long, b long"))
    near = scratch.keep(near.join(_once(likely), ["a", "b"], "left_anti"), "near", batch=64)
    return _confirm(near, sets, percent)


def _confirm(pairs: DataFrame, sets: DataFrame, percent: int) -> DataFrame:
    one, two = sets.select(F.col("id").alias("a"), F.col("items").alias("x")), sets.select(F.col("id").alias("b"), F.col("items").alias("y"))
    return pairs.select("a", "b").join(one, "a").join(two, "b").select("a", "b", "x", "y").mapInArrow(common.lean(_confirmed(percent)), "a long, b long").distinct()


def _apart(pairs: DataFrame, label: DataFrame) -> DataFrame:
    """Pairs whose ends lie in different components so far."""
    one, two = label.select(F.col("node").alias("a"), F.col("label").alias("la")), label.select(F.col("node").alias("b"), F.col("label").alias("lb"))
    apart = F.coalesce("la", "a") != F.coalesce("lb", "b")
    return _once(pairs.join(one, "a", "left").join(two, "b", "left").where(apart))
