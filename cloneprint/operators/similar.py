"""Similar functions: exact set-similarity joins by inverted index or prefix filter, and MinHash bands.

All work on classes of equal shingle sets: copies are one class with a member count, and links are between classes. So a
unit that stands thousands of times never expands to its pairs. A class keeps the words of one member, not its shingles: words are a fraction of the hashes' size, and the set is
made again where it is needed. Index keys of one class alone are told by a bitmap and do not travel; others go as packed blocks of one bucket each, beside a bit sketch of the set,
so that most candidates fall before they are written.
Shingles are 64-bit hashes. Thresholds are in percent and compared as integers.
"""

from __future__ import annotations

from functools import reduce

import numpy as np
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..functions import text as T
from ..plans.groups import runs
from ..plans.store import Store

K, PERCENT = 3, 70
#: classes drawn to tell frequent shingles from rare ones, and how many of these are told apart at most; the order only decides the cost
SAMPLE, FREQUENT = 100_000, 200_000
#: index keys of a bucket, about; keys a task holds back before it sends its blocks; pairs made at once
BUCKET, BLOCK, STEP = 1_000_000, 1_000_000, 2_000_000
#: keys meet in rounds, each with a share of the buckets, so that few blocks are on disk at once: keys of a round at least, and rounds at most, as each reads all keys
ROUND, ROUNDS = 8_000_000, 4
#: pairs of a cell, about; words of 64 bits of a sketch; bits of the bitmap of keys, as a power of two at most, and how many slices it is made in
CELL, WORDS, SPOTS, SLICES = 20_000, 4, 28, 64
#: remainders by which classes without a pair are told; it bounds what is broadcast
REMAINDERS = 1 << 20
#: fewer keys go without the bitmap
FEW = 1_000_000
_KEYS = "rep long, n int, sketch binary, keys binary"
_BLOCKS = "bucket int, g binary, rep binary, n binary, sketch binary"
#: bits of a bitmap of shingles
BITMAP = 1 << 24


def _set(words: Column) -> Column:
    """Sorted hashes of an array's distinct runs of K words."""
    # the array beside itself, shifted: where Spark puts the words' expression in, it runs once for each shift, not for each run
    runs = F.transform(F.arrays_zip(words, *[F.slice(words, k + 1, 1 << 30) for k in range(1, K)]), lambda run: F.xxhash64(run))
    return F.when(F.size(words) >= K, F.sort_array(F.array_distinct(F.slice(runs, F.lit(1), F.greatest(F.size(words) - (K - 1), F.lit(0))))))


def shingled(units: DataFrame, id_col: str, text: str) -> DataFrame:
    """(id, words, n, h1, h2) of units with at least K words: the words, the size of their shingle set, and its digest."""
    # words in a projection of their own, else each run would extract them again
    split = units.select(F.col(id_col).alias("id"), T.words(F.col(text)).alias("w"))
    sets = split.select("id", F.array_join("w", " ").alias("words"), _set(F.col("w")).alias("set"))
    # a row's digest as one value that is there or not, so that the filter does not make the set a second time
    made = sets.select("id", "words", F.explode_outer(F.when(F.col("set").isNotNull(), F.array(F.struct(F.size("set").alias("n"), F.xxhash64("set").alias("h1"), F.xxhash64(F.lit(1), "set").alias("h2"))))).alias("d"))
    return made.where("d is not null").select("id", "words", "d.n", "d.h1", "d.h2")


def classes(sets: DataFrame, store: Store) -> DataFrame:
    """(rep, first, n_members, n, words, h1, h2), written: rep is the class's number, first its smallest id, words those of that member."""
    grouped = sets.groupBy("h1", "h2").agg(F.min(F.struct("id", "words", "n")).alias("m"), F.count("*").alias("n_members"))
    groups = store.keep(grouped.select(F.monotonically_increasing_id().alias("rep"), F.col("m.id").alias("first"), "n_members", "m.n", "m.words", "h1", "h2"), "classes", "zstd")
    store.free()
    return groups


def classes_of(sets: DataFrame, store: Store) -> tuple[DataFrame, DataFrame]:
    """(id, h1, h2) of all units and their classes, both written; the words stay with the classes alone."""
    kept = store.keep(sets, "sets", "zstd")
    groups, members = classes(kept, store), store.keep(kept.select("id", "h1", "h2"), "members", "zstd")
    store.drop("sets")
    return members, groups


def with_set(groups: DataFrame) -> DataFrame:
    """(rep, set) of classes, made from their words."""
    return groups.select("rep", F.split("words", " ").alias("w")).select("rep", _set(F.col("w")).alias("set"))


def similar(shared: Column, n: Column, m: Column, percent: int) -> Column:
    return shared * 100 >= (n + m - shared) * percent


def _sim(shared: Column, n: Column, m: Column) -> Column:
    return F.round(shared / (n + m - shared), 6)


def _verified(pairs: DataFrame, groups: DataFrame, percent: int, store: Store) -> DataFrame:
    """Pairs whose whole sets reach the threshold.

    Classes are dealt to sides and pairs to the cells of two sides. A class's words go once to each cell where it has a pair, however many it has there.
    """
    pairs = store.keep(pairs, "pairs")
    store.drop(*[f"met{k}" for k in range(ROUNDS)])
    cells = max(2 * groups.sparkSession.sparkContext.defaultParallelism, pairs.count() // CELL)
    store.free()
    sides = int(np.ceil(np.sqrt(2 * cells)))
    side = lambda c: F.pmod(F.xxhash64(c), F.lit(sides)).cast("int")
    # a cell goes by its sides in order, so that both halves of the square are used as one
    x, y = side("a"), side("b")
    placed = pairs.select("a", "b", F.least(x, y).alias("x"), F.greatest(x, y).alias("y"))
    ends = placed.select("x", "y", F.explode(F.array("a", "b")).alias("rep")).distinct()
    # most classes are in no pair: a bounded number of remainders tells nearly all of them before their words move
    spot = F.pmod(F.xxhash64("rep"), F.lit(REMAINDERS))
    among = groups.select("rep", "words", spot.alias("spot")).join(F.broadcast(ends.select(spot.alias("spot")).distinct()), "spot", "left_semi")
    texts = among.join(ends, "rep").select("x", "y", F.col("rep").alias("a"), F.lit(None).cast("long").alias("b"), "words")
    rows = texts.unionByName(placed.withColumn("words", F.lit(None).cast("string")))
    counted = rows.repartition(cells, "x", "y").sortWithinPartitions("x", "y").mapInArrow(_counted(percent), "a long, b long, n long, m long, shared long")
    # written, so that what comes after neither counts again nor waits for these shuffle files to go
    out = store.keep(counted.select("a", "b", _sim(F.col("shared"), F.col("n"), F.col("m")).alias("sim")), "similar")
    store.drop("pairs")
    store.free()
    return out


def _counted(percent: int):
    """Shared runs of words of a cell's pairs, by the words themselves; rows without b hold a class's words."""

    def cell(table):
        import pyarrow as pa
        import pyarrow.compute as pc

        texts, pairs = table.filter(pc.is_null(table.column("b"))), table.filter(pc.is_valid(table.column("b")))
        reps = texts.column("a").to_numpy()
        order = np.argsort(reps)
        lists = pc.split_pattern(texts.column("words").combine_chunks().cast(pa.large_string()), " ")
        words = pc.dictionary_encode(lists.flatten())
        code, many = words.indices.to_numpy().astype(np.int64), len(words.dictionary)
        count = np.diff(lists.offsets.to_numpy())
        row = np.repeat(np.arange(len(count)), count)
        run = code
        for k in range(1, K):
            run = np.unique(run[:-1] * many + code[k:], return_inverse=True)[1].astype(np.int64)
        kinds = int(run.max()) + 1
        held = np.unique((row[: len(run)] * kinds + run)[row[: len(run)] == row[K - 1 :]])
        size = np.bincount(held // kinds, minlength=len(count))
        start = np.cumsum(size) - size
        a, b = (order[np.searchsorted(reps, pairs.column(c).to_numpy(), sorter=order)] for c in "ab")
        less, more = np.where(size[a] <= size[b], a, b), np.where(size[a] <= size[b], b, a)
        total = np.cumsum(size[less])
        begin, shared = 0, np.zeros(len(a), np.int64)
        while begin < len(a):
            end = max(begin + 1, int(np.searchsorted(total, (total[begin - 1] if begin else 0) + STEP, "right")))
            n = size[less[begin:end]]
            at = np.repeat(start[less[begin:end]] - (np.cumsum(n) - n), n) + np.arange(n.sum())
            wanted = held[at] % kinds + np.repeat(more[begin:end], n) * kinds
            hit = held[np.minimum(np.searchsorted(held, wanted), len(held) - 1)] == wanted
            shared[begin:end] = np.add.reduceat(hit.astype(np.int64), np.cumsum(n) - n)
            begin = end
        n, m = size[a], size[b]
        kept = shared * 100 >= (n + m - shared) * percent
        out = pairs.select(["a", "b"]).filter(pa.array(kept))
        return out.append_column("n", pa.array(n[kept])).append_column("m", pa.array(m[kept])).append_column("shared", pa.array(shared[kept]))

    def run(batches):
        for table in runs(batches, ("x", "y")):
            yield from cell(table).combine_chunks().to_batches()

    return run


def _frequent(groups: DataFrame) -> tuple:
    """Shingles that are frequent in a sample of classes, in order, and their levels."""
    total = max(1, groups.count())
    drawn = groups if total <= SAMPLE else groups.where(F.pmod(F.xxhash64("h1"), F.lit(total)) < SAMPLE)
    counts = with_set(drawn).select(F.explode_outer("set").alias("g")).groupBy("g").agg(F.count("*").alias("df")).where("df > 3")
    rows = counts.orderBy(F.desc("df"), "g").limit(FREQUENT).toArrow()
    g, df = rows.column("g").to_numpy(), rows.column("df").to_numpy()
    order = np.argsort(g)
    return g[order], (2 * np.log2(df[order])).astype(np.int64)


def _joined(groups: DataFrame, keys, n_keys: float, percent: int, sized: bool, sketched: bool, store: Store) -> DataFrame:
    """(a, b) of distinct classes that share a key; ``keys`` makes them from a batch of sets. Of many keys, those of one class alone do not move, and the others meet in rounds."""
    spark = groups.sparkSession
    # what the classes were made from
    store.free()
    buckets = max(spark.sparkContext.defaultParallelism, int(n_keys / BUCKET) + 1)
    if n_keys < FEW:
        blocks = with_set(groups).mapInArrow(_packed(keys, buckets, sketched), _BLOCKS)
        return blocks.repartition(buckets, "bucket").mapInArrow(_met(percent, sized), "a long, b long").distinct()
    keyed = store.keep(with_set(groups).mapInArrow(_keyed(keys, sketched), _KEYS), "keys")
    twice = spark.sparkContext.broadcast(_twice(keyed, n_keys))
    store.free()
    rounds = int(np.clip(n_keys // ROUND, 1, ROUNDS))
    # a round has few buckets, which more partitions hold apart
    parts = buckets if rounds == 1 else max(spark.sparkContext.defaultParallelism, 2 * -(-buckets // rounds))
    met = []
    for k in range(rounds):
        blocks = keyed.mapInArrow(_dealt(twice, buckets, k, rounds), _BLOCKS)
        met.append(store.keep(blocks.repartition(parts, "bucket").mapInArrow(_met(percent, sized), "a long, b long").distinct(), f"met{k}"))
        store.free()
    store.drop("keys")
    # a pair may have met in several rounds
    return met[0] if rounds == 1 else reduce(DataFrame.unionByName, met).distinct()


def _twice(keyed: DataFrame, n_keys: float) -> np.ndarray:
    """A bitmap of keys that two classes hold, and of some others that fall on the same bit as another one."""
    power = int(np.clip(np.ceil(np.log2(4 * n_keys + 1)), 16, SPOTS))
    parts = keyed.mapInArrow(_spots(power), "slice int, wide boolean, steps binary").repartition(SLICES, "slice").mapInArrow(_full(power), "slice int, bits binary").toArrow()
    out = np.zeros((SLICES, (1 << power) // SLICES // 8), np.uint8)
    for k, bits in zip(parts.column("slice").to_pylist(), parts.column("bits"), strict=True):
        out[k] = np.frombuffer(bits.as_buffer(), np.uint8)
    return out.reshape(-1)


def _spot(key: np.ndarray, power: int) -> np.ndarray:
    return (_mixed(key ^ np.uint64(0x5851F42D4C957F2D)) >> np.uint64(64 - power)).astype(np.int64)


def _spots(power: int):
    """Sorted spots of a task's keys by slice, as steps from one to the next."""
    per = (1 << power) // SLICES

    def run(batches):
        import pyarrow as pa

        held, count = [], 0

        def sent():
            spots = np.sort(_spot(np.concatenate(held), power))
            cuts = np.searchsorted(spots, np.arange(SLICES + 1) * per)
            out = []
            for k in range(SLICES):
                steps = np.diff(spots[cuts[k] : cuts[k + 1]], prepend=k * per)
                wide = bool(len(steps)) and int(steps.max()) > 0xFFFF
                out.append((k, wide, steps.astype(np.uint32 if wide else np.uint16).tobytes()))
            return pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*out, strict=True), (pa.int32(), pa.bool_(), pa.binary()), strict=True)], ["slice", "wide", "steps"])

        for batch in batches:
            for keys in batch.column("keys").to_pylist():
                held.append(np.frombuffer(keys, np.uint64))
                count += len(held[-1])
            if count >= BLOCK:
                yield sent()
                held, count = [], 0
        if held:
            yield sent()

    return run


def _full(power: int):
    per = (1 << power) // SLICES

    def run(batches):
        import pyarrow as pa

        # of each slice, the spots seen so far and those seen again
        seen: dict = {}
        for batch in batches:
            for k, wide, steps in zip(*(c.to_pylist() for c in batch.columns), strict=True):
                at = np.cumsum(np.frombuffer(steps, np.uint32 if wide else np.uint16).astype(np.int64))
                once, again = seen.setdefault(k, (np.zeros(per, bool), np.zeros(per, bool)))
                again[at[1:][at[1:] == at[:-1]]] = True
                again[at[once[at]]] = True
                once[at] = True
        for k, (_, again) in seen.items():
            yield pa.RecordBatch.from_arrays([pa.array([k], pa.int32()), pa.array([np.packbits(again, bitorder="little").tobytes()], pa.binary())], ["slice", "bits"])

    return run


def prefix_join(groups: DataFrame, percent: int = PERCENT, lengths: bool = True) -> DataFrame:
    """(a, b, sim) of class numbers, from rare shingles only: two sets above the threshold share one within their rarest n - ceil(t n) + 1. Exact.

    Any order that all sets share is as right as that of the true frequencies: frequent shingles are told by a sample, others go by their hash. With ``lengths`` a set meets only
    sets whose size allows the threshold.
    """
    total = groups.agg(F.sum(F.col("n") * (100 - percent) / 100 + 1)).first()[0] or 0
    frequent, store = groups.sparkSession.sparkContext.broadcast(_frequent(groups)), Store(groups.sparkSession, "join")
    return _verified(_joined(groups, _prefix(frequent, percent), float(total), percent, lengths, True, store), groups, percent, store)


def index_join(groups: DataFrame, percent: int = PERCENT) -> DataFrame:
    """The same answer through an inverted index of those shingles that decide, without regard to sizes; shared shingles are counted on whole sets.

    An index of all shingles would pair every two holders of a frequent one, the square of its postings, and find no more.
    """
    return prefix_join(groups, percent, lengths=False)


def minhash_join(groups: DataFrame, percent: int = PERCENT, bands: int = 24, rows: int = 4) -> DataFrame:
    """Pairs that share a band of ``rows`` minima, verified; misses a pair at 0.7 about once in 700."""
    store = Store(groups.sparkSession, "join")
    return _verified(_joined(groups, _bands(bands, rows), bands * groups.count(), percent, True, True, store), groups, percent, store)


def _mixed(v: np.ndarray) -> np.ndarray:
    """64 bits that do not follow from another's low or high ones (a finalizer of shifts and odd factors)."""
    v = (v ^ (v >> np.uint64(31))) * np.uint64(0x9E3779B97F4A7C15)
    v = (v ^ (v >> np.uint64(29))) * np.uint64(0xD6E8FEB86659FD93)
    return v ^ (v >> np.uint64(32))


def _prefix(frequent, percent: int):
    def keys(values: np.ndarray, row: np.ndarray, sizes: np.ndarray):
        known, levels = frequent.value
        level = np.zeros(len(values), np.int64)
        if len(known):
            at = np.minimum(np.searchsorted(known, values), len(known) - 1)
            level = np.where(known[at] == values, levels[at] + 1, 0)
        order = np.lexsort((values, level, row))
        start = np.cumsum(sizes) - sizes
        kept = np.arange(len(values)) - start[row] <= sizes[row] - -(-sizes[row] * percent // 100)
        order = order[kept]  # rows keep their places, as they are the first to sort by
        return values[order].view(np.uint64), row[order]

    return keys


def _bands(bands: int, rows: int):
    draw = np.random.default_rng(7)
    seeds = draw.integers(0, 2**63, bands * rows, dtype=np.uint64)

    def keys(values: np.ndarray, row: np.ndarray, sizes: np.ndarray):
        start, v, out = np.cumsum(sizes) - sizes, values.view(np.uint64), []
        for b in range(bands):
            key = np.full(len(sizes), b, np.uint64)
            for seed in seeds[b * rows : (b + 1) * rows]:
                key = _mixed(key + np.minimum.reduceat(_mixed(v ^ seed), start))
            out.append(key)
        return np.concatenate(out), np.tile(np.arange(len(sizes)), bands)

    return keys


def _keyed(keys, sketched: bool):
    """Of each class its keys, its size and, if asked for, a sketch whose bits are parities of the set's hashes."""

    def run(batches):
        import pyarrow as pa

        for batch in batches:
            lists = batch.column(1)
            sizes = np.diff(lists.offsets.to_numpy()).astype(np.int64)
            if not len(sizes):
                continue
            values = lists.flatten().to_numpy()
            row = np.repeat(np.arange(len(sizes)), sizes)
            key, at = keys(values, row, sizes)
            order = np.argsort(at, kind="stable")
            key, many = key[order], np.bincount(at, minlength=len(sizes))
            ends = np.cumsum(many)
            mixed = _mixed(values.view(np.uint64)) & np.uint64(64 * WORDS - 1)
            sketch = np.stack([np.bitwise_xor.reduceat(np.where(mixed >> np.uint64(6) == w, np.uint64(1) << (mixed & np.uint64(63)), np.uint64(0)), np.cumsum(sizes) - sizes) for w in range(WORDS)], 1)
            cut = [key[e - m : e].tobytes() for e, m in zip(ends, many, strict=True)]
            bits = [r.tobytes() for r in sketch] if sketched else [b""] * len(sizes)
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(sizes.astype(np.int32)), pa.array(bits, pa.binary()), pa.array(cut, pa.binary())], ["rep", "n", "sketch", "keys"])

    return run


def _packed(keys, buckets: int, sketched: bool):
    """Blocks of all keys."""
    made, dealt = _keyed(keys, sketched), _dealt(None, buckets)
    return lambda batches: dealt(made(batches))


def _dealt(twice, buckets: int, part: int = 0, rounds: int = 1):
    """Blocks of keys by bucket: the key's rest, its class, its size and sketch. With a bitmap, of those keys that two classes may hold; of several rounds, one's buckets."""

    def run(batches):
        import pyarrow as pa

        known = twice.value if twice else None
        power = int(len(known) * 8).bit_length() - 1 if twice else 0
        held, count = [], 0

        def sent():
            key, rep, n, sketch = (np.concatenate(c) for c in zip(*held, strict=True))
            bucket = (_mixed(key) % np.uint64(buckets)).astype(np.int32)
            order = np.argsort(bucket, kind="stable")
            found, start = np.unique(bucket[order], return_index=True)
            parts = [order[a:b] for a, b in zip(start, [*start[1:], len(order)], strict=True)]
            cut = lambda c: pa.array([c[p].tobytes() for p in parts], pa.binary())
            return pa.RecordBatch.from_arrays([pa.array(found, pa.int32()), cut((key >> np.uint64(32)).astype(np.uint32)), cut(rep), cut(n), cut(sketch)], ["bucket", "g", "rep", "n", "sketch"])

        for batch in batches:
            lists = batch.column("keys").to_pylist()
            many = np.array([len(k) // 8 for k in lists], np.int64)
            key = np.frombuffer(b"".join(lists), np.uint64)
            kept = np.ones(len(key), bool)
            if twice:
                spot = _spot(key, power)
                kept = (known[spot >> 3] >> (spot & 7).astype(np.uint8)) & 1 == 1
            if rounds > 1:
                kept &= _mixed(key) % np.uint64(buckets) % np.uint64(rounds) == part
            at = np.repeat(np.arange(len(many)), many)[kept]
            if not len(at):
                continue
            bits = np.frombuffer(b"".join(batch.column("sketch").to_pylist()), np.uint64).reshape(len(many), -1)
            held.append((key[kept], batch.column("rep").to_numpy()[at], batch.column("n").to_numpy()[at], bits[at]))
            count += len(at)
            if count >= BLOCK:
                yield sent()
                held, count = [], 0
        if held:
            yield sent()

    return run


def _met(percent: int, sized: bool):
    """Pairs of classes that share a key of a bucket, whose sizes and sketches allow the threshold.

    Sets that differ in d shingles differ in at most d bits of their sketches, so no pair above the threshold is lost.
    """

    def run(batches):
        import pyarrow as pa

        parts = [r for batch in batches for r in zip(*(c.to_pylist() for c in batch.columns), strict=True)]
        read = lambda k, kind: np.concatenate([np.frombuffer(p[k], kind) for p in parts])
        if not parts:
            return
        rest, rep, n = read(1, np.uint32), read(2, np.int64), read(3, np.int32).astype(np.int64)
        key = (np.repeat(np.array([p[0] for p in parts], np.uint64), [len(p[1]) // 4 for p in parts]) << np.uint64(32)) | rest
        sketch = read(4, np.uint64).reshape(len(key), -1)
        parts.clear()
        order = np.lexsort((n, key))
        key, rep, n, sketch = key[order], rep[order], n[order], sketch[order]
        number = np.cumsum(np.concatenate([[0], key[1:] != key[:-1]])).astype(np.int64)
        most = n * 100 // percent if sized else np.full(len(n), (1 << 31) - 1)
        partners = np.searchsorted((number << 32) | n, (number << 32) | np.minimum(most, (1 << 32) - 1), "right") - np.arange(len(n)) - 1
        total = np.cumsum(partners)
        begin = 0
        while begin < len(n):
            end = max(begin + 1, int(np.searchsorted(total, (total[begin - 1] if begin else 0) + STEP, "right")))
            many = partners[begin:end]
            i = np.repeat(np.arange(begin, end), many)
            j = i + 1 + np.arange(len(i)) - np.repeat(np.cumsum(many) - many, many)
            begin = end
            for w in range(sketch.shape[1]):
                part = np.bitwise_count(sketch[i, w] ^ sketch[j, w]).astype(np.int64)
                apart = part if not w else apart + part
            if sketch.shape[1]:
                near = apart <= (n[i] + n[j]) * (100 - percent) // (100 + percent)
                i, j = i[near], j[near]
            a, b = np.minimum(rep[i], rep[j]), np.maximum(rep[i], rep[j])
            pair = np.unique(np.stack([a, b], 1)[a < b], axis=0) if len(a) < 1000 else _once(a, b)
            if len(pair):
                yield pa.RecordBatch.from_arrays([pa.array(pair[:, 0]), pa.array(pair[:, 1])], ["a", "b"])

    return run


def _once(a: np.ndarray, b: np.ndarray) -> np.ndarray:
    order = np.lexsort((b, a))
    a, b = a[order], b[order]
    new = np.concatenate([[True], (a[1:] != a[:-1]) | (b[1:] != b[:-1])]) & (a < b)
    return np.stack([a[new], b[new]], 1)


def reaching(sets: DataFrame, other: DataFrame, percent: int = PERCENT) -> DataFrame:
    """Rows of ``sets`` that hold enough shingles of any of ``other`` to be similar to one: the threshold's share of their own. Exact, as collisions only keep more."""
    one = lambda df: df.select(F.split("words", " ").alias("w")).select(F.explode_outer(_set(F.col("w"))).alias("g"))
    spots = one(other).select(F.pmod("g", F.lit(BITMAP)).cast("int").alias("spot")).distinct().toArrow().column("spot").to_numpy()
    bitmap = np.zeros(BITMAP // 8, np.uint8)
    np.bitwise_or.at(bitmap, spots >> 3, (1 << (spots & 7)).astype(np.uint8))
    known = sets.sparkSession.sparkContext.broadcast(bitmap)
    return sets.withColumn("w", F.split("words", " ")).withColumn("set", _set(F.col("w"))).drop("w").mapInArrow(_reached(known, percent), sets.schema)


def _reached(known, percent: int):
    def run(batches):
        import pyarrow as pa

        for batch in batches:
            lists = batch.column("set")
            sizes = np.diff(lists.offsets.to_numpy())
            spots = lists.flatten().to_numpy() % BITMAP
            hit = (known.value[spots >> 3] >> (spots & 7)) & 1
            held = np.add.reduceat(hit.astype(np.int64), np.cumsum(sizes) - sizes) if len(sizes) else sizes
            yield batch.drop_columns(["set"]).filter(pa.array(held * 100 >= sizes * percent))

    return run


def named(pairs: DataFrame, groups: DataFrame) -> DataFrame:
    """Pairs of class numbers as pairs of first ids, the smaller one first: a, b, sim."""
    one, two = groups.select(F.col("rep").alias("a"), F.col("first").alias("x")), groups.select(F.col("rep").alias("b"), F.col("first").alias("y"))
    return pairs.join(one, "a").join(two, "b").select(F.least("x", "y").alias("a"), F.greatest("x", "y").alias("b"), "sim")


def both_ways(pairs: DataFrame, groups: DataFrame) -> DataFrame:
    """(rep, other) of similar classes in both directions, each class beside itself too."""
    one = pairs.select(F.col("a").alias("rep"), F.col("b").alias("other"))
    return one.unionByName(pairs.select(F.col("b").alias("rep"), F.col("a").alias("other"))).unionByName(groups.select("rep", F.col("rep").alias("other")))


def unit_links(sets: DataFrame, groups: DataFrame, pairs: DataFrame) -> DataFrame:
    """(id, first, n_links): other units similar to each one, copies included."""
    size = groups.select(F.col("rep").alias("other"), "n_members")
    linked = both_ways(pairs, groups).join(size, "other").groupBy("rep").agg(F.sum("n_members").alias("linked"))
    per = groups.join(linked, "rep").select("h1", "h2", "first", (F.col("linked") - 1).alias("n_links"))
    return sets.join(per, ["h1", "h2"]).select("id", "first", "n_links")
