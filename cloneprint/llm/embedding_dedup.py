"""Embedding near-dedup with an inverted multi-index.

Vectors are scaled to length 1 and halved; each half has its own codebook, and a pair of codes is a cell of the product grid. Every
vector lies in its home cell and visits cells in the order of the sum of its halves' distances (multi-sequence traversal), as many as reach the
target recall. All pairs found are verified by cosine in double precision.

Of two cells one side does the visiting, by a rule on their numbers (``asks``), so a pair of vectors is looked at once and counts for both
ends. The codebooks are fitted on about ``FIT_ROWS`` vectors, drawn by a hash; the number of visits is the one that finds
``recall`` of pairs at exactly the threshold, made from the sample by turning its vectors away at random and towards one another. The number of
codes grows with the table: the choice is the one with the least cost, of copies sent and products taken together (``_cost``).

Equal vectors of one label are one class from the start, with a count. Members of a cell are dealt to chunks of about ``CHUNK``, and every
chunk of a cell is a group of its own, so a cell that holds most of the data is work for many tasks; a task holds one chunk and a block of
visitors at a time. It sends on a count per vector and a spanning forest of the links, never the pairs.

Defined cases: vectors that are null, empty, zero, or hold null or non-finite components, and those with a null label or vec_id, link with nothing; so do
vectors of different lengths, however many lengths there are (a length too rare for the sample has one cell). Rows that repeat a vec_id are each a vector
that others link with, and are one component. Empty tables give no rows; other columns are ignored.
"""

from __future__ import annotations

import heapq
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.types import FloatType

from .common import Scratch, connected_components

COSINE, RECALL, FIT_ROWS, CHUNK, BLOCK = 0.93, 0.99, 10_000, 512, 1024
CODES = (4, 8, 16, 32, 64, 128, 256, 512)  # codes a half may have
#: seconds of one copy of a kilobyte through a shuffle, and of one multiplication
COPY_SECONDS, PRODUCT_SECONDS = 5e-5, 2.5e-10


def _kmeans(x: np.ndarray, k: int, rounds: int = 12) -> np.ndarray:
    rng = np.random.default_rng(11)
    centre = x[rng.choice(len(x), min(k, len(x)), replace=False)].copy()
    for _ in range(rounds):
        near = _distances(x, centre).argmin(axis=1)
        for c in range(len(centre)):
            if (near == c).any():
                centre[c] = x[near == c].mean(axis=0)
    return centre


def _distances(x: np.ndarray, centre: np.ndarray) -> np.ndarray:
    return np.maximum((x**2).sum(axis=1)[:, None] - 2 * x @ centre.T + (centre**2).sum(axis=1), 0)


def multi_sequence(a: np.ndarray, b: np.ndarray, n: int) -> list[tuple[int, int]]:
    """The n pairs (i, j) with the smallest a[i] + b[j], nearest first."""
    p, q = np.argsort(a, kind="stable"), np.argsort(b, kind="stable")
    heap, pushed, out = [(a[p[0]] + b[q[0]], 0, 0)], {(0, 0)}, []
    while heap and len(out) < n:
        _, i, j = heapq.heappop(heap)
        out.append((int(p[i]), int(q[j])))
        for s, t in ((i + 1, j), (i, j + 1)):
            if s < len(p) and t < len(q) and (s, t) not in pushed:
                pushed.add((s, t))
                heapq.heappush(heap, (a[p[s]] + b[q[t]], s, t))
    return out


def asks(one: np.ndarray, two: np.ndarray) -> np.ndarray:
    """Whether members of cell ``one`` visit cell ``two`` rather than the other way; each cell asks about half of the others."""
    return (one < two) ^ ((one + two) % 2 == 1)


@dataclass
class MultiIndex:
    left: np.ndarray
    right: np.ndarray
    visits: int = 1

    @classmethod
    def fit(cls, x: np.ndarray, codes: int, cosine: float, recall: float) -> MultiIndex:
        """Codebooks of a sample of unit vectors, and the visits that find ``recall`` of its pairs at the threshold."""
        half = x.shape[1] // 2
        index = cls(_kmeans(x[:, :half], codes), _kmeans(x[:, half:], codes))
        rng = np.random.default_rng(5)
        ranks = []
        for towards in (rng.normal(size=x.shape), x[rng.permutation(len(x))]):
            away = towards - (towards * x).sum(axis=1, keepdims=True) * x
            size = np.sqrt((away * away).sum(axis=1, keepdims=True))
            fine = size[:, 0] > 1e-9
            near = cosine * x[fine] + np.sqrt(1 - cosine**2) * away[fine] / size[fine]
            one, two = index.home(x[fine]), index.home(near)
            swap = asks(two, one)
            for at in range(0, len(near), BLOCK):
                part, turn = slice(at, at + BLOCK), swap[at : at + BLOCK, None]
                order = index.order(np.where(turn, near[part], x[fine][part]))
                goal = np.where(turn[:, 0], one[part], two[part])
                ranks.append(np.argmax(order == goal[:, None], axis=1) + 1)
        ranks = np.concatenate(ranks) if ranks else np.ones(1, int)
        index.visits = int(np.quantile(ranks, recall, method="higher")) if len(ranks) else 1
        return index

    def home(self, x: np.ndarray) -> np.ndarray:
        half = x.shape[1] // 2
        return _distances(x[:, :half], self.left).argmin(axis=1) * len(self.right) + _distances(x[:, half:], self.right).argmin(axis=1)

    def order(self, x: np.ndarray, n: int | None = None) -> np.ndarray:
        """The first n cells that each vector visits: ``multi_sequence`` of many vectors at once.

        The n-th cell in order lies at ranks (i, j) with (i + 1)(j + 1) <= n, so only these sums are taken.
        """
        half, every = x.shape[1] // 2, len(self.left) * len(self.right)
        n = min(n or every, every)
        a, b = _distances(x[:, :half], self.left), _distances(x[:, half:], self.right)
        p, q = np.argsort(a, axis=1, kind="stable")[:, :n], np.argsort(b, axis=1, kind="stable")[:, :n]
        i, j = (k.ravel() for k in np.indices((p.shape[1], q.shape[1])))
        some = (i + 1) * (j + 1) <= n
        i, j = i[some], j[some]
        total = np.take_along_axis(a, p, 1)[:, i] + np.take_along_axis(b, q, 1)[:, j]
        # as the nearest codes of both halves, the home cell is first whatever sums are equal
        first = np.argsort(total, axis=1, kind="stable")[:, :n]
        return np.take_along_axis(p, i[first], 1) * len(self.right) + np.take_along_axis(q, j[first], 1)


def _cost(index: MultiIndex, dims: int, n: float, squares: float) -> float:
    """Seconds for n vectors in labels whose sizes have the given sum of squares."""
    cells = len(index.left) * len(index.right)
    looks = (index.visits + 1) / 2
    return n * looks * dims / 256 * COPY_SECONDS + squares / cells * looks * dims * PRODUCT_SECONDS


def choose(x: np.ndarray, n: float, squares: float, cosine: float, recall: float) -> MultiIndex | None:
    """The index of least cost for a sample ``x`` of n vectors; none for a sample too small for the smallest codebooks."""
    best, cost = None, 0.0
    for codes in CODES:
        if len(x) < 16 * codes or x.shape[1] < 2:
            break
        index = MultiIndex.fit(x, codes, cosine, recall)
        seconds = _cost(index, x.shape[1], n, squares)
        if best is not None and seconds >= cost:
            break
        best, cost = index, seconds
    return best


def _unit(x: np.ndarray) -> np.ndarray:
    """Rows scaled to length 1; first by their largest component, so that squares neither vanish nor overflow."""
    x = x.astype(np.float64)
    x /= np.abs(x).max(axis=1, keepdims=True)
    return x / np.sqrt((x * x).sum(axis=1, keepdims=True))


def _packed(kind: str):
    """Rows (vec_id, embedding, label): the vector's bytes, null if it links with nothing."""

    def run(batches):
        for batch in batches:
            lists = batch.column(1)
            size = pc.fill_null(pc.list_value_length(lists), 0).to_numpy(zero_copy_only=False).astype(np.int64)
            flat = lists.flatten()
            v = flat.to_numpy(zero_copy_only=False).astype(kind)
            end = np.cumsum(size)
            start = end - size
            bad, some = (np.concatenate(([0], np.cumsum(m))) for m in (~np.isfinite(v), v != 0))
            fine = (size > 0) & (bad[end] == bad[start]) & (some[end] > some[start])
            fine &= ~(np.asarray(batch.column(0).is_null()) | np.asarray(batch.column(2).is_null()))
            offsets = np.concatenate(([0], end)).astype(np.int32) * np.int32(v.itemsize)
            mask = pa.py_buffer(np.packbits(fine, bitorder="little").tobytes())
            x = pa.Array.from_buffers(pa.binary(), len(size), [mask, pa.py_buffer(offsets.tobytes()), pa.py_buffer((v + v.dtype.type(0)).tobytes())])
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(2), x], ["vec_id", "label", "x"])

    return run


def _matrix(column, kind: str, dims: int) -> np.ndarray:
    """A binary column of vectors of one length as unit rows."""
    return _unit(np.frombuffer(b"".join(column.to_pylist()), kind).reshape(-1, dims))


def _spread(handle, kind: str, homes_only: bool):
    """Rows (dims, label, id, n, x): a row for the home cell and each visit (``home``: the vector's own cell)."""

    def run(batches):
        indexes: dict[int, MultiIndex] = handle.value
        for batch in batches:
            every = batch.column(0).to_numpy()
            for dims in np.unique(every).tolist():
                rows = np.flatnonzero(every == dims)
                index = indexes.get(dims)
                for at in range(0, len(rows), 4 * BLOCK):
                    part = batch.take(pa.array(rows[at : at + 4 * BLOCK]))
                    row = np.arange(part.num_rows)
                    if index is None:
                        home = cell = np.zeros(len(row), np.int64)
                    else:
                        order = index.order(_matrix(part.column(4), kind, dims), 1 if homes_only else index.visits)
                        goes = asks(order[:, :1], order)
                        goes[:, 0] = True
                        row, column = np.nonzero(goes)
                        home, cell = order[row, 0], order[row, column]
                    sent = part.take(pa.array(row))
                    arrays = [pa.array(home.astype(np.int32)), pa.array(cell.astype(np.int32))]
                    yield pa.RecordBatch.from_arrays([*sent.columns[: 2 if homes_only else 5], *arrays], [*sent.schema.names[: 2 if homes_only else 5], "home", "cell"])

    return run


def _linked(q: tuple, h: tuple, cosine: float, same: bool):
    """Links of two groups (id, n, unit rows), or of one with itself: rows of id, root in a spanning forest, links found."""
    near = q[2] @ h[2].T >= cosine
    if same:
        near = np.triu(near, 1)
    i, j = np.nonzero(near)
    if not len(i):
        return None
    found, back = near @ h[1], near.T @ q[1]
    node = np.concatenate((q[0], h[0]))
    if same:
        node, found, j = q[0], found + back, j
    else:
        found, j = np.concatenate((found, back)), j + len(q[0])
    root = node.copy()
    while True:  # smallest id reachable inside the group, spread until it settles
        was = root.copy()
        np.minimum.at(root, j, root[i])
        np.minimum.at(root, i, root[j])
        if (root == was).all():
            break
    hit = found > 0
    return node[hit], root[hit], found[hit]


def _compare(kind: str, cosine: float):
    """Rows (dims, label, cell, chunk, visitor, id, n, x) in this order: the members of a chunk, then its visitors."""

    def run(batches):
        key, members, visitors, waiting = None, [], [], 0
        out: list[tuple] = []

        def joined(parts):
            return tuple(np.concatenate(c) for c in zip(*parts, strict=True))

        def settle(last: bool):
            nonlocal members, visitors, waiting
            if len(members) > 1:
                members = [joined(members)]
            if members and visitors:
                out.append(_linked(joined(visitors), members[0], cosine, False))
            visitors, waiting = [], 0
            if last and members:
                out.append(_linked(members[0], members[0], cosine, True))

        def sent():
            rows = [r for r in out if r is not None]
            out.clear()
            if rows:
                return pa.RecordBatch.from_arrays([pa.array(c) for c in joined(rows)], ["a", "b", "links"])

        for batch in batches:
            columns = [batch.column(k).to_numpy() for k in range(7)]
            keys = np.stack([c.astype(np.int64) for c in columns[:5]])
            cuts = np.concatenate(([0], np.flatnonzero((keys[:, 1:] != keys[:, :-1]).any(axis=0)) + 1, [batch.num_rows]))
            for a, b in zip(cuts[:-1].tolist(), cuts[1:].tolist(), strict=True):
                now = tuple(keys[:4, a].tolist())
                if now != key:
                    settle(True)
                    key, members = now, []
                visiting = bool(keys[4, a])
                for s in range(a, b, BLOCK):
                    e = min(b, s + BLOCK)
                    part = (columns[5][s:e], columns[6][s:e], _matrix(batch.column(7).slice(s, e - s), kind, now[0]))
                    (visitors if visiting else members).append(part)
                    waiting += (e - s) * visiting
                    if waiting >= BLOCK:
                        settle(False)
            if (rows := sent()) is not None:
                yield rows
        settle(True)
        if (rows := sent()) is not None:
            yield rows

    return run


def _indexes(classes: DataFrame, kind: str, cosine: float, recall: float) -> dict[int, MultiIndex]:
    """An index per vector length that the sample holds enough of."""
    sizes = classes.groupBy("dims", "label").agg(F.count("*").alias("m")).groupBy("dims").agg(F.sum("m").alias("n"), F.sum(F.col("m").cast("double") * F.col("m")).alias("squares"))
    total = classes.count()
    if not total:
        return {}
    share = F.pmod(F.xxhash64("x"), F.lit(1 << 40)) < int((1 << 40) * min(1.0, FIT_ROWS / total))
    drawn = classes.where(share).select("dims", "x").limit(2 * FIT_ROWS).collect()  # about FIT_ROWS by the share; the limit is a guard
    held: dict[int, list[bytes]] = {}
    for r in drawn:
        held.setdefault(r["dims"], []).append(bytes(r["x"]))
    wanted = [d for d, rows in held.items() if len(rows) >= 16 * CODES[0]]  # at most FIT_ROWS / 64 lengths
    out = {}
    for r in sizes.where(F.col("dims").isin(wanted)).collect() if wanted else ():
        x = _unit(np.frombuffer(b"".join(sorted(held[r["dims"]])), kind).reshape(-1, r["dims"]))
        if (index := choose(x, r["n"], r["squares"], cosine, recall)) is not None:
            out[r["dims"]] = index
    return out


def near_duplicates(vectors: DataFrame, cosine: float = COSINE, recall: float = RECALL, chunk: int = CHUNK) -> DataFrame:
    """vec_id, n_links, component_id, kept of every row; columns vec_id, embedding, label are read."""
    spark = vectors.sparkSession
    scratch = Scratch(spark, "embedding")
    narrow = isinstance(vectors.schema["embedding"].dataType.elementType, FloatType)
    kind = "<f4" if narrow else "<f8"
    base = vectors.select(F.col("vec_id").cast("long").alias("vec_id"), F.col("embedding").cast(f"array<{'float' if narrow else 'double'}>").alias("v"), F.col("label").cast("int").alias("label"))
    whole = scratch.keep(base.mapInArrow(_packed(kind), "vec_id long, label int, x binary").withColumn("d", F.unhex(F.md5("x"))), "whole", batch=2000)
    # a class of equal vectors; ids may repeat, so classes get numbers of their own when they are written
    same = whole.where("x is not null").groupBy("label", "x").agg(F.min("vec_id").alias("first"), F.count("*").alias("n"))
    width = np.dtype(kind).itemsize
    classes = scratch.keep(same.select(F.monotonically_increasing_id().alias("id"), "label", "first", "n", F.unhex(F.md5("x")).alias("d"), "x", F.floor(F.octet_length("x") / width).cast("int").alias("dims")), "classes")
    handle = spark.sparkContext.broadcast(_indexes(classes, kind, cosine, recall))  # bounded by the codebooks' largest size

    rows = classes.select("dims", "label", "id", "n", "x")
    cells = rows.mapInArrow(_spread(handle, kind, True), "dims int, label int, home int, cell int").groupBy("dims", "label", "cell").agg(F.count("*").alias("m"))
    large = scratch.keep(cells.where(F.col("m") > chunk).select("dims", "label", "cell", F.ceil(F.col("m") / chunk).cast("int").alias("chunks")), "large")
    sent = rows.mapInArrow(_spread(handle, kind, False), "dims int, label int, id long, n long, x binary, home int, cell int").join(large, ["dims", "label", "cell"], "left")
    # members go to one chunk and visit those chunks of their cell that do not visit theirs; visitors go to all chunks
    mine, to = F.pmod(F.xxhash64("id"), F.col("chunks")).cast("int"), F.sequence(F.lit(0), F.col("chunks") - 1)
    inside = F.transform(F.filter(to, lambda k: (k == mine) | ((mine < k) != ((mine + k) % 2 == 1))), lambda k: F.struct(k.alias("chunk"), (k != mine).alias("visitor")))
    across = F.transform(to, lambda k: F.struct(k.alias("chunk"), F.lit(True).alias("visitor")))
    one = F.array(F.struct(F.lit(0).alias("chunk"), (F.col("home") != F.col("cell")).alias("visitor")))
    place = F.when(F.col("chunks").isNull(), one).when(F.col("home") == F.col("cell"), inside).otherwise(across)
    dealt = sent.select("dims", "label", "cell", "id", "n", "x", F.explode(place).alias("p")).select("dims", "label", "cell", "p.chunk", "p.visitor", "id", "n", "x")
    key = ("dims", "label", "cell", "chunk")
    dealt = dealt.repartition(*key).sortWithinPartitions(*key, "visitor").withColumn("visitor", F.col("visitor").cast("int"))
    links = scratch.keep(dealt.mapInArrow(_compare(kind, cosine), "a long, b long, links long"), "links", batch=2000)

    # rows that repeat a vec_id join their classes
    of = scratch.keep(whole.join(classes.select("id", "label", "d", "first", "n"), ["label", "d"], "left").select("vec_id", "id", "first", "n"), "of")
    again = of.where("id is not null").groupBy("vec_id").agg(F.min("id").alias("a"), F.max("id").alias("z")).where("a < z").select("vec_id", "a")
    again = of.join(again, "vec_id").where("id <> a").select("a", F.col("id").alias("b")).distinct()
    label = connected_components(links.where("a <> b").select("a", "b").unionByName(again), scratch)
    root = classes.select(F.col("id").alias("node"), "first").join(label, "node").groupBy("label").agg(F.min("first").alias("root"))
    root = label.join(root, "label").select(F.col("node").alias("id"), "root")
    counts = links.groupBy(F.col("a").alias("id")).agg(F.sum("links").alias("links"))
    known = scratch.keep(root.join(counts, "id", "full"), "known")
    scratch.drop("whole", "classes", "large", "links")
    component = F.coalesce("root", "first", "vec_id")
    n_links = F.coalesce(F.coalesce("links", F.lit(0)) + F.col("n") - 1, F.lit(0)).cast("long")
    return of.join(known, "id", "left").select("vec_id", n_links.alias("n_links"), component.alias("component_id"), F.coalesce(component == F.col("vec_id"), F.lit(True)).alias("kept"))
