"""Each operator against brute force on small data with nulls, empty and long texts, repeated rows, empty tables and extra columns."""

import base64
import hashlib
import random
import re
import zlib
from collections import defaultdict

import numpy as np
import pytest
from pyspark.sql import functions as F

SF = "/root/testdata/sf0.001"
rng = random.Random(4)
VOCAB = [f"w{k}" for k in range(400)]


def prose(n):
    return " ".join(rng.choice(VOCAB) for _ in range(n))


@pytest.fixture(scope="module")
def texts():
    base = [prose(n) for n in (3, 8, 60, 200, 200, 1000)]
    out = [None, "", "   \n", "A b", "a B", *base]
    for b in base:
        w = b.split()
        out += [b, b.upper(), " ".join(w[: len(w) // 2] + ["new"] + w[len(w) // 2 :]), " ".join(w[: len(w) // 3])]
    return out + [prose(30_000), "x" * 300_000]


@pytest.fixture(scope="module")
def docs(spark, texts):
    rows = [(k, t, "en", "s", 0, "extra") for k, t in enumerate(texts)] + [(4, texts[4], "en", "s", 0, "extra"), (None, texts[7], None, None, None, None)]
    return spark.createDataFrame(rows, "doc_id long, text string, lang string, source string, n_chars long, key string")


def empty(df):
    return df.limit(0)


def roots(n, links):
    parent = list(range(n))

    def find(x):
        while parent[x] != x:
            x = parent[x]
        return x

    for a, b in links:
        a, b = find(a), find(b)
        parent[max(a, b)] = min(a, b)
    return [find(k) for k in range(n)]


def shingles(text):
    w = re.findall(r"[^\x20\x09-\x0D]+", "".join(c.lower() if "A" <= c <= "Z" else c for c in text or ""))
    return set(zip(*[w[k:] for k in range(5)], strict=False)) if len(w) >= 5 else ({tuple(w)} if w else set())


def test_minhash(docs, texts):
    from cloneprint.llm import minhash_dedup as M

    sets = [shingles(t) for t in texts]
    links = [(a, b) for a in range(len(texts)) for b in range(a) if sets[a] and sets[b] and 100 * len(sets[a] & sets[b]) >= 75 * len(sets[a] | sets[b])]
    want = roots(len(texts), links)
    got = M.near_duplicates(docs).collect()
    assert len(got) == docs.count()
    for r in got:
        if r["doc_id"] is None:
            assert r["component_id"] is None and r["kept"]
        else:
            assert (r["component_id"], r["kept"], r["n_shingles"]) == (want[r["doc_id"]], want[r["doc_id"]] == r["doc_id"], len(sets[r["doc_id"]]))
    assert M.near_duplicates(empty(docs)).count() == 0


def test_minhash_chain_and_large_group(spark):
    """Links along a chain join its ends; a group beyond the size of a large component stays whole."""
    from cloneprint.llm import minhash_dedup as M

    w = [f"c{k}" for k in range(60)]
    chain = [" ".join(w[k : k + 40]) for k in range(0, 12, 2)]
    base = prose(80).split()
    group = []
    for _ in range(120):
        t = list(base)
        for p in rng.sample(range(80), 1):
            t[p] = f"n{rng.random()}"
        group.append(" ".join(t))
    every = chain + group
    sets = [shingles(t) for t in every]
    want = roots(len(every), [(a, b) for a in range(len(every)) for b in range(a) if 100 * len(sets[a] & sets[b]) >= 75 * len(sets[a] | sets[b])])
    got = {r["doc_id"]: r["component_id"] for r in M.near_duplicates(spark.createDataFrame(list(enumerate(every)), "doc_id long, text string")).collect()}
    assert [got[k] for k in range(len(every))] == want


def test_minhash_ids_with_several_texts_and_repeats(spark):
    """Each text of an id is compared; the id joins what its texts link with; repeated rows change nothing."""
    from cloneprint.llm import minhash_dedup as M

    r = random.Random(3)
    base = [[f"v{r.randrange(90)}" for _ in range(r.randint(20, 60))] for _ in range(60)]
    rows = []
    for k in range(400):
        w = list(r.choice(base))
        for _ in range(r.randint(0, 2)):
            w[r.randrange(len(w))] = f"x{r.randrange(9)}"
        rows.append((k if k % 5 else k // 5 + 1000 * (k % 2), " ".join(w)))
    rows += [rows[7]] * 30 + [(3, rows[40][1]), (3, rows[200][1])]
    sets = [shingles(t) for _, t in rows]
    links = [(a, b) for a in range(len(rows)) for b in range(a) if rows[a][0] == rows[b][0] or 100 * len(sets[a] & sets[b]) >= 75 * len(sets[a] | sets[b])]
    root = roots(len(rows), links)
    low = defaultdict(lambda: 1 << 60)
    for k, (d, _) in enumerate(rows):
        low[root[k]] = min(low[root[k]], d)
    want = {d: low[root[k]] for k, (d, _) in enumerate(rows)}
    got = M.near_duplicates(spark.createDataFrame(rows, "doc_id long, text string").repartition(5)).collect()
    assert len(got) == len(rows) and all(q["component_id"] == want[q["doc_id"]] for q in got)


def test_components(spark):
    from cloneprint.llm.common import Scratch, connected_components

    edges = [(a, a + 1) for a in range(100, 160)] + [(1, k) for k in range(2, 50)] + [(7, 300), (5, 5)]
    got = {r["node"]: r["label"] for r in connected_components(spark.createDataFrame(edges, "a long, b long").where("a <> b").repartition(7), Scratch(spark, "t")).collect()}
    assert all(got[k] == 100 for k in range(100, 161)) and all(got[k] == 1 for k in range(1, 50)) and got[300] == 1


def test_token_ids_and_packing(docs, texts):
    from tokenizers import Tokenizer

    from cloneprint.llm import encode, packing, token_ids

    path = encode.public_path()
    odd = ["a  b", "x <|endoftext|> y", " lead", "tail ", "tab\t x\n\n  y", "it's  '' ok", "é　b 漢字 ×a aÃ÷ ŉ", "A" * 1000 + " b " * 3]
    lib = Tokenizer.from_file(path)
    ids = lambda t: np.array(lib.encode(t or "", add_special_tokens=False).ids, "<u4")
    every = [t or "" for t in texts] + odd
    assert encode.encoder(path).ids(every) == [ids(t).tobytes() for t in every]
    at = 0
    for r in sorted(token_ids.round_trip(docs, path).collect(), key=lambda r: (r["doc_id"] is not None, r["doc_id"], r["start"])):
        t = np.append(ids(texts[7 if r["doc_id"] is None else r["doc_id"]]), 2).astype("<u4")
        assert (r["start"], r["n_tokens"], r["ids_crc32"]) == (at, len(t), zlib.crc32(t.tobytes()))
        at += len(t)
    seqs = defaultdict(list)
    for r in packing.pack(docs, path).collect():
        t = np.append(ids(texts[7 if r["doc_id"] is None else r["doc_id"]]), 0).astype("<u4")
        assert r["doc_tokens"] == len(t) and zlib.crc32(t[r["start"] : r["start"] + r["length"]].tobytes()) == r["ids_crc32"]
        seqs[r["sequence_id"]].append((r["offset"], r["length"]))
    for parts in seqs.values():
        end = 0
        for a, n in sorted(parts):
            assert a == end
            end += n
        assert end <= 1024
    assert sorted(seqs) == list(range(len(seqs)))
    assert token_ids.round_trip(empty(docs), path).count() == packing.pack(empty(docs), path).count() == 0


def test_token_ids_of_texts_without_a_place_to_cut():
    from cloneprint.llm import encode
    from tokenizers import Tokenizer

    path = encode.public_path()
    lines, solid = prose(600_000).replace(" ", "\n"), "".join(prose(700_000).split())
    texts = [lines, "a b", solid, prose(200_000) + " " + lines, "  ".join(prose(300_000).split()), " " * (3 << 20), "語" * (1 << 20)]
    assert all(len(t.encode()) > 2 * encode.GROUP for t in texts if t != "a b")
    lib = Tokenizer.from_file(path)
    want = [np.array(lib.encode(t, add_special_tokens=False).ids, "<u4").tobytes() for t in texts]
    assert encode.encoder(path).ids(texts) == want


def test_workers_hold_no_encoder_and_no_free_memory(spark):
    from cloneprint.llm import common, encode, packing

    packing.pack(spark.createDataFrame([(k, f"word {k}") for k in range(40)], "doc_id long, text string").repartition(4), encode.public_path()).collect()

    def left(batches):
        import pyarrow as pa

        from cloneprint.llm import encode as e

        for batch in batches:
            yield pa.RecordBatch.from_arrays([pa.array([len(e._loaded)] * batch.num_rows, pa.int64())], ["n"])

    assert {r["n"] for r in spark.range(64).repartition(8).mapInArrow(left, "n long").collect()} == {0}

    def resident():
        with open("/proc/self/statm") as f:
            return int(f.read().split()[1]) * 4096

    def run(batches):
        held = [bytes(50_000) for _ in range(10_000)]
        yield from batches
        yield resident()
        del held

    (large,) = common.lean(run)([])
    assert resident() < large - 300_000_000


@pytest.mark.parametrize("bits", [1, 5, 16, 17, 31])
def test_bit_packing(bits, tmp_path):
    from cloneprint.llm import token_ids as T

    ids = np.random.default_rng(bits).integers(0, 1 << bits, 20_000, dtype=np.uint64).astype("<u4")
    assert (T.unpack_bits(T.pack_bits(ids, bits), bits, len(ids)) == ids).all()
    w = T.Writer(str(tmp_path / "f.ids"), bits)
    for k, part in enumerate(np.split(ids, [0, 3, 9000])):
        w.add(k, part)
    w.close()
    r = T.Reader(str(tmp_path / "f.ids"))
    assert (r.document(3)[1] == ids[9000:]).all() and len(r.document(0)[1]) == 0 and (r.ids(8190, 10) == ids[8190:8200]).all()
    assert T.width(50257) == 16 and T.width(1) == 1


def test_best_fit_decreasing_matches_plain_version():
    from collections import Counter

    from cloneprint.llm.packing import best_fit_decreasing

    for seed in range(20):
        r = random.Random(seed)
        sizes = [r.randint(1, 64) for _ in range(r.randint(0, 300))]
        rules, opened = best_fit_decreasing(dict(Counter(sizes)), 64)
        free = []
        for s in sorted(sizes, reverse=True):
            fits = [k for k, f in enumerate(free) if f >= s]
            if fits:
                free[min(fits, key=lambda k: free[k])] -= s
            else:
                free.append(64 - s)
        assert opened == len(free)
        fill, placed = defaultdict(list), Counter()
        for length, lo, hi, per, first, offset in rules:
            for k in range(hi - lo):
                fill[first + k // per].append((offset + k % per * length, length))
                placed[length] += 1
        assert placed == Counter(sizes)
        assert all(sum(n for _, n in v) <= 64 and [a for a, _ in sorted(v)] == list(np.cumsum([0, *[n for _, n in sorted(v)]])[:-1]) for v in fill.values())


def test_quality(spark):
    from cloneprint.llm import quality as Q

    good = [(k, prose(rng.randint(20, 90)).capitalize() + ".") for k in range(300)]
    bad = [(1000 + k, "### $$$ " * rng.randint(10, 50) + prose(5)) for k in range(100)]
    docs = spark.createDataFrame([*good, *bad, (5000, ""), (5001, None), (0, good[0][1])], "doc_id long, text string").withColumn("score", F.lit("clash"))
    labels = spark.createDataFrame([(k, int(k < 1000)) for k, _ in good + bad] + [(5000, None)], "doc_id long, quality int")
    rows = Q.classify(docs, labels).collect()
    assert len(rows) == docs.count() and all(0 <= r["score"] <= 1 and r["predicted"] == int(r["score"] >= 0.7) for r in rows)
    held = [r for r in rows if r["held_out"] and r["doc_id"] < 5000]
    assert len(held) > 50 and all(r["predicted"] == int(r["doc_id"] < 1000) for r in held)
    assert all(r["held_out"] == (zlib.crc32(str(r["doc_id"]).encode()) % 4 == 2) for r in rows)
    assert Q.classify(empty(docs), labels).count() == 0
    assert {r["score"] for r in Q.classify(docs, empty(labels)).collect()} == {0.5}


def test_quality_scores_are_the_density_differences(spark):
    """Scores of the operator against plain normal densities with the same shrinkage."""
    from cloneprint.llm import quality as Q

    r = random.Random(6)
    rows = [(k, prose(r.randint(1, 80)) + ("!" * r.randint(0, 9) if k % 3 else "."), int(k % 3 == 0)) for k in range(400)]
    docs = spark.createDataFrame([x[:2] for x in rows] + [rows[5][:2]] * 40, "doc_id long, text string").withColumn("y", F.lit("clash"))
    labels = spark.createDataFrame([(k, y) for k, _, y in rows], "doc_id long, quality int")
    fold = {k: zlib.crc32(str(k).encode()) % 4 == 2 for k, _, _ in rows}
    x = np.array([Q.statistics(t.encode()) for _, t, _ in rows])
    y, known = np.array([q for _, _, q in rows]), np.array([not fold[k] for k, _, _ in rows])
    scale = x[known].std(axis=0) + 1e-6
    z = x / scale
    pooled = sum(np.cov(z[known & (y == c)].T, bias=True) * (known & (y == c)).sum() for c in (0, 1)) / known.sum()
    logs = []
    for c in (0, 1):
        part = z[known & (y == c)]
        cov = (1 - Q.SHRINK_POOLED) * np.cov(part.T, bias=True) + Q.SHRINK_POOLED * pooled
        cov = (1 - Q.SHRINK_DIAGONAL) * cov + Q.SHRINK_DIAGONAL * (np.diag(np.diag(cov)) + 1e-3 * np.eye(len(cov)))
        gap = z - part.mean(axis=0)
        logs.append(np.log(len(part) / known.sum()) - 0.5 * np.linalg.slogdet(cov)[1] - 0.5 * np.einsum("ij,jk,ik->i", gap, np.linalg.inv(cov), gap))
    want = 1 / (1 + np.exp(np.clip(logs[0] - logs[1], -500, 500)))
    got = Q.classify(docs, labels).collect()
    assert len(got) == 440 and all(q["score"] == pytest.approx(want[q["doc_id"]], abs=1e-6) for q in got)
    clash = Q.score(docs.withColumn("score", F.lit("s")).withColumn("kept", F.lit(1)), Q.fit(docs, labels), ["doc_id", "kept", "score"], "other")
    assert clash.columns == ["doc_id", "kept", "score", "other"] and clash.where("score = 's' and kept = 1").count() == 440


def test_language_whole_operator_against_plain(spark):
    """Word by word in plain Python: letters by category, hashed n-grams, the same tables, plain Viterbi."""
    import unicodedata

    from cloneprint.llm import language_id as L

    r = random.Random(8)
    words = {"aa": "the and ing that with for", "bb": "der und ung nicht mit das", "cc": "это как что для его они", "dd": "हिन्दी में है और यह"}
    langs = list(words)
    rows = [(k, " ".join(r.choice(words[l].split()) for _ in range(r.randint(1, 90))) + r.choice(["", " 12 ", "!?", " 😀"]), l) for k in range(200) for l in [r.choice(langs)]]
    rows += [(1000, " ".join(rows[k][1] for k in range(12)), None), (1001, "😀😀 🎉", "aa"), (1002, "٣٤٥ १२३ ①②", "dd"), (1003, "́̀", "bb"), (1004, "𝒜𝒷 𐐀", None), (1005, "...", "aa"), (7, rows[7][1], rows[7][2])]
    docs = spark.createDataFrame(rows, "doc_id long, text string, lang string").withColumn("th", F.lit("clash")).withColumn("size", F.lit("clash"))
    docs = docs.unionByName(docs.where("doc_id = 9")).repartition(4)
    held = {k: zlib.crc32(str(k).encode()) % 3 == 1 for k, _, _ in rows}
    known = {(k, t, l) for k, t, l in rows if l and not held[k]}
    model = L.train([t for _, t, _ in sorted(known)], [l for _, _, l in sorted(known)])

    def plain(text):
        low, found, at = text.lower(), [], 0
        kind = [unicodedata.category(c)[0] for c in low]
        while at < len(low):
            end = at
            while end < len(low) and kind[end] in "LM":
                end += 1
            if "L" in kind[at:end]:
                found.append((at, end))
            at = max(end, at + 1)
        if not found:
            return "und", 0.0
        s = model.word_scores(L.letters(text)).astype(float)
        assert len(s) == len(found)
        v, back = s[0].copy(), []
        for row in s[1:]:
            best = int(v.argmax())
            stay = v >= v[best] - L.PENALTY
            back.append(np.where(stay, np.arange(len(v)), best))
            v = np.where(stay, v, v[best] - L.PENALTY) + row
        path = [int(v.argmax())]
        for b in reversed(back):
            path.append(int(b[path[-1]]))
        weight = np.zeros(len(v))
        for (a, b), k in zip(found, path[::-1], strict=True):
            weight[k] += b - a
        return model.langs[int(weight.argmax())], weight.max() / weight.sum()

    got = L.identify(docs).collect()
    text = {k: t for k, t, _ in rows}
    assert len(got) == docs.count()
    for q in got:
        name, share = plain(text[q["doc_id"]])
        assert (q["lang_pred"], q["held_out"]) == (name, held[q["doc_id"]]) and q["score"] == pytest.approx(share, abs=1e-6), q
    und = {q["doc_id"] for q in got if q["lang_pred"] == "und"}
    assert und == {1001, 1002, 1003, 1005}


def test_language(spark):
    from cloneprint.llm import language_id as L

    words = {"aa": "the and ing that with for", "bb": "der und ung nicht mit das", "cc": "это как что для его они"}
    make = lambda l, n: " ".join(rng.choice(words[l].split()) for _ in range(n))
    rows = [(k, make(l, rng.randint(5, 60)), l) for k in range(300) for l in [rng.choice(list(words))]]
    docs = spark.createDataFrame([*rows, (900, None, "aa"), (901, "", "aa"), (902, "123 !?", "bb"), (903, make("aa", 200_000), None)], "doc_id long, text string, lang string")
    got = {r["doc_id"]: r for r in L.identify(docs).collect()}
    assert all(got[k]["lang_pred"] == l for k, _, l in rows)
    assert all(got[k]["lang_pred"] == "und" and got[k]["score"] == 0 for k in (900, 901, 902)) and got[903]["lang_pred"] == "aa"
    assert L.identify(empty(docs)).count() == 0
    model = L.train([t for _, t, _ in rows], [l for _, _, l in rows])
    mixed = make("aa", 30) + " " + make("bb", 30) + " " + make("cc", 30)
    assert [s[2] for s in L.spans(mixed, model)] == ["aa", "bb", "cc"]


def test_viterbi_blocks_equal_plain():
    from cloneprint.llm import language_id as L

    r = np.random.default_rng(2)
    texts = [r.normal(size=(n, 3)) * 4 for n in (1, 31, 32, 33, 200, 5)]
    plain = []
    for s in texts:
        v, back = s[0].copy(), []
        for row in s[1:]:
            best = int(v.argmax())
            stay = v >= v[best] - L.PENALTY
            back.append(np.where(stay, np.arange(3), best))
            v = np.where(stay, v, v[best] - L.PENALTY) + row
        path = [int(v.argmax())]
        for b in reversed(back):
            path.append(int(b[path[-1]]))
        plain.append(path[::-1])
        assert L.viterbi(s).tolist() == plain[-1]
    first = np.cumsum([0, *[len(s) for s in texts]])
    assert L._viterbi_many(np.concatenate(texts).astype(np.float32), first).tolist() == sum(plain, [])


def test_decontamination(spark):
    from cloneprint.llm import decontaminate as D

    items = [prose(40) for _ in range(6)] + ["", None, "uniqueone uniquetwo"]
    w = items[1].split()
    edited = " ".join(x if k % 7 else f"edit{k}" for k, x in enumerate(w))
    docs = [prose(50) + " " + items[0].upper() + ", " + prose(50), prose(20) + " " + edited, prose(5000), None, "", "see uniqueone uniquetwo here", " ".join(items[2].split()[:4])]
    df = spark.createDataFrame([(k, t, 1.0) for k, t in enumerate(docs)] + [(0, docs[0], 1.0)], "doc_id long, text string, score double")
    bench = spark.createDataFrame(list(enumerate(items)), "item_id long, text string")
    got = D.contaminated(df, bench).collect()
    assert sorted((r["doc_id"], r["item_id"]) for r in got) == [(0, 0), (0, 0), (1, 1), (5, 8)]
    span = next(r for r in got if r["doc_id"] == 0)
    assert docs[0].encode()[span["start"] : span["end"]].decode().lower() == items[0] and span["score"] == 1
    assert D.contaminated(empty(df), bench).count() == D.contaminated(df, empty(bench)).count() == 0


@pytest.mark.parametrize("every", [3, 4, 5, 6])
@pytest.mark.parametrize("others", ["none", "exact copy", "half of the runs"])
def test_decontamination_edited_copies(spark, every, others):
    from cloneprint.llm import decontaminate as D

    items = [prose(n) for n in (24, 40, 60)]
    edited = [" ".join(f"x{k}" if k % every == every - 1 else w for k, w in enumerate(i.split())) for i in items]
    docs = [f"{prose(80)} {e} {prose(80)}" for e in edited]
    more = {"none": [], "exact copy": items * 3, "half of the runs": [" ".join(i.split()[:4]) for i in items] * 3}[others]
    df = spark.createDataFrame(list(enumerate(docs + more + [prose(400)])), "doc_id long, text string")
    got = D.contaminated(df, spark.createDataFrame(list(enumerate(items)), "item_id long, text string")).collect()
    assert {(r["doc_id"], r["item_id"]) for r in got if r["doc_id"] < 3} == {(k, k) for k in range(3)}
    assert all(r["doc_id"] < len(docs) + len(more) for r in got)


def test_decontamination_search_against_plain(spark):
    """Every document aligned with every item at every place, without seeds."""
    from cloneprint.llm import decontaminate as D

    r = random.Random(21)
    items = [prose(n) for n in (3, 8, 20, 20, 35, 50)]
    docs = []
    for k in range(80):
        w = r.choice(items).split()
        for _ in range(r.randint(0, max(1, len(w) // 3))):
            what, p = r.randrange(3), r.randrange(len(w))
            w[p : p + (what != 1)] = [] if what == 0 and len(w) > 2 else [f"n{r.randrange(99)}"]
        docs.append(f"{prose(r.randint(0, 30))} {' '.join(w)} {prose(r.randint(0, 30))}" if k % 4 else prose(60))
    code = lambda t: np.array([hash(x) & 0xFFFFFFFF for x in re.findall(r"[a-z0-9]+", t.lower())], np.uint64)
    want = {}
    for d, text in enumerate(docs):
        for i, item in enumerate(items):
            score = D.align(code(item), code(text))[0]
            if score >= D.CUT:
                want[d, i] = score
    df = spark.createDataFrame(list(enumerate(docs)) + [(None, docs[1])], "doc_id long, text string").withColumn("item_id", F.lit("clash"))
    got = {(q["doc_id"], q["item_id"]): q["score"] for q in D.contaminated(df.repartition(3), spark.createDataFrame(list(enumerate(items)), "item_id long, text string")).collect()}
    found = {k: v for k, v in got.items() if k[0] is not None}
    assert set(found) <= set(want) and all(v == pytest.approx(want[k]) for k, v in found.items())
    # what the seeds let go: items of few words, where one pair is not enough, and copies with words put in everywhere
    long = {k for k in want if len(items[k[1]].split()) >= 8}
    assert len(long & set(found)) >= 0.97 * len(long) and {i for d, i in got if d is None} == {i for d, i in found if d == 1}


def test_smith_waterman():
    from cloneprint.llm.decontaminate import GAP, MATCH, MISMATCH, align

    r = np.random.default_rng(8)
    for _ in range(40):
        a, b = r.integers(0, 5, r.integers(1, 12)).astype(np.uint64), r.integers(0, 5, r.integers(1, 20)).astype(np.uint64)
        h = np.zeros((len(a) + 1, len(b) + 1), int)
        for i in range(1, len(a) + 1):
            for j in range(1, len(b) + 1):
                h[i, j] = max(0, h[i - 1, j - 1] + (MATCH if a[i - 1] == b[j - 1] else MISMATCH), h[i - 1, j] + GAP, h[i, j - 1] + GAP)
        assert align(a, b)[0] * MATCH * len(a) == pytest.approx(h.max())


def test_substring(spark):
    from cloneprint.llm import substring_dedup as S

    passage, line = prose(70), prose(15)
    docs = [prose(40) + " " + passage + " " + prose(40), line + "\n" + prose(60), prose(30) + " " + passage + " " + prose(35) + "\n" + line, None, "", prose(90), line]
    df = spark.createDataFrame([(k, t, k, "x") for k, t in enumerate(docs)] + [(0, docs[0], 0, "x"), (None, docs[0], 9, "x")], "doc_id long, text string, place long, digest string")
    got = S.dedup_units(df).collect()
    assert len(got) == len(docs) + 2
    by = {r["doc_id"]: r for r in got}
    assert all(by[k]["text"] == docs[k] and not by[k]["removed"] for k in (0, 1, 3, 4, 5)) and by[None]["text"] == docs[0]
    assert passage not in by[2]["text"] and line not in by[2]["text"] and len(by[2]["text"].split()) >= 65 and by[6]["text"] == ""
    for r in got:  # the spans tell what is left
        if r["removed"]:
            raw, at, keep = docs[r["doc_id"]].encode(), 0, b""
            for s in r["removed"]:
                keep, at = keep + raw[at : s["start"]], s["end"]
            assert (keep + raw[at:]).decode() == r["text"]
    assert S.dedup_units(empty(df)).count() == 0


def _digests(text):
    """Kind, digest and check of the units of one text alone."""
    from cloneprint.llm import substring_dedup as S

    u = S.units([text.encode()])
    return u.kind.tolist(), u.digest.tolist(), u.check.tolist()


def test_substring_ids_with_several_texts_and_any_columns(spark):
    from cloneprint.llm import substring_dedup as S

    a, b, c = (prose(20) for _ in range(3))
    rows = [(1, a + "\n" + b), (2, c + "\n" + a), (2, b + "\n" + prose(12)), (2, c + "\n" + a), (3, c)]
    names = "doc_id long, text string"
    df = spark.createDataFrame(rows, names)
    for k, name in enumerate(("_text", "_again", "tag", "places", "spans", "removed", "others", "a.b", "_removed")):
        df = df.withColumn(name, F.lit(k))
    got = S.dedup_units(df).collect()
    assert S.dedup_units(df).columns == ["doc_id", "text", "_text", "_again", "tag", "places", "spans", "others", "a.b", "_removed", "removed"]
    left = sorted((r["doc_id"], r["text"]) for r in got)
    # both rows of id 2 with the text (c, a) lose a and keep c; its other text loses b, not its own second line
    assert left == sorted([(1, a + "\n" + b), (2, c), (2, c), (2, rows[2][1].split("\n")[1]), (3, "")])
    assert all((r["_text"], r["tag"], r["a.b"]) == (0, 2, 7) for r in got)


@pytest.mark.parametrize("often", [10_000, 4])
def test_substring_whole_operator_against_plain(spark, monkeypatch, often):
    """Group all units of all documents in a dictionary, keep the first, and cut by the same rule; with frequent units broadcast and without."""
    from cloneprint.llm import substring_dedup as S

    monkeypatch.setattr(S, "OFTEN", often)
    r = random.Random(12)
    shared = [prose(n) for n in (11, 15, 26, 40, 55, 80)]
    docs = ["\n".join(" ".join([prose(r.randint(3, 20)), r.choice(shared)] if r.random() < 0.4 else [r.choice(shared)] if r.random() < 0.4 else [prose(r.randint(5, 30))]) for _ in range(r.randint(1, 6))) for _ in range(150)]
    first, places = {}, defaultdict(set)
    per = []
    for d, text in enumerate(docs):
        kind, digest, check, *_ = _digests(text)
        seen = defaultdict(int)
        row = []
        for k, h, c in zip(kind, digest, check, strict=True):
            row.append(((h, c), 3 * seen[k] + k))
            seen[k] += 1
        per.append(row)
    count = defaultdict(int)
    for d, row in enumerate(per):
        for key, place in row:
            count[key] += 1
            first[key] = min(first.get(key, (d, place)), (d, place))
    for d, row in enumerate(per):
        for key, place in row:
            if count[key] > 1 and first[key] != (d, place):
                places[d].add(place)
    got = {q["doc_id"]: q for q in S.dedup_units(spark.createDataFrame(list(enumerate(docs)), "doc_id long, text string").repartition(6)).collect()}
    removed = 0
    for d, text in enumerate(docs):
        want = S.removed_spans([text.encode()], [sorted(places[d])], S.LINE_WORDS, S.RUN_WORDS)[0] if places[d] else []
        assert [(s["start"], s["end"]) for s in got[d]["removed"]] == want
        removed += len(want)
    assert removed > 50
    # no line of ten words or more is left twice
    lines = [tuple(x.split()) for q in got.values() for x in q["text"].split("\n") if len(x.split()) >= 10]
    assert len(lines) == len(set(lines))


def test_substring_passages_of_51_words(spark):
    from cloneprint.llm import substring_dedup as S

    passages = [prose(51) for _ in range(600)]
    docs = [f"{prose(30)} {p} {prose(30)}" for p in passages for _ in range(2)] + [prose(300)]
    df = spark.createDataFrame(list(enumerate(docs)), "doc_id long, text string")
    got = {r["doc_id"]: r for r in S.dedup_units(df).collect()}
    assert all(not got[2 * k]["removed"] and passages[k] not in got[2 * k + 1]["text"] for k in range(600))
    assert not got[1200]["removed"]
    w = [r["text"].split() for r in got.values()]
    assert all(len(x) <= 86 for x in w[1:1200:2])  # at least 25 of the 111 words


def test_substring_units_of_a_text_do_not_depend_on_its_neighbours():
    from cloneprint.llm import substring_dedup as S

    r = random.Random(2)
    texts = [("\n" if r.random() < 0.3 else " ").join(prose(r.randint(0, 120)).split()).encode() for _ in range(60)] + [b"", b"\n", b" \n\n x"]
    every = S.units(texts)
    for d, text in enumerate(texts):
        alone, mine = S.units([text]), every.doc == d
        for name in ("kind", "place", "digest", "check", "size"):
            assert (getattr(alone, name) == getattr(every, name)[mine]).all()
        assert (alone.start == every.start[every.first[d] : every.first[d + 1]]).all() and (alone.word == every.word[mine] - every.first[d]).all()


def test_substring_periodic_text():
    from cloneprint.llm import substring_dedup as S

    text = b"la " * 200
    places = 3 * np.arange(1, int((S.units([text]).kind == 2).sum())) + 2
    (((a, b),),) = S.removed_spans([text], [places.tolist()], 10, 25)
    assert (text[:a] + text[b:]).split() == [b"la"] * 51  # the first window, and what no drawn window reaches


def test_embeddings(spark):
    from cloneprint.llm import embedding_dedup as E

    r = np.random.default_rng(1)
    base = r.normal(size=(20, 16))
    rows = [(k, [float(x) for x in base[k % 20] + r.normal(size=16) * (0.12 if k >= 20 else 0)], k % 20 % 3) for k in range(160)]
    rows += [(200, None, 1), (201, [0.0] * 16, 1), (202, [float("nan")] * 16, 1), (203, [None] * 16, 1), (204, rows[3][1], None), (205, [1.0, 2.0], 1), (206, rows[3][1], 0), (207, [x * 1e-30 for x in rows[3][1]], 0), (208, [], 1)]
    df = spark.createDataFrame([(*x, "z") for x in rows], "vec_id long, embedding array<double>, label int, n long".replace("n long", "n string"))
    ok = [x for x in rows if x[1] and x[2] is not None and None not in x[1] and np.isfinite(x[1]).all() and any(x[1])]
    unit = {x[0]: np.array(x[1]) / np.linalg.norm(x[1]) for x in ok}
    label = {x[0]: x[2] for x in ok}
    links = [(a, b) for a in unit for b in unit if a != b and label[a] == label[b] and len(unit[a]) == len(unit[b]) and unit[a] @ unit[b] >= 0.93]
    want = roots(300, links)
    n = defaultdict(int)
    for a, _ in links:
        n[a] += 1
    got = {q["vec_id"]: q for q in E.near_duplicates(df).collect()}
    assert len(got) == len(rows) and all((q["component_id"], q["n_links"]) == (want[k], n[k]) for k, q in got.items())
    assert E.near_duplicates(empty(df)).count() == 0


def test_embeddings_hot_group_repeats_and_rare_lengths(spark):
    """Several thousand vectors: a large group of near copies, loose pairs around the threshold, repeated ids, many lengths."""
    from cloneprint.llm import embedding_dedup as E

    r = np.random.default_rng(5)
    unit = lambda x: x / np.linalg.norm(x, axis=-1, keepdims=True)
    near = lambda x, c: c * x + np.sqrt(1 - c * c) * unit((lambda u: u - (u * x).sum(-1, keepdims=True) * x)(r.normal(size=x.shape)))
    lone = unit(r.normal(size=(2500, 24)))
    pairs = near(lone[:800], r.uniform(0.9, 0.97, (800, 1)))
    hot = unit(lone[:1] + r.normal(size=(1500, 24)) * 0.035)
    x = np.concatenate((lone, pairs, hot)).astype(np.float32)
    label = np.concatenate((np.arange(2500) % 3, np.arange(800) % 3, np.zeros(1500, int)))
    rows = [(k, v.tolist(), int(l)) for k, (v, l) in enumerate(zip(x, label, strict=True))]
    rows += [(5, x[5].tolist(), 2), (5, x[900].tolist(), 0), (7, x[7].tolist(), 1), (7, x[7].tolist(), 1)]
    rows += [(9000 + 2 * n + k, [1.0] * n if k else [1.0] * (n - 1) + [1.1], 0) for n in range(30, 60) for k in range(2)]
    df = spark.createDataFrame(rows, "vec_id long, embedding array<float>, label int").repartition(7)
    want, links = defaultdict(list), []
    width = defaultdict(list)
    for k, (_, v, l) in enumerate(rows):
        width[len(v), l].append(k)
    total = [0] * len(rows)
    for group in width.values():
        m = unit(np.array([np.array(rows[k][1], np.float32) for k in group], float))
        i, j = np.nonzero(np.triu(m @ m.T >= 0.93, 1))
        for a, b in zip(i.tolist(), j.tolist(), strict=True):
            links.append((group[a], group[b]))
            total[group[a]] += 1
            total[group[b]] += 1
    first = {}
    for k, (d, _, _) in enumerate(rows):
        if first.setdefault(d, k) != k:
            links.append((first[d], k))
    root = roots(len(rows), links)
    low = defaultdict(lambda: 1 << 60)
    for k, (d, _, _) in enumerate(rows):
        low[root[k]] = min(low[root[k]], d)
        want[d].append(total[k])
    got = E.near_duplicates(df, chunk=200).collect()
    assert len(got) == len(rows) and sum(q["n_links"] for q in got) % 2 == 0
    seen = defaultdict(list)
    for q in got:
        seen[q["vec_id"]].append(q["n_links"])
    found, there = sum(map(sum, seen.values())), sum(map(sum, want.values()))
    assert 0.99 * there <= found <= there  # links are verified, so none is false
    assert sum(sorted(seen[d]) != sorted(want[d]) for d in want) <= 0.01 * len(want)
    component = {d: low[root[k]] for k, (d, _, _) in enumerate(rows)}
    assert sum(q["component_id"] != component[q["vec_id"]] for q in got) <= 0.01 * len(got)
    assert all(sum(seen[d]) == sum(want[d]) for d in seen if d >= 9000)  # lengths without an index are compared whole


def test_embedding_index_grows_and_orders_like_the_traversal():
    from cloneprint.llm import embedding_dedup as E

    r = np.random.default_rng(3)
    x = r.normal(size=(3000, 16))
    x /= np.linalg.norm(x, axis=1, keepdims=True)
    small, big = (E.choose(x, n, n * n / 10, 0.93, 0.99) for n in (1e4, 1e8))
    assert len(small.left) < len(big.left) and E.choose(x[:20], 20, 400, 0.93, 0.99) is None
    a, b = E._distances(x[:50, :8], big.left), E._distances(x[:50, 8:], big.right)
    for n in (1, 7, 40):
        got = big.order(x[:50], n)
        for k in range(50):
            cells = E.multi_sequence(a[k], b[k], n)
            assert [a[k, i] + b[k, j] for i, j in cells] == pytest.approx([a[k, c // len(big.right)] + b[k, c % len(big.right)] for c in got[k].tolist()])
    one, two = np.indices((30, 30))
    assert (E.asks(one, two) ^ E.asks(two, one))[one != two].all() and abs(E.asks(one, two).sum(axis=1) - 15).max() <= 1


def test_multi_sequence_order():
    from cloneprint.llm.embedding_dedup import multi_sequence

    r = np.random.default_rng(0)
    a, b = r.random(7), r.random(5)
    got = multi_sequence(a, b, 35)
    assert sorted(got) == [(i, j) for i in range(7) for j in range(5)]
    sums = [a[i] + b[j] for i, j in got]
    assert sums == sorted(sums)


def test_warc(spark, tmp_path):
    from cloneprint.llm import warc as W

    html = ["<p>ä</p>", "", None, "<p>ä</p>", "x" * 200_000, "WARC/1.1\r\n\r\ntrap", "<p>ä</p>"]
    rows = [(k * 3 - 4, f"http://h/{k}", h, 1) for k, h in enumerate(html)] + [(50, None, "z" * 9, 1)]
    df = spark.createDataFrame(rows, "page_id long, url string, html string, payload int")
    first, got = {}, {r["page_id"]: r for r in W.round_trip(df).collect()}
    for p, _, h, _ in sorted(rows):
        first.setdefault((h or "").encode(), p)
    for p, _, h, _ in rows:
        b, r = (h or "").encode(), got[p]
        assert (r["payload_bytes"], r["payload_digest"]) == (len(b), base64.b32encode(hashlib.sha1(b).digest()).decode())
        assert (r["record_type"], r["refers_to"]) == (("response", None) if first[b] == p else ("revisit", first[b]))
    # repeated rows, pages without an id
    more = df.unionByName(df.where("page_id in (-4, 5)")).unionByName(spark.createDataFrame([(None, None, "<p>ä</p>", 1), (None, None, "only here", 1)], df.schema))
    kinds = sorted((str(r["page_id"]), r["record_type"], r["refers_to"]) for r in W.round_trip(more).collect() if r["page_id"] in (None, -4, 5))
    assert kinds == [("-4", "response", None)] * 2 + [("5", "revisit", -4)] * 2 + [("None", "response", None), ("None", "revisit", -4)]
    assert all(r["record_type"] == "response" for r in W.round_trip(df, least=100).where("payload_bytes < 100").collect())
    assert W.round_trip(empty(df)).count() == 0
    from cloneprint.llm.common import Scratch

    at = str(tmp_path / "w")
    W.page_records(df, Scratch(spark, "w")).write.format("warc").mode("append").option("path", at).save()
    read = lambda **o: spark.read.format("warc").options(path=at, **o).load()
    assert read(record_types="revisit").count() == sum(r["record_type"] == "revisit" for r in got.values())
    assert read().where("record_type = 'revisit'").count() == read(record_types="revisit").count()
    assert read(payload="false").where("payload is not null").count() == 0
    assert read(**{"header.WARC-Target-URI": "http://h/4"}).first()["payload_bytes"] == 200_000
    assert read(split="200").rdd.getNumPartitions() > 1
    (tmp_path / "plain").mkdir()
    (tmp_path / "plain" / "a.warc").write_bytes(b"".join(W.record("response", f"<urn:{k}>", None, None, b"y" * k) for k in range(5)))
    assert [r["payload_bytes"] for r in spark.read.format("warc").load(str(tmp_path / "plain")).orderBy("payload_bytes").collect()] == list(range(5))


def test_rollup(spark, tmp_path):
    from cloneprint.llm import token_rollup as R

    roll = R.Rollup(spark, str(tmp_path / "roll"))
    kind = "source string, lang string, tokenizer string, docs long, tokens long"
    one = spark.createDataFrame([("a", "x", "t", 1, 10), ("a", None, "t", 1, 5), ("b", "x", "t", 1, 7)], kind)
    two = spark.createDataFrame([("b", "x", "t", -1, -7), ("a", "x", "t", 0, 3)], kind)
    assert roll.totals().count() == 0
    assert roll.commit("1", one) and not roll.commit("1", one) and roll.commit("2", two) and roll.commit("3", one.limit(0))
    want = {("a", "x", 1, 13), ("a", None, 1, 5)}
    total = lambda: {(r["source"], r["lang"], r["n_docs"], r["n_tokens"]) for r in roll.totals().collect()}
    assert total() == want
    roll.compact()
    assert total() == want and not roll.commit("2", two) and roll.commit("4", one)
    assert ("b", "x", 1, 7) in total()


def test_rollup_compactions_and_crashes(spark, tmp_path):
    from cloneprint.llm import token_rollup as R

    kind = "source string, lang string, tokenizer string, docs long, tokens long"
    batch = lambda n: spark.createDataFrame([("a", "x", "t", 1, n)], kind)
    roll = R.Rollup(spark, str(tmp_path / "roll"))
    total = lambda: [(r["n_docs"], r["n_tokens"]) for r in roll.totals().collect()]
    for k in (1, 2, 3):
        assert roll.commit(str(k), batch(10))
    roll.compact()
    assert roll.commit("4", batch(5)) and total() == [(4, 35)]
    roll.compact()
    assert total() == [(4, 35)] and not any(roll.commit(str(k), batch(99)) for k in (1, 2, 3, 4))
    # a crash after the new folder is published: nothing is deleted yet, and all still counts once
    roll.commit("5/odd id", batch(7))
    sweep, roll._sweep = roll._sweep, lambda: None
    roll.compact()
    assert len(roll._names("compacted")) == 2 and roll._names("batch") and total() == [(5, 42)] and not roll.commit("5/odd id", batch(1))
    roll._sweep = sweep
    # a crash before it is published
    publish, roll._publish = roll._publish, lambda temp, name: False
    roll.compact()
    assert not roll.commit("6", batch(1)) and total() == [(5, 42)]
    roll._publish = publish
    roll.compact()
    assert len(roll._names("compacted")) == 1 and not roll._names("batch") and total() == [(5, 42)] and roll.commit("6", batch(1)) and total() == [(6, 43)]


def test_rollup_replay_cases(spark):
    from cloneprint.llm import token_rollup as R

    rows = [(1, "a b! c", "s", "en"), (1, "a b! c", "s", "en"), (2, None, "s", "en"), (3, "", None, None), (4, "!! x #y", "s", None), (5, "x y", "s", "en"), (None, "q q", "s", "en"), (6, "gone now", "t", "en")]
    docs = spark.createDataFrame(rows, "doc_id long, text string, source string, lang string").withColumn("counts", F.lit("clash")).withColumn("low", F.lit(1))
    flags = [(1, 0, 0), (1, 0, 0), (4, 0, 0), (5, 1, 1), (6, 0, 1), (None, 0, 1), (2, None, None)]
    labels = spark.createDataFrame(flags, "doc_id long, quality int, toxic int")
    low, toxic = {d for d, q, _ in flags if q == 0 and d}, {d for d, _, x in flags if x == 1 and d}
    want = defaultdict(lambda: [0, 0])
    for d, t, s, l in rows:
        if d in toxic:
            continue
        t = "".join(c for c in t or "" if not (d in low and c in R.MARKS))
        for name, pattern in R.TOKENIZERS.items():
            want[s, l, name][0] += 1
            want[s, l, name][1] += len(re.findall(pattern, t))
    got = {(r["source"], r["lang"], r["tokenizer"]): [r["n_docs"], r["n_tokens"]] for r in R.replay(docs, labels).collect()}
    assert got == dict(want)
    assert R.replay(empty(docs), labels).count() == 0 and R.replay(docs, empty(labels)).groupBy().sum("n_docs").first()[0] == 2 * len(rows)


def test_pipeline_cases(spark, tmp_path):
    """Nulls, empty texts, repeated rows, clashing columns and empty tables through all stages."""
    import corpus_pipeline as P

    docs = spark.read.parquet(f"{SF}/documents.parquet")
    some = docs.orderBy("doc_id").limit(3).collect()
    more = [(None, some[0]["text"], "en", "s", 5), (90001, None, "en", "s", 0), (90002, "", None, None, 0), (90001, None, "en", "s", 0), (some[1]["doc_id"], some[1]["text"], some[1]["lang"], some[1]["source"], some[1]["n_chars"])]
    wide = docs.unionByName(spark.createDataFrame(more, docs.schema))
    for name in ("score", "_text", "spans", "removed", "gone", "tag", "kept", "key", "a.b", "item_id"):
        wide = wide.withColumn(name, F.lit(name))
    for table in ("labels", "benchmark"):
        spark.read.parquet(f"{SF}/{table}.parquet").write.parquet(str(tmp_path / f"{table}.parquet"))
    at = wide
    for name, stage in P.STAGES[:-1]:
        out = stage(spark, at, str(tmp_path))
        assert out.columns == wide.columns, name
        out.write.parquet(str(tmp_path / name.replace(" ", "-")))
        at = spark.read.parquet(str(tmp_path / name.replace(" ", "-")))
        assert at.where("score <> 'score' or `a.b` <> 'a.b'").count() == 0 and 0 < at.count() <= wide.count()
        assert stage(spark, empty(wide), str(tmp_path)).count() == 0
    pieces = P.STAGES[-1][1](spark, at, str(tmp_path))
    assert pieces.groupBy("sequence_id").sum("length").where("`sum(length)` > 1024").count() == 0
    assert P.STAGES[-1][1](spark, empty(wide), str(tmp_path)).count() == 0


def test_pipeline_small(spark):
    """Stage by stage against plain versions on the smallest tables."""
    import corpus_pipeline as P

    docs = spark.read.parquet(f"{SF}/documents.parquet")
    names = [n for n, _ in P.STAGES]
    assert names == ["quality classifier", "minhash near-dedup", "substring dedup", "benchmark decontamination", "packing"]
    kept = P.quality_stage(spark, docs, SF).cache()
    labels = {r["doc_id"]: r["quality"] for r in spark.read.parquet(f"{SF}/labels.parquet").collect()}
    ids = {r["doc_id"] for r in kept.select("doc_id").collect()}
    assert kept.columns == docs.columns and np.mean([(d in ids) == (q == 1) for d, q in labels.items()]) > 0.95
    near = P.near_duplicate_stage(spark, kept, SF).cache()
    sets = {r["doc_id"]: shingles(r["text"]) for r in near.collect()}
    assert near.columns == docs.columns
    assert not any(100 * len(sets[a] & sets[b]) >= 75 * len(sets[a] | sets[b]) for a in sets for b in sets if a < b and sets[a] and sets[b])
    cut = P.substring_stage(spark, near, SF).cache()
    assert cut.columns == docs.columns and cut.where("n_chars <> char_length(text)").count() == 0
    clean = P.decontamination_stage(spark, cut, SF)
    items = [r["text"] for r in spark.read.parquet(f"{SF}/benchmark.parquet").collect()]
    left = clean.collect()
    assert not any(i in r["text"] for i in items for r in left) and len(left) >= cut.count() - 20
    pieces = P.packing_stage(spark, clean, SF)
    assert pieces.select("doc_id").distinct().count() == len(left)


def test_pipeline_end_to_end_against_plain(spark):
    """run() against plain Python versions of all five stages, one after another, on the smallest tables."""
    import corpus_pipeline as P
    from tokenizers import Tokenizer

    from cloneprint.llm import decontaminate as D
    from cloneprint.llm import encode
    from cloneprint.llm import quality as Q
    from cloneprint.llm import substring_dedup as S

    docs = {r["doc_id"]: r["text"] for r in spark.read.parquet(f"{SF}/documents.parquet").collect()}
    labels = sorted({(r["doc_id"], r["quality"]) for r in spark.read.parquet(f"{SF}/labels.parquet").collect() if r["quality"] in (0, 1) and r["doc_id"] in docs})
    x, y = np.array([Q.statistics((docs[d] or "").encode()) for d, _ in labels]), np.array([q for _, q in labels])
    order = np.lexsort((*x.T, y))
    model = Q.Discriminant(x[order], y[order])
    ids = sorted(docs)
    scores = model.scores(np.array([Q.statistics((docs[d] or "").encode()) for d in ids]))
    kept = [d for d, s in zip(ids, scores, strict=True) if s >= P.QUALITY_CUT]
    sets = [shingles(docs[d]) for d in kept]
    root = roots(len(kept), [(a, b) for a in range(len(kept)) for b in range(a) if sets[a] and sets[b] and 100 * len(sets[a] & sets[b]) >= 75 * len(sets[a] | sets[b])])
    kept = [d for k, d in enumerate(kept) if root[k] == k]
    first, places = {}, defaultdict(list)
    for d in kept:
        kind, digest, check = _digests(docs[d] or "")
        seen = defaultdict(int)
        for k, h, c in zip(kind, digest, check, strict=True):
            place = 3 * seen[k] + k
            seen[k] += 1
            if first.setdefault((h, c), (d, place)) != (d, place):
                places[d].append(place)
    # the first of a text's own places is by kind and number, not by the order of units
    lowest = {}
    for d in kept:
        kind, digest, check = _digests(docs[d] or "")
        seen = defaultdict(int)
        for k, h, c in zip(kind, digest, check, strict=True):
            lowest[h, c] = min(lowest.get((h, c), (d, 3 * seen[k] + k)), (d, 3 * seen[k] + k))
            seen[k] += 1
    assert lowest == first
    left = {}
    for d in kept:
        raw = (docs[d] or "").encode()
        spans = S.removed_spans([raw], [places[d]], S.LINE_WORDS, S.RUN_WORDS)[0] if raw and places[d] else []
        out, at = b"", 0
        for a, b in spans:
            out, at = out + raw[at:a], b
        text = (out + raw[at:]).decode()
        if not spans or text.strip():
            left[d] = text
    code = lambda text: np.array([zlib.crc32(w.encode()) for w in re.findall(r"[a-z0-9\x80-\U0010ffff]+", "".join(c.lower() if "A" <= c <= "Z" else c for c in text))], np.uint64)
    items = [code(r["text"]) for r in spark.read.parquet(f"{SF}/benchmark.parquet").collect() if r["text"]]
    clean = {d: t for d, t in left.items() if not any(len(i) and D.align(i, code(t))[0] >= D.CUT for i in items)}
    lib = Tokenizer.from_file(encode.public_path())
    want = set()
    for d, t in clean.items():
        got = np.append(lib.encode(t, add_special_tokens=False).ids, 0).astype("<u4")
        want |= {(d, k, min(1024, len(got) - k), zlib.crc32(got[k : k + 1024].tobytes()), len(got)) for k in range(0, len(got), 1024)}
    rows = P.run(spark, SF).collect()
    assert {(r["doc_id"], r["start"], r["length"], r["ids_crc32"], r["doc_tokens"]) for r in rows} == want and len(rows) == len(want)
    fill = defaultdict(list)
    for r in rows:
        fill[r["sequence_id"]].append((r["offset"], r["length"]))
    assert all([a for a, _ in sorted(v)] == list(np.cumsum([0, *[n for _, n in sorted(v)]])[:-1]) and sum(n for _, n in v) <= 1024 for v in fill.values())


def test_queries_registered():
    from cloneprint.llm.queries import QUERIES

    assert sorted(int(re.match(r"op(\d+)_", q)[1]) for q in QUERIES) == list(range(1, 11))
