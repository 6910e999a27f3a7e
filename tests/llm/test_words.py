import random
import re

import numpy as np
import pyarrow as pa
import pytest

from gridalg.llm import components, decontaminate as dec, kernel, minhash
from gridalg.llm.lineage import cut

LOWER = str.maketrans("ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz")
ALNUM = re.compile(r"[^\x00-\x2F\x3A-\x60\x7B-\x7F]+")
NONSPACE = re.compile(r"[^\x20\x09-\x0D]+")
RND = random.Random(4)
ODD = [None, "", " ", "\n\t", "a", "É", "x" * 5000, "日本 語", "A b\x00c", " x y", "!!!"]


def noise(n, alphabet="abcDE é日.,\n\t1_-"):
    return "".join(RND.choice(alphabet) for _ in range(n))


@pytest.mark.parametrize("piece", [1 << 20, 37])
def test_words_are_those_of_the_pattern(monkeypatch, piece):
    monkeypatch.setattr(kernel, "PIECE", piece)
    texts = ODD + [noise(RND.randint(0, 300)) for _ in range(200)]
    raw, offsets = kernel.buffers(pa.array(texts, pa.string()))
    for rx, cls in ((ALNUM, kernel.ALNUM), (NONSPACE, kernel.NONSPACE)):
        s, e, h, first = kernel.words(raw, offsets, cls)
        seen = {}
        for d, t in enumerate(texts):
            want = rx.findall((t or "").translate(LOWER))
            got = [bytes(kernel._LOWER[raw[a:b]]).decode() for a, b in zip(s[first[d] : first[d + 1]], e[first[d] : first[d + 1]], strict=True)]
            assert got == want
            for w, x in zip(want, h[first[d] : first[d + 1]].tolist(), strict=True):
                assert seen.setdefault(w, x) == x
        assert len(set(seen.values())) == len(seen)


def test_slices_of_columns_and_other_types():
    col = pa.array(["ab", None, "cd", "é"], pa.string()).slice(1)
    raw, offsets = kernel.buffers(col)
    assert bytes(raw) == "cdé".encode() and offsets.tolist() == [0, 0, 2, 4]
    assert kernel.buffers(pa.array([], pa.string()))[1].tolist() == [0]
    assert bytes(kernel.buffers(pa.chunked_array([["a"], ["b"]], pa.large_string()))[0]) == b"ab"


def grams(words, k):
    return {tuple(words[i : i + k]) for i in range(len(words) - k + 1)} if len(words) >= k else ({tuple(words)} if words else set())


def brute_hits(docs, items, window=10):
    out = {}
    parsed = {i: ALNUM.findall((t or "").translate(LOWER)) for i, t in items}
    for d, t in docs:
        w = ALNUM.findall((t or "").translate(LOWER))
        hit, found = set(), set()
        for i, iw in parsed.items():
            k = min(window, len(iw))
            own = grams(iw, k) if iw else set()
            for p in range(len(w) - k + 1) if k else ():
                if tuple(w[p : p + k]) in own:
                    hit.update(range(p, p + k))
                    found.add(str(i))
        out[d] = (len(w), len(hit), len(found), dec.sha_of(found), bool(hit))
    return out


def some_documents():
    vocab = [noise(4, "abcdé") for _ in range(40)]
    text = lambda n: " ".join(RND.choice(vocab) for _ in range(n))
    items = [(k, text(RND.choice([3, 9, 10, 14, 30]))) for k in range(8)] + [(20, None), (21, "..."), (22, "")]
    docs = []
    for d in range(120):
        t = text(RND.randint(0, 60))
        if d % 3 == 0:
            w = RND.choice(items)[1] or ""
            t = t[: len(t) // 2] + " " + w.upper().replace(" ", ", ") + " " + t[len(t) // 2 :]
        docs.append((d, t))
    return docs + [(200 + k, t) for k, t in enumerate(ODD)], items


@pytest.mark.parametrize("block", [1 << 24, 60])
def test_hits_against_brute_force(spark, monkeypatch, block):
    monkeypatch.setattr(dec, "BLOCK_BYTES", block)  # small: the benchmark is scanned in several blocks, long items in parts
    docs, items = some_documents()
    d = spark.createDataFrame([(*r, "x") for r in docs], "doc_id long, text string, n_words string")
    b = spark.createDataFrame(items, "item_id long, text string")
    got = {r[0]: tuple(r[1:]) for r in dec.digest(dec.find_windows(d, b)).collect()}
    assert got == brute_hits(docs, items)


@pytest.mark.parametrize("block", [1 << 24, 30])
def test_documents_without_passages(spark, monkeypatch, block):
    monkeypatch.setattr(dec, "BLOCK_BYTES", block)
    passage = "one two three four five six seven eight nine ten eleven"
    rows = [(1, f"Before, {passage}! after", 5, "s"), (2, "clean text", 6, "s"), (3, None, None, "s"), (4, passage, 7, "s"), (4, passage, 7, "s"), (4, "other", 1, "s"), (None, passage, 8, "s"), (None, "é", 1, "s"), (None, "é", 1, "s")]
    d = spark.createDataFrame(rows, "doc_id long, text string, n_chars int, hit_spans string")
    b = spark.createDataFrame([(9, passage), (10, "")], "item_id long, text string")
    left = dec.decontaminate(d, b)
    assert left.schema == d.schema
    plain = lambda rows: sorted(map(str, rows))
    assert plain(map(tuple, left.collect())) == plain([rows[i] for i in (1, 2, 5, 7, 8)])
    cut = dec.decontaminate(d, b, mode="span")
    want = [(1, "Before, ! after", 15, "s"), rows[1], rows[2], (4, "", 0, "s"), (4, "", 0, "s"), rows[5], (None, "", 0, "s"), rows[7], rows[8]]
    assert cut.schema == d.schema and plain(map(tuple, cut.collect())) == plain(want)
    found = dec.digest(dec.find_windows(d, b)).collect()
    assert sorted((r.doc_id or 0, r.n_words, r.n_hit) for r in found) == [(0, 1, 0), (0, 1, 0), (0, 11, 11), (1, 13, 11), (2, 2, 0), (3, 0, 0), (4, 1, 0), (4, 11, 11), (4, 11, 11)]
    with pytest.raises(ValueError):
        dec.decontaminate(d, b, mode="other")
    assert dec.find_windows(d.limit(0), b).count() == 0 == dec.decontaminate(d.limit(0), b).count()
    assert dec.find_windows(d, b.limit(0)).filter("size(items) > 0").count() == 0
    assert dec.decontaminate(d, b.limit(0)).count() == len(rows)


def shingles(text, k):
    return grams(NONSPACE.findall((text or "").translate(LOWER)), k)


def brute_classes(docs, k):
    sets = {d: shingles(t, k) for d, t in docs}
    root = {d: d for d in sets}

    def find(x):
        while root[x] != x:
            x = root[x]
        return x

    ids = sorted(sets)
    for i, a in enumerate(ids):
        for b in ids[:i]:
            u = len(sets[a] | sets[b])
            if u and sets[a] and sets[b] and 100 * len(sets[a] & sets[b]) >= 80 * u:
                x, y = find(a), find(b)
                root[max(x, y)] = min(x, y)
    return {d: (len(sets[d]), find(d), d == find(d)) for d in ids}


def near_copies():
    vocab = [noise(3, "abcdefgh") for _ in range(60)]
    docs, d = [], 0
    for group in range(6):
        base = [RND.choice(vocab) for _ in range(RND.choice([6, 25, 120]))]
        for _ in range(25):
            w = list(base)
            for _ in range(RND.randint(0, max(1, len(w) // 9))):
                w[RND.randrange(len(w))] = RND.choice(vocab)
            if RND.random() < 0.2:
                w = w[: RND.randint(len(w) * 8 // 10, len(w))]
            docs.append((1000 - d, " ".join(w)))
            d += 1
    for n in (1, 2, 3, 4, 5):
        docs += [(2000 + n * 10 + k, " ".join(vocab[:n])) for k in range(3)]
    return docs + [(3000 + k, t) for k, t in enumerate(ODD)]


@pytest.mark.parametrize("k", [2, 5])
def test_classes_against_all_pairs(spark, k):
    docs = near_copies()
    d = spark.createDataFrame([(*r, 1) for r in docs], "doc_id long, text string, n int")
    got = {r[0]: tuple(r[1:]) for r in minhash.near_duplicates(d, shingle=k).collect()}
    assert got == brute_classes(docs, k)
    kept = {r.doc_id for r in minhash.deduplicate(d, shingle=k).collect()}
    assert kept == {i for i, v in got.items() if v[2]}


def test_links_that_no_centre_shows(spark):
    """A chain of edits: neighbours are similar, ends are not, so links lie between members other than the centre."""
    words = [f"w{i}" for i in range(400)]
    docs = [(i, " ".join(words[i * 8 : i * 8 + 120])) for i in range(30)]
    d = spark.createDataFrame(docs, "doc_id long, text string")
    got = {r[0]: tuple(r[1:]) for r in minhash.near_duplicates(d, shingle=2).collect()}
    assert got == brute_classes(docs, 2)
    assert len({v[1] for v in got.values()}) == 1


@pytest.mark.parametrize("links", [[], [(5, 5), (2, 1), (1, 2), (1, 2)], [(i, i + 1) for i in range(100)], [(i, 1000) for i in range(40)] + [(1000, 2000), (2000, -3)], [(i * i * 7 % 151, i * 31 % 149) for i in range(110)]])
def test_rounds_of_components_deal_the_edges_twice(spark, monkeypatch, links):
    """With up to eleven exchanges in the plan of a round, many partitions left tens of thousands of small files."""
    plans = []
    monkeypatch.setattr(components, "cut", lambda df: plans.append(df._jdf.queryExecution().executedPlan().toString()) or cut(df))
    got = components.components(spark.createDataFrame(links, "a long, b long")).collect()
    root = {x: x for link in links if link[0] != link[1] for x in link}
    for _ in root:
        for a, b in links:
            if a != b:
                root[a] = root[b] = min(root[a], root[b])
    assert sorted(map(tuple, got)) == sorted(root.items())
    assert plans and max(p.count("Exchange ") for p in plans) <= 2


def test_no_documents_and_repeated_rows(spark):
    d = spark.createDataFrame([], "doc_id long, text string")
    assert minhash.near_duplicates(d).count() == 0
    d = spark.createDataFrame([(1, "a b c"), (1, "a b c"), (2, "a b c")], "doc_id long, text string")
    assert sorted(tuple(r) for r in minhash.near_duplicates(d, shingle=2).select("doc_id", "component_id", "kept").collect()) == [(1, 1, True), (1, 1, True), (2, 1, False)]


def test_rows_without_id_and_clashing_names(spark):
    rows = [(None, "a b c", 1), (None, "a b c", 2), (4, "a b c", 3), (6, "a b c", 4), (7, None, 5)]
    d = spark.createDataFrame(rows, "doc_id long, text string, component_id int")
    got = minhash.near_duplicates(d, shingle=2).select("doc_id", "n_shingles", "component_id", "kept").collect()
    assert sorted(map(str, map(tuple, got))) == sorted(map(str, [(None, 2, None, True), (None, 2, None, True), (4, 2, 4, True), (6, 2, 4, False), (7, 0, 7, True)]))
    kept = minhash.deduplicate(d, shingle=2)
    assert kept.columns == d.columns and sorted(r.component_id for r in kept.collect()) == [1, 2, 3, 5]


def test_signature_of_few_shingles():
    one = minhash.signature(np.array([5], np.uint64))
    assert (one == 5).all() and len(minhash.band_keys(one)) == 32
    with pytest.raises(ValueError):
        minhash.near_duplicates(None, share=(0, 1))
