import hashlib
import random

import numpy as np
import pytest
from pyspark.sql import functions as F

from gridalg.llm import piecefst, suffix, suffixdedup, tokencount

tokenizers = pytest.importorskip("public_tokenizers")
RND = random.Random(8)
SOUP = "aaabeinst  ▁.,'\"éßñ—\n\t0123xyz的一😀ABC()<>/_-"
ODD = [None, "", " ", "  a", "a\x00b", "<|endoftext|>", "x<|endoftext|> y <|endoftext|>", "<s> </s>", "▁ x ▁▁a", "!" * 40, "日本語テキスト", "é" * 300, "a" * 5000, "word " * 3000]


def soup(n):
    return "".join(RND.choice(SOUP) for _ in range(n))


def test_pieces_are_those_of_the_library(spark):
    sp = pytest.importorskip("sentencepiece")
    path = tokenizers.path("piece_bpe_32k.model")
    lib = sp.SentencePieceProcessor(model_file=path)
    texts = ODD + [soup(RND.randint(0, 80)) for _ in range(400)] + [r.text for r in spark.read.parquet("/root/testdata/sf0.001/documents.parquet").select("text").collect()]
    rows = [(i, t, "x") for i, t in enumerate(texts)]
    got = {r.doc_id: r for r in piecefst.encode_decode(spark.createDataFrame(rows, "doc_id long, text string, ids string"), path).collect()}
    for i, t in enumerate(texts):
        want = lib.encode(t or "")
        assert list(got[i].ids) == want and got[i].n_pieces == len(want)
        assert got[i].decoded == lib.decode(want)
        assert got[i].lossless == ("▁" not in (t or ""))
        assert got[i].ids_sha256 == hashlib.sha256(np.array(want, "<i4").tobytes()).hexdigest()
    assert piecefst.encode_decode(spark.createDataFrame([], "doc_id long, text string"), path).count() == 0


def test_small_caches_change_nothing(monkeypatch):
    path = tokenizers.path("piece_bpe_32k.model")
    with open(path, "rb") as f:
        model = f.read()
    monkeypatch.setattr(piecefst, "WORDS", 3)
    monkeypatch.setattr(piecefst, "PAIRS", 5)
    small, usual = piecefst.Transducer(model), piecefst.load(path)
    for _ in range(200):
        t = soup(40)
        assert small.encode(t) == usual.encode(t)


def message(number, value):
    def varint(n):
        out = b""
        while True:
            out += bytes([n & 127 | (128 if n > 127 else 0)])
            n >>= 7
            if not n:
                return out

    if isinstance(value, float):
        import struct

        return varint(number << 3 | 5) + struct.pack("<f", value)
    if isinstance(value, int):
        return varint(number << 3) + varint(value)
    return varint(number << 3 | 2) + varint(len(value)) + value


def test_unigram_models_take_the_cheapest_path():
    pieces = [("<unk>", 0.0, 2), ("▁", -2.0, 1), ("a", -1.5, 1), ("b", -1.6, 1), ("ab", -2.0, 1), ("▁ab", -5.5, 1), ("aba", -9.0, 1), ("bb", -2.9, 1)]
    model = b"".join(message(1, message(1, p.encode()) + message(2, s) + message(3, t)) for p, s, t in pieces) + message(2, message(3, 1)) + message(3, message(1, b"identity") + message(3, 1) + message(4, 0))
    f = piecefst.Transducer(model)
    score = {p: s for p, s, t in pieces if t == 1}

    def best(text):
        if not text:
            return 0.0
        return max([score[text[:k]] + best(text[k:]) for k in range(1, len(text) + 1) if text[:k] in score] + ([f.least + best(text[1:])] if text[0] not in score else []))

    for _ in range(200):
        t = "".join(RND.choice("ab c") for _ in range(RND.randint(1, 9)))
        ids = np.frombuffer(f.encode(t), "<i4").tolist()
        cost = sum(f.score[i] if i else f.least for i in ids)
        assert cost == pytest.approx(best("▁" + t.replace(" ", "▁")))


@pytest.mark.parametrize("rule", ["nmt_nfkc", "nfkc_cf"])
def test_character_maps_are_compiled(rule):
    sp = pytest.importorskip("sentencepiece")
    lib = sp.SentencePieceNormalizer(rule_name=rule, escape_whitespaces=False, add_dummy_prefix=False, remove_extra_whitespaces=False)
    spec = dict(piecefst._fields(dict(piecefst._fields(lib.serialized_model_proto()))[3]))
    own = piecefst.Normaliser(piecefst.character_map(spec[2]), False, False)
    texts = ["ﬁne ½ Ａ①", "e\u0301a\u0308\u0304 ｶﾞ", "Ǆ ℌ", "\u00a0x\u3000y", "plain", "", "가각힣 ㈱", "Straße ΑΣ"]
    texts += ["".join(chr(RND.choice([RND.randrange(32, 127), RND.randrange(0xA0, 0x250), RND.randrange(0x300, 0x370), RND.randrange(0x1100, 0x1200), RND.randrange(0x3000, 0x3200), RND.randrange(0xFF00, 0xFFF0)])) for _ in range(30)) for _ in range(300)]
    for t in texts:
        assert own(t).replace("▁", " ") == lib.normalize(t).replace("▁", " "), t
    # a whole model with this map gives the ids of the library
    pieces = [("<unk>", 0.0, 2), ("<s>", 0.0, 3), ("</s>", 0.0, 3), ("▁", -2.0, 1), *((c, -3.0, 1) for c in "abcdefghinortux"), ("▁fi", -2.5, 1), ("ne", -2.2, 1), ("re", -2.7, 1)]
    model = b"".join(message(1, message(1, p.encode()) + message(2, s) + message(3, t)) for p, s, t in pieces) + message(2, message(3, 1)) + message(3, message(1, rule.encode()) + message(2, spec[2]) + message(3, 1) + message(4, 1))
    whole, f = sp.SentencePieceProcessor(model_proto=model), piecefst.Transducer(model)
    for t in ["ﬁne  ｆｏｒ e\u0301 ", "  ﬁ\u3000ne½ x", "", "ＡＢｃ"]:
        assert [i for i in np.frombuffer(f.encode(t), "<i4").tolist() if i] == [i for i in whole.encode(t) if i]


def test_rows_of_pieces_stay(spark):
    path = tokenizers.path("piece_bpe_32k.model")
    df = spark.createDataFrame([(None, "a b"), (3, "a b"), (3, "a b"), (3, None)], "doc_id long, text string")
    got = piecefst.encode_decode(df, path).collect()
    assert sorted((r.doc_id or 0, r.decoded, r.n_pieces) for r in got) == [(0, "a b", 2), (3, "", 0), (3, "a b", 2), (3, "a b", 2)]
    counted = tokencount.count_tokens(df, tokenizers.path("byte_bpe_50k.json")).collect()
    assert sorted((r.doc_id or 0, r.n_bytes, r.n_tokens) for r in counted) == [(0, 3, 2), (3, 0, 0), (3, 3, 2), (3, 3, 2)]


def test_token_counts(spark, monkeypatch):
    from tokenizers import Tokenizer

    monkeypatch.setattr(tokencount, "PART_CHARS", 50)
    texts = ODD + ["plain words, and it's 12 more " * 30] + [soup(RND.randint(0, 200)) for _ in range(200)]
    for file in ("byte_bpe_50k.json", "word_bpe_49k.json"):
        path = tokenizers.path(file)
        lib = Tokenizer.from_file(path)
        rows = [(i, t, 1) for i, t in enumerate(texts)]
        got = {r.doc_id: tuple(r)[1:] for r in tokencount.count_tokens(spark.createDataFrame(rows, "doc_id long, text string, n_tokens int"), path).collect()}
        for i, t in enumerate(texts):
            n = len(lib.encode(t or "", add_special_tokens=False).ids)
            assert got[i] == (len((t or "").encode()), n, n > 1024)
    parts = list(tokencount.parts("ab cd " * 100, 50))
    assert "".join(parts) == "ab cd " * 100 and len(parts) > 5
    import sentencepiece

    path = tokenizers.path("piece_bpe_32k.model")
    lib = sentencepiece.SentencePieceProcessor(model_file=path)
    assert tokencount.Counter(path).counts(["a b", ""]) == [len(lib.encode("a b")), 0]
    assert tokencount.count_tokens(spark.createDataFrame([], "doc_id long, text string"), tokenizers.path("byte_bpe_50k.json")).count() == 0


def brute_repeats(rows):
    seen, out = set(), {}
    for d, t in sorted(rows, key=lambda r: r[0]):
        x = (t or "").encode()
        gone = bytearray(len(x))
        for p in range(len(x) - 99):
            if x[p : p + 100] in seen:
                gone[p : p + 100] = b"\1" * 100
            seen.add(x[p : p + 100])
        left = bytes(b for b, g in zip(x, gone, strict=True) if not g)
        runs = sum(1 for i, g in enumerate(gone) if g and (i == 0 or not gone[i - 1]))
        out[d] = (len(x), sum(gone), runs, hashlib.sha256(left).hexdigest(), left)
    return out


def repeated_rows():
    words = ["".join(RND.choice("abcdé") for _ in range(RND.randint(1, 8))) for _ in range(300)]
    text = lambda n: " ".join(RND.choice(words) for _ in range(n))
    passage, line = text(60), text(25)
    rows = []
    for d in range(60):
        t = text(RND.randint(5, 120))
        k = d % 6
        if k == 0:
            t = t + passage[: RND.randint(80, len(passage))] + text(10)
        elif k == 1:
            t = passage[RND.randint(0, 200) :] + t + line
        elif k == 2 and rows:
            t = rows[RND.randrange(len(rows))][1]
        elif k == 3 and rows:
            t = list(rows[RND.randrange(len(rows))][1])
            for _ in range(3):
                t[RND.randrange(len(t))] = "Q"
            t = "".join(t)
        elif k == 4:
            t = t + line + t + line
        rows.append((d * 3 % 61, t))
    odd = [None, "", "a" * 99, "a" * 100, "a" * 500, "a" * 100 + "b", "xyz" * 100, "é" * 120, "q" + "é" * 70, "ab" * 200 + "c" + "ab" * 200]
    return list({d: (d, t) for d, t in rows + [(100 + k, t) for k, t in enumerate(odd)]}.values())


@pytest.mark.parametrize("hot,part,problem", [(2000, 1 << 22, 1 << 21), (0, 1 << 22, 1 << 21), (1, 700, 5000)])
def test_repeats_against_brute_force(spark, monkeypatch, hot, part, problem):
    rows = repeated_rows()
    want = brute_repeats(rows)
    monkeypatch.setattr(suffixdedup, "HOT", hot)
    monkeypatch.setattr(suffixdedup, "_PART", part)
    monkeypatch.setattr(suffixdedup, "PROBLEM", problem)
    monkeypatch.setattr(suffixdedup, "_LOCAL", 1 if hot == 1 else 2000)  # anchors meet in the task or after it
    import pyarrow as pa

    docs = pa.record_batch([pa.array([r[0] for r in rows]), pa.array([r[1] or "" for r in rows])], names=["doc_id", "text"])
    anchors = pa.Table.from_batches(suffixdedup._anchor_rows([docs])).sort_by([(c, "ascending") for c in ("h", "doc_id", "pos")])
    told = pa.Table.from_batches(suffixdedup._settle(anchors.to_batches(max_chunksize=97)))
    msgs = {}
    for d, m in zip(told.column(0).to_pylist(), told.column(1).to_pylist(), strict=True):
        msgs.setdefault(d, []).append(m)
    held = [(d, t, msgs[d]) for d, t in rows if d in msgs]
    batch = pa.record_batch([pa.array([h[0] for h in held]), pa.array([h[1] for h in held]), pa.array([h[2] for h in held], pa.list_(pa.int64()))], names=["doc_id", "text", "msg"])
    pieces = pa.Table.from_batches(suffixdedup._pieces([batch])).sort_by([(c, "ascending") for c in ("key", "doc_id", "lo")])
    gone = {}
    for b in suffixdedup._merge(pieces.to_batches(max_chunksize=50)):
        for d, lo, hi in zip(*(c.to_pylist() for c in b.columns), strict=True):
            gone.setdefault(d, set()).update(range(lo, hi))
    for d, t in rows:
        x = (t or "").encode()
        assert bytes(b for i, b in enumerate(x) if i not in gone.get(d, ())) == want[d][4]


def test_removal_over_spark(spark):
    rows = repeated_rows()
    want = brute_repeats(rows)
    df = spark.createDataFrame([(*r, 1) for r in rows], "doc_id long, text string, sha int")
    got = {r.doc_id: (r.n_bytes, r.n_removed, len(r.spans), r.kept_sha256, bytes(r.kept)) for r in suffixdedup.remove_repeats(df, with_text=True).collect()}
    assert got == want
    assert suffixdedup.remove_repeats(df.limit(0)).count() == 0
    odd = spark.createDataFrame([(None, "z" * 300, 1)], df.schema)
    twice = suffixdedup.remove_repeats(df.union(df).union(odd)).groupBy("doc_id").agg(F.count("*").alias("n"), F.min("n_removed").alias("least"), F.max("n_removed").alias("most")).collect()
    assert all(r.n == 2 and r.least == r.most == want[r.doc_id][1] for r in twice) and len(twice) == len(rows)


def test_digests_of_many_copies_are_broadcast(spark, monkeypatch):
    monkeypatch.setattr(suffixdedup, "COPIES", 5)
    rows = [(i, ("copy " * 40) if i % 3 else f"other {i // 12} " * 20) for i in range(60)]
    df = spark.createDataFrame(rows, "doc_id long, text string")
    want = brute_repeats(rows)
    assert {r.doc_id: (r.n_bytes, r.n_removed, len(r.spans), r.kept_sha256) for r in suffixdedup.remove_repeats(df).collect()} == {d: v[:4] for d, v in want.items()}


def test_settled_surroundings_are_compared_byte_by_byte(monkeypatch):
    import pyarrow as pa

    monkeypatch.setattr(suffixdedup, "_between", lambda total, lo, hi: np.zeros(len(lo), np.uint64))  # all hashes collide
    texts = ["".join(RND.choice("abcd") for _ in range(140)) for _ in range(8)]
    texts += [texts[0], texts[3]]
    batch = pa.record_batch([pa.array(range(len(texts))), pa.array(texts)], names=["doc_id", "text"])
    found = pa.Table.from_batches(suffixdedup._anchor_rows([batch])).to_pylist()
    for r in found:
        if r["done"]:
            p0, n, at = r["pos"] >> 14, (r["pos"] >> 7 & 127) + 100, r["pos"] & 127
            piece = texts[r["doc_id"]][p0 : p0 + n]
            assert any(s["doc_id"] <= r["doc_id"] and (s["doc_id"], s["pos"]) != (r["doc_id"], r["pos"]) and s["pos"] & 127 == at and texts[s["doc_id"]][s["pos"] >> 14 :][:n] == piece for s in found)


@pytest.mark.parametrize("size", [400, 3000, 1 << 20])
def test_merged_orders_are_sorted(size):
    texts = [np.frombuffer("".join(RND.choice("ab") for _ in range(RND.randint(100, 300))).encode(), np.uint8) for _ in range(30)]
    texts += [texts[3].copy(), np.frombuffer(b"a" * 250, np.uint8), np.zeros(200, np.uint8)]
    rank, at = suffix.classes(texts, size)
    own = {}
    for i, t in enumerate(texts):
        for p in range(len(t) - 99):
            own.setdefault(t[p : p + 100].tobytes(), set()).add(int(rank[at[i] + p]))
    assert all(len(v) == 1 for v in own.values())
    order = sorted(own)
    assert [next(iter(own[k])) for k in order] == sorted(next(iter(v)) for v in own.values())  # classes follow byte order
    assert len({next(iter(v)) for v in own.values()}) == len(own)


def rotations(x):
    return [bytes(np.roll(x, -i)[:100]) for i in range(len(x))]


def common(a, b):
    return next((k for k in range(100) if a[k] != b[k]), 100)


def test_transform_of_a_shard():
    x = np.frombuffer(b"banana", np.uint8)
    t = suffix.shard(x)
    assert [bytes(x[i:]) for i in t.order if i < 6] == [b"a", b"ana", b"anana", b"banana", b"na", b"nana"]
    assert bytes(t.bwt()[t.order < 6]) == b"nnb\0aa"


def test_transforms_merge_without_their_texts():
    for _ in range(20):
        a = "".join(RND.choice("ab") for _ in range(RND.randint(0, 400)))
        b = "".join(RND.choice("ab\0") for _ in range(RND.randint(0, 300))) + "a" * RND.randint(0, 200) + a[:150]
        texts = [np.frombuffer(t.encode(), np.uint8) for t in (a, b, b[: RND.randint(0, len(b))])]
        circles = [suffix._pad(t) for t in texts]
        parts = [suffix.shard(t) for t in texts]
        got = suffix.merge(suffix.merge(*parts[:2]), parts[2])
        every = [r for x in circles for r in rotations(x)]
        before = [bytes([x[i - 1]]) for x in circles for i in range(len(x))]
        rot = [every[i] for i in got.order]
        assert sorted(got.order.tolist()) == list(range(len(every))) and rot == sorted(rot)
        assert bytes(got.bwt()) == b"".join(before[i] for i in got.order)
        for t, own in [(got, rot), (parts[0], [rotations(circles[0])[i] for i in parts[0].order])]:
            assert t.steps[1:].tolist() == [common(p, q) // suffix.STEP for p, q in zip(own, own[1:], strict=False)]
