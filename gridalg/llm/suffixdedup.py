"""Removal of repeated strings of 100 bytes and more, by merged Burrows-Wheeler transforms of the text that can repeat.

1. Texts equal to an earlier one as a whole are found by their digest (SHA-256): all their bytes repeat.
2. Anchors: in every 100-byte string, the 32-byte substrings of smallest hash (all of them on a tie). Equal
   strings hold equal anchors at equal offsets, so only the surroundings of anchors that occur twice matter. An anchor whose
   surroundings (all 100-byte strings around it) a task has seen before, byte by byte, is settled there, so that a
   passage of very many texts doesn't meet in one task.
3. Anchor occurrences meet by hash; those that occur once are left out. The surroundings of the others are the pieces,
   dealt by anchor. Equal pieces of an anchor are folded byte by byte, the earliest stays.
4. What differs are the shards: their transforms are built, merged by interleave refinement (see suffix.py), and the
   intervals of rotations with 100 bytes in common give the repeats; the earliest string of each interval stays.
   Anchors with very many occurrences are dealt by longer substrings.
5. The removed ranges meet their texts again, which are dealt once by id for all steps.

Hashes of 64 bits choose what meets. What is removed has been compared byte by byte, whole texts by SHA-256.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, functions as F

from gridalg.llm import kernel, suffix
from gridalg.llm.lineage import cut

N = suffix.DEPTH
K = 32
SPAN = N - K + 1
#: Occurrences of one anchor beyond which they are dealt by longer substrings.
HOT = 2000
#: Copies of one text, at least, that are resolved by a broadcast of their digests, and how many digests that may be.
COPIES, DIGESTS = 1000, 10_000
#: Bytes of one merge problem; whole groups are put together up to it.
PROBLEM = 1 << 20
U64 = np.uint64


def _slide(x: np.ndarray, width: int, f) -> np.ndarray:
    done = 1
    while done * 2 <= width:
        x = f(x[:-done], x[done:])
        done *= 2
    return f(x[: len(x) - (width - done)], x[width - done :]) if done < width else x


def _prefix(x: np.ndarray) -> np.ndarray:
    p, _ = kernel._power(len(x) + 1)
    total = np.zeros(len(x) + 1, U64)
    with np.errstate(over="ignore"):
        np.cumsum(kernel._VALUE[x] * p[: len(x)], out=total[1:])
    return total


def _between(total: np.ndarray, lo: np.ndarray, hi: np.ndarray) -> np.ndarray:
    _, inverse = kernel._power(len(total))
    with np.errstate(over="ignore"):
        return kernel.mix((total[hi] - total[lo]) * inverse[lo] + (hi - lo).astype(U64))


def anchors(x: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Place, hash and hash of the surroundings of each anchor of a text.

    The strings of an anchor are the 100-byte strings in which it has the smallest hash, one run of starts p0 to p1;
    the surroundings are all their bytes. A place packs p0, p1 - p0 and the anchor's distance from p0.
    """
    n = len(x)
    if n < N:
        z = np.zeros(0, np.int64)
        return z, z.view(U64), z.view(U64)
    total = _prefix(x)
    starts = np.arange(n - K + 1)
    h = _between(total, starts, starts + K)
    low = _slide(h, SPAN, np.minimum)
    edge = np.zeros(SPAN - 1, U64)
    at = np.flatnonzero(_slide(np.concatenate([edge, low, edge]), SPAN, np.maximum) == h)
    p0 = np.flatnonzero(np.concatenate([[True], low[1:] != low[:-1]]))
    p1 = np.append(p0[1:], len(low)) - 1
    if len(p0) != len(at) or (low[p0] != h[at]).any() or (p1 > at).any() or (at > p0 + SPAN - 1).any():  # ties
        bounds = []
        for a, v in zip(at.tolist(), h[at], strict=True):
            left = max(0, a - SPAN + 1)
            own = np.flatnonzero(low[left : a + 1] == v)
            bounds.append((left + own[0], left + own[-1]))
        p0, p1 = np.array(bounds, np.int64).T
    with np.errstate(over="ignore"):
        around = kernel.mix(_between(total, p0, p1 + N) + (at - p0).astype(U64) * U64(0x9E3779B97F4A7C15))
    return p0 << 14 | (p1 - p0) << 7 | (at - p0), h[at], around


#: Bytes of a long text whose anchors are found at once; consecutive parts overlap so that no string is missed.
_PART = 1 << 22


def _parts(x: np.ndarray) -> Iterator[tuple[np.ndarray, np.ndarray, np.ndarray]]:
    if len(x) <= _PART:
        yield anchors(x)
        return
    for lo in range(0, len(x), _PART):
        left, right = max(0, lo - 3 * N), min(len(x), lo + _PART + 3 * N)
        place, h, around = anchors(x[left:right])
        at = (place >> 14) + (place & 127) + left
        own = (at >= lo) & (at < lo + _PART)
        yield place[own] + (left << 14), h[own], around[own]


#: Anchors of a task that are compared with each other before they are dealt out.
_LOCAL = 400_000


def _same(raw: np.ndarray, a: np.ndarray, b: np.ndarray, size: np.ndarray) -> np.ndarray:
    """Whether raw holds the same size[i] bytes from a[i] and from b[i] on."""
    out = np.ones(len(a), bool)
    for lo in range(0, len(a), 1 << 15):
        some = slice(lo, lo + (1 << 15))
        n = size[some]
        step = np.arange(int(n.sum())) - np.repeat(np.cumsum(n) - n, n)
        differ = raw[np.repeat(a[some], n) + step] != raw[np.repeat(b[some], n) + step]
        out[some] = np.add.reduceat(differ, np.cumsum(n) - n) == 0 if len(n) else out[some]
    return out


def _local(rows: list[tuple], raw: np.ndarray) -> pa.RecordBatch:
    """Anchors to deal by hash. One whose surroundings the task has seen at an earlier place is settled: it is dealt anywhere."""
    h, around, doc, pos, base = (np.concatenate(c) for c in zip(*rows, strict=True))
    turn = np.lexsort((pos, doc, around, h))
    h, around, doc, pos, base = h[turn], around[turn], doc[turn], pos[turn], base[turn]
    again = np.zeros(len(h), bool)
    again[1:] = (h[1:] == h[:-1]) & (around[1:] == around[:-1])
    same = np.zeros(len(h), bool)  # a row given twice is one occurrence
    same[1:] = again[1:] & (doc[1:] == doc[:-1]) & (pos[1:] == pos[:-1])
    h, doc, pos, base, again = (x[~same] for x in (h, doc, pos, base, again))
    hit = np.flatnonzero(again)
    if len(hit):
        first = np.maximum.accumulate(np.where(again, 0, np.arange(len(h))))[hit]
        place = pos >> 14
        size = (pos[hit] >> 7 & 127) + N
        alike = (pos[hit] & 0x3FFF) == (pos[first] & 0x3FFF)  # as many strings, and the anchor at the same distance
        again[hit] = alike & _same(raw, (base + place)[np.where(alike, hit, first)], (base + place)[first], size)
    with np.errstate(over="ignore"):
        free = kernel.mix(doc.view(U64) * U64(0x9E3779B97F4A7C15) + pos.view(U64)).view(np.int64)
    return pa.record_batch([pa.array(np.where(again, free, h)), pa.array(doc), pa.array(pos), pa.array(again)], names=["h", "doc_id", "pos", "done"])


def _anchor_rows(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    rows, texts, load, size = [], [], 0, 0
    for batch in batches:
        raw, offsets = kernel.buffers(batch.column(1))
        ids = np.asarray(batch.column(0).cast(pa.int64()))
        for i in range(batch.num_rows):
            text = raw[offsets[i] : offsets[i + 1]]
            for at, h, around in _parts(text):
                rows.append((h.view(np.int64), around.view(np.int64), np.full(len(at), ids[i]), at, np.full(len(at), size)))
                load += len(at)
            texts.append(text)
            size += len(text)
            if load > _LOCAL:
                yield _local(rows, np.concatenate(texts))
                rows, texts, load, size = [], [], 0, 0
    if rows:
        yield _local(rows, np.concatenate(texts))


def _settle(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """From occurrences sorted by anchor, doc and position: doc_id and position * 4 + kind.

    Kind 1: settled. Kind 2: its anchor occurs elsewhere; kind 3: in very many places. An occurrence that nothing shares is left out.
    """
    held = [np.zeros(0, np.int64)] * 3
    hot: int | None = None  # anchor of a group that is being passed on in parts

    def out(d, p, kind):
        keep = kind > 0
        return pa.record_batch([pa.array(d[keep]), pa.array(p[keep] * 4 + kind[keep])], names=["doc_id", "msg"])

    def whole(h, d, p):
        group = np.ones(len(h), bool)
        group[1:] = h[1:] != h[:-1]
        number = np.cumsum(group) - 1
        count = np.bincount(number)[number] if len(h) else np.zeros(0, np.int64)
        return out(d, p, np.where(count < 2, 0, np.where(count > HOT, 3, 2)))

    for batch in batches:
        done = np.asarray(batch.column(3).cast(pa.int8()), bool)
        columns = [np.asarray(x) for x in batch.columns[:3]]
        if done.any():
            yield pa.record_batch([pa.array(columns[1][done]), pa.array(columns[2][done] * 4 + 1)], names=["doc_id", "msg"])
        held = [np.concatenate([a, x[~done]]) for a, x in zip(held, columns, strict=True)]
        fresh = np.ones(len(held[0]), bool)  # a row that is given twice is one occurrence
        fresh[1:] = np.logical_or.reduce([a[1:] != a[:-1] for a in held])
        held = [a[fresh] for a in held]
        if len(held[0]) < 50_000:
            continue
        if hot is not None:
            n = int(np.searchsorted(held[0] != hot, True)) if (held[0] != hot).any() else len(held[0])
            yield out(held[1][:n], held[2][:n], np.full(n, 3))
            held = [a[n:] for a in held]
            if not len(held[0]):
                continue
            hot = None
        change = np.flatnonzero(held[0][1:] != held[0][:-1])
        n = int(change[-1]) + 1 if len(change) else 0
        if n:
            yield whole(*[a[:n] for a in held])
            held = [a[n:] for a in held]
        elif len(held[0]) > max(HOT, 200_000):
            yield out(held[1], held[2], np.full(len(held[0]), 3))
            hot = int(held[0][-1])
            held = [a[:0] for a in held]
    if hot is not None and len(held[0]):
        n = int((held[0] == hot).argmin()) if not (held[0] == hot).all() else len(held[0])
        yield out(held[1][:n], held[2][:n], np.full(n, 3))
        held = [a[n:] for a in held]
    if len(held[0]):
        yield whole(*held)


_PIECE = pa.schema([("key", pa.int64()), ("doc_id", pa.int64()), ("lo", pa.int64()), ("hi", pa.int64()), ("piece", pa.binary())])


def _union(lo: np.ndarray, hi: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Maximal runs of a set of ranges; ranges that touch make one."""
    turn = np.argsort(lo, kind="stable")
    lo, hi = lo[turn], np.maximum.accumulate(hi[turn])
    new = np.ones(len(lo), bool)
    new[1:] = lo[1:] > hi[:-1]
    at = np.flatnonzero(new)
    return lo[at], hi[np.append(at[1:], len(lo)) - 1] if len(at) else hi


#: Bytes of pieces that a task remembers, to fold equal ones before they are dealt.
_KNOWN = 32 << 20


def _pieces(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """From texts and messages, sorted by id: settled ranges (without piece) and pieces to merge, with their key.

    A piece whose bytes the task has dealt under the same key from an earlier place is settled, so a key of very many
    equal pieces gets one from each task.
    """
    known: dict[tuple[int, bytes], tuple[int, int]] = {}
    held = 0
    for batch in batches:
        raw, offsets = kernel.buffers(batch.column(1))
        ids = np.asarray(batch.column(0).cast(pa.int64()))
        rows: list[tuple] = []
        load = 0
        for i in range(batch.num_rows):
            x = raw[offsets[i] : offsets[i + 1]]
            msg = np.sort(np.asarray(batch.column(2)[i].values, np.int64))
            place, kind = msg >> 2, msg & 3
            p0, p1 = place >> 14, (place >> 14) + (place >> 7 & 127)
            at = p0 + (place & 127)
            doc = int(ids[i])
            done = kind == 1
            settled = [(p0[done], p1[done] + N)]
            new = ~done
            for lo, hi, a, k in zip(p0[new].tolist(), p1[new].tolist(), at[new].tolist(), kind[new].tolist(), strict=True):
                if k == 2:
                    spots = [(lo, hi, a, a + K)]
                else:  # every string of the first spot holds the bytes from a - 34 on, of the second those from a on
                    spots = [(lo, min(hi, a - 34), a - 34, a + K), (max(lo, a - 33), hi, a, a + 67)]
                for s, e, ks, ke in spots:
                    if s <= e:
                        digest = hashlib.blake2b(x[ks:ke].tobytes() + bytes([k, ks == a]), digest_size=8).digest()
                        key, piece = int.from_bytes(digest, "little", signed=True), x[s : e + N].tobytes()
                        first = known.setdefault((key, piece), (doc, s))
                        if first < (doc, s):
                            settled.append((np.array([s]), np.array([e + N])))
                            continue
                        rows.append((key, doc, s, e + N, piece))
                        load += len(piece)
                        held += len(piece) + 200
                        if held > _KNOWN:
                            known.clear()
                            held = 0
            for lo, hi in zip(*_union(*(np.concatenate(c) for c in zip(*settled, strict=True))), strict=True):
                rows.append((doc * 31 + int(lo), doc, int(lo), int(hi), None))
            if load > 2 << 20 or len(rows) > 50_000:
                yield pa.record_batch([pa.array(c, t.type) for c, t in zip(zip(*rows, strict=True), _PIECE, strict=True)], schema=_PIECE)
                rows, load = [], 0
        if rows:
            yield pa.record_batch([pa.array(c, t.type) for c, t in zip(zip(*rows, strict=True), _PIECE, strict=True)], schema=_PIECE)


def repeats(docs: np.ndarray, starts: np.ndarray, texts: list[np.ndarray]) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """doc, start and end of the ranges of pieces whose 100-byte strings occur earlier among the pieces."""
    rank, at = suffix.classes(texts)
    windows = np.array([max(0, len(t) - N + 1) for t in texts], np.int64)
    owner = np.repeat(np.arange(len(texts)), windows)
    inner = np.arange(len(owner)) - np.repeat(np.cumsum(windows) - windows, windows)
    group, start = rank[at[owner] + inner], starts[owner] + inner
    _, doc = np.unique(docs, return_inverse=True)
    code = (doc[owner].astype(np.int64) << 40) + start
    turn = np.argsort(code)[::-1]
    least = np.zeros(int(rank.max(initial=0)) + 1, np.int64)
    least[group[turn]] = code[turn]  # the last write is the earliest string
    hit = np.flatnonzero(code != least[group])
    if not len(hit):
        return docs[:0], starts[:0], starts[:0]
    new = np.ones(len(hit), bool)
    new[1:] = (hit[1:] != hit[:-1] + 1) | (owner[hit[1:]] != owner[hit[:-1]])
    a = np.flatnonzero(new)
    b = np.append(a[1:], len(hit)) - 1
    return docs[owner[hit[a]]], start[hit[a]], start[hit[b]] + N


def _merge(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """From pieces sorted by key, doc and start: doc_id and removed range; settled ranges pass through.

    A piece equal to an earlier one of its key is removed whole. A key with one kind of piece needs no more: two of its
    strings would be equal only if the anchor were there twice. The kinds of the other keys are merged.
    """
    held: list[tuple[int, int, bytes]] = []  # doc, start and piece of the keys that wait for a merge
    group: dict[bytes, tuple[int, int]] = {}  # the kinds of the current key, each with its earliest place
    now: int | None = None
    load = 0

    def batch_of(d, s, e):
        return pa.record_batch([pa.array(np.asarray(d, np.int64)), pa.array(np.asarray(s, np.int64)), pa.array(np.asarray(e, np.int64))], names=["doc_id", "lo", "hi"])

    def solve():
        docs, starts, texts = zip(*held, strict=True)
        return batch_of(*repeats(np.array(docs, np.int64), np.array(starts, np.int64), [np.frombuffer(t, np.uint8) for t in texts]))

    def end_key() -> int:
        if len(group) > 1:
            held.extend((d, s, t) for t, (d, s) in group.items())
            return sum(map(len, group))
        return 0

    for batch in batches:
        settled = np.asarray(batch.column(4).is_null())
        if settled.any():
            yield batch_of(*(np.asarray(c)[settled] for c in batch.columns[1:4]))
            batch = batch.filter(pa.array(~settled))
        out: list[tuple[int, int, int]] = []
        for key, doc, lo, text in zip(*(batch.column(k).to_pylist() for k in (0, 1, 2, 4)), strict=True):
            if key != now:
                load += end_key()
                if load >= PROBLEM:
                    yield solve()
                    held.clear()
                    load = 0
                group, now = {}, key
            first = group.setdefault(text, (doc, lo))
            if first != (doc, lo):  # rows come in order, so the piece held is the earlier one
                out.append((doc, lo, lo + len(text)))
        if out:
            yield batch_of(*zip(*out, strict=True))
    end_key()
    if held:
        yield solve()


def _cut(with_text: bool):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            raw, offsets = kernel.buffers(batch.column(1))
            removed, spans, digest, texts = [], [], [], []
            for i in range(batch.num_rows):
                x = raw[offsets[i] : offsets[i + 1]]
                lo, hi = _union(np.asarray(batch.column(2)[i].values, np.int64), np.asarray(batch.column(3)[i].values, np.int64))
                keep = np.ones(len(x), bool)
                for a, b in zip(lo.tolist(), hi.tolist(), strict=True):
                    keep[a:b] = False
                left = x[keep].tobytes()
                removed.append(len(x) - len(left))
                spans.append([{"start": a, "stop": b} for a, b in zip(lo.tolist(), hi.tolist(), strict=True)])
                digest.append(hashlib.sha256(left).hexdigest())
                texts.append(left if with_text else None)
            yield pa.record_batch(
                [batch.column(0).cast(pa.int64()), pa.array(removed, pa.int64()), pa.array(spans, pa.list_(pa.struct([("start", pa.int64()), ("stop", pa.int64())]))), pa.array(digest, pa.string()), pa.array(texts, pa.binary())],
                names=["doc_id", "n_removed", "spans", "kept_sha256", "kept"],
            )

    return run


def _copies(own: DataFrame) -> tuple[DataFrame, DataFrame]:
    """The first document of each digest, and the later ones. Digests of very many copies are broadcast, so they need not meet in one task."""
    first = own.groupBy("sha").agg(F.min("doc_id").alias("first"), F.count("*").alias("copies"))
    n = own.agg(F.count("*")).first()[0]
    limit = max(COPIES, n // DIGESTS)  # so there are DIGESTS of them at most
    some = cut(first.filter("copies > 1"))
    hot = F.broadcast(some.filter(F.col("copies") > limit).select("sha", "first"))
    rest = own.join(hot.select("sha"), "sha", "left_anti").join(some.filter(F.col("copies") <= limit).select("sha", "first"), "sha")
    later = own.join(hot, "sha").select("doc_id", "first").unionByName(rest.select("doc_id", "first")).filter("doc_id <> first")
    return first.select(F.col("first").alias("doc_id")), later.select("doc_id", F.lit(True).alias("copy")).distinct()


def remove_repeats(docs: DataFrame, *, with_text: bool = False, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """doc_id, n_bytes, n_removed, spans, kept_sha256 (and kept, the remaining bytes) for each document.

    Every byte is removed that a 100-byte string covers which also starts earlier: in a smaller doc_id, or in the
    same text at an earlier place. Strings never cross texts and are judged on the input. Null counts as empty; texts
    under 100 bytes stay whole. Rows without id are left out; rows that are given twice count once and each gets the
    result, but one id must not stand for different texts. Other columns are not read. What is left of a text
    may not be whole UTF-8 characters, so kept is binary.
    """
    texts = docs.filter(F.col(id_col).isNotNull()).select(F.col(id_col).cast("long").alias("doc_id"), F.coalesce(F.col(text_col).cast("string"), F.lit("")).alias("text"))
    own = cut(texts.select("doc_id", F.octet_length("text").cast("long").alias("n_bytes"), F.sha2("text", 256).alias("sha")))
    firsts, again = _copies(own.filter(f"n_bytes >= {N}"))

    # One exchange of the texts serves three joins: they must stay inner joins on equal plans, so that Spark reuses it.
    dealt = docs.select(F.col(id_col).alias("doc_id"), F.col(text_col).alias("text")) if [id_col, text_col] != ["doc_id", "text"] else docs.select("doc_id", "text")
    if dict(dealt.dtypes) != {"doc_id": "bigint", "text": "string"}:
        dealt = dealt.select(F.col("doc_id").cast("long"), F.col("text").cast("string"))
    dealt = dealt.filter(F.col("doc_id").isNotNull() & (F.octet_length("text") >= N)).repartition("doc_id")
    single = dealt.join(firsts.withColumn("one", F.lit(1)).hint("merge"), "doc_id").select("doc_id", "text", "one")
    found = single.mapInArrow(_anchor_rows, "h long, doc_id long, pos long, done boolean")
    told = found.repartition("h").sortWithinPartitions("h", "doc_id", "pos").mapInArrow(_settle, "doc_id long, msg long")
    per_doc = told.groupBy("doc_id").agg(F.collect_list("msg").alias("msg"))
    pieces = dealt.join(per_doc.hint("merge"), "doc_id").select("doc_id", "text", "msg").mapInArrow(_pieces, "key long, doc_id long, lo long, hi long, piece binary")
    ranges = pieces.repartition("key").sortWithinPartitions("key", "doc_id", "lo").mapInArrow(_merge, "doc_id long, lo long, hi long")
    gone = ranges.groupBy("doc_id").agg(F.collect_list("lo").alias("lo"), F.collect_list("hi").alias("hi"))
    done = dealt.join(gone.hint("merge"), "doc_id").select("doc_id", "text", "lo", "hi").mapInArrow(_cut(with_text), "doc_id long, n_removed long, spans array<struct<start:long,stop:long>>, kept_sha256 string, kept binary")
    done = (done if with_text else done.drop("kept")).dropDuplicates(["doc_id"])

    whole = F.array(F.struct(F.lit(0).cast("long").alias("start"), F.col("n_bytes").alias("stop")))
    none = F.expr("cast(array() as array<struct<start:long,stop:long>>)")
    copy = F.coalesce("copy", F.lit(False))
    out = own.join(again, "doc_id", "left").join(done, "doc_id", "left").select(
        "doc_id",
        "n_bytes",
        F.when(copy, F.col("n_bytes")).otherwise(F.coalesce("n_removed", F.lit(0))).alias("n_removed"),
        F.when(copy, whole).otherwise(F.coalesce("spans", none)).alias("spans"),
        F.when(copy, F.sha2(F.lit(""), 256)).otherwise(F.coalesce("kept_sha256", "sha")).alias("kept_sha256"),
        *([F.when(copy, F.lit("").cast("binary")).otherwise(F.col("kept")).alias("kept")] if with_text else []),
    )
    if with_text:
        out = out.join(texts.dropDuplicates(["doc_id"]), "doc_id", "left").withColumn("kept", F.coalesce("kept", F.col("text").cast("binary"))).drop("text")
    return out
