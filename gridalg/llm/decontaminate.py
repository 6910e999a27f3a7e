"""Benchmark decontamination with a broadcast hash set of test word windows."""

from __future__ import annotations

import hashlib
from collections.abc import Iterator
from itertools import chain

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, functions as F

from gridalg.llm import kernel
from gridalg.llm.lineage import cut
from gridalg.llm.native import fresh

WINDOW = 10
#: Characters of benchmark text for one broadcast index (which takes about twelve times that); more are scanned in blocks.
BLOCK_BYTES = 16 << 20

_SCHEMA = "doc_id long, n_words long, items array<string>, spans array<struct<first:long,last:long,start:long,stop:long>>"
_ARROW = pa.schema(
    [
        ("doc_id", pa.int64()),
        ("n_words", pa.int64()),
        ("items", pa.list_(pa.string())),
        ("spans", pa.list_(pa.struct([(k, pa.int64()) for k in ("first", "last", "start", "stop")]))),
    ]
)


class WindowIndex:
    """Sorted hashes of the windows of a block of items, with their words for the check of each hit."""

    def __init__(self, items: list[tuple[object, str | None]], window: int = WINDOW):
        self.sizes: dict[int, tuple[np.ndarray, np.ndarray]] = {}
        found: dict[int, dict[int, dict[bytes, set[str]]]] = {}
        for item, text in items:
            raw, offsets = kernel.buffers(pa.array([text], pa.string()))
            s, e, h, _ = kernel.words(raw, offsets, kernel.ALNUM)
            if not len(h):
                continue
            size = min(window, len(h))
            low = kernel._LOWER[raw]
            for i, x in enumerate(kernel.windows(h, size).tolist()):
                text_of = b" ".join(low[s[i + k] : e[i + k]].tobytes() for k in range(size))
                found.setdefault(size, {}).setdefault(x, {}).setdefault(text_of, set()).add(str(item))
        self.owners = found
        for size, own in found.items():
            keys = np.sort(np.fromiter(own, np.uint64, len(own)))
            bits = np.zeros(1 << 20, bool)
            bits[(keys >> np.uint64(44)).astype(np.int64)] = True
            self.sizes[size] = (keys, bits)

    def hits(self, raw, s, e, h, first) -> Iterator[tuple[int, int, set[str]]]:
        """Index of the first word, number of words and items of each verified hit."""
        for size, (keys, bits) in self.sizes.items():
            w, at = kernel.row_windows(h, first, size)
            maybe = np.flatnonzero(bits[(w >> np.uint64(44)).astype(np.int64)])
            if not len(maybe):
                continue
            x = w[maybe]
            pos = np.minimum(np.searchsorted(keys, x), len(keys) - 1)
            for j in maybe[keys[pos] == x].tolist():
                i = int(at[j])
                text = b" ".join(kernel._LOWER[raw[s[i + k] : e[i + k]]].tobytes() for k in range(size))
                owners = self.owners[size][int(w[j])].get(text)
                if owners:
                    yield i, size, owners


def _rows(found: WindowIndex, column: pa.Array) -> Iterator[tuple[np.ndarray, list[set[str]], list[list[dict]]]]:
    """For runs of rows: number of words, items and spans of each."""
    raw, offsets = kernel.buffers(column)
    for lo, hi in kernel.pieces(offsets):
        own = offsets[lo : hi + 1] - offsets[lo]
        part = raw[offsets[lo] : offsets[hi]]
        s, e, h, first = kernel.words(part, own, kernel.ALNUM)
        items: list[set[str]] = [set() for _ in range(hi - lo)]
        edge = np.zeros(len(h) + 1, np.int64)
        for i, size, owners in found.hits(part, s, e, h, first):
            items[int(np.searchsorted(first, i, side="right")) - 1] |= owners
            edge[i] += 1
            edge[i + size] -= 1
        spans: list[list[dict]] = [[] for _ in items]
        for d in [d for d, x in enumerate(items) if x]:
            a, b = int(first[d]), int(first[d + 1])
            # windows never leave their row, so the sums inside it start and end at zero
            on = np.concatenate([[False], np.cumsum(edge[a:b]) > 0, [False]])
            turn = np.flatnonzero(on[1:] != on[:-1])
            for x, y in zip(turn[::2].tolist(), turn[1::2].tolist(), strict=True):
                spans[d].append({"first": x, "last": y, "start": int(s[a + x] - own[d]), "stop": int(e[a + y - 1] - own[d])})
        yield np.diff(first), items, spans


def _scan(index):
    """The hits of each row; what comes after id and text goes through."""

    @kernel.tidy
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            lo = 0
            for n_words, items, spans in _rows(index.value, batch.column(1)):
                more = [c.slice(lo, len(items)) for c in batch.columns[2:]]
                yield pa.record_batch(
                    [batch.column(0).slice(lo, len(items)).cast(pa.int64()), pa.array(n_words, pa.int64()), pa.array([sorted(x) for x in items], _ARROW[2].type), pa.array(spans, _ARROW[3].type), *more],
                    names=[*_ARROW.names, *batch.schema.names[2:]],
                )
                lo += len(items)

    return run


def _blocks(benchmark: DataFrame, item: str, text: str, window: int) -> Iterator[list[tuple[object, str | None]]]:
    """The benchmark in blocks of BLOCK_BYTES and one text at most, read a partition at a time; at least one block.

    A text beyond the size of a block is cut into parts that share all but one word of a window, which have the windows of the whole.
    """
    block: list[tuple[object, str | None]] = []
    load = 0
    for row in benchmark.select(F.col(item), F.col(text).cast("string")).toLocalIterator():
        for part in _cuts(row[1], window):
            if block and load + len(part) > BLOCK_BYTES:
                yield block
                block, load = [], 0
            block.append((row[0], part))
            load += len(part)
    yield block


def _cuts(text: str | None, window: int) -> Iterator[str]:
    if text is None or len(text) <= BLOCK_BYTES:
        yield text or ""
        return
    raw, offsets = kernel.buffers(pa.array([text], pa.large_string()))
    s, e, _, _ = kernel.words(raw, offsets, kernel.ALNUM)
    if len(s) <= window:
        yield text
        return
    at = 0
    while at + window <= len(s):
        # as many words as fit, and a window at least
        to = max(at + window, int(np.searchsorted(e, s[at] + BLOCK_BYTES)))
        yield raw[s[at] : e[min(to, len(s)) - 1]].tobytes().decode("utf-8", "replace")
        at = to - window + 1


def _union(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Items and spans of all blocks of a text, from lists of lists; spans that meet or overlap become one."""
    for batch in batches:
        items = [sorted({i for x in row for i in x}) for row in batch.column(2).to_pylist()]
        spans = []
        for row in batch.column(3).to_pylist():
            out: list[dict] = []
            for x in sorted((x for part in row for x in part), key=lambda x: x["first"]):
                if out and x["first"] <= out[-1]["last"]:
                    if x["last"] > out[-1]["last"]:
                        out[-1] = out[-1] | {"last": x["last"], "stop": x["stop"]}
                else:
                    out.append(x)
            spans.append(out)
        yield pa.record_batch([batch.column(0), batch.column(1), pa.array(items, _ARROW[2].type), pa.array(spans, _ARROW[3].type)], names=["hit_id", "hit_text", "hit_items", "hit_spans"])


_KEYED = _SCHEMA.replace("doc_id long, n_words long", "hit_id long, hit_text long").replace("items ", "hit_items ").replace("spans ", "hit_spans ")


def _block_hits(rows: DataFrame, blocks: Iterator[list], window: int) -> DataFrame:
    """hit_id, hit_text (a hash of the text), hit_items, hit_spans of each different row with hits.

    One index at a time is built, broadcast, used and released; only the hits of a block are kept.
    """
    sc = rows.sparkSession.sparkContext
    found = None
    for block in blocks:
        index = sc.broadcast(WindowIndex(block, window))
        # repeated rows hit the same, so one of each is enough
        part = rows.mapInArrow(_scan(index), f"{_SCHEMA}, hit_text long").filter("size(items) > 0").dropDuplicates(["doc_id", "hit_text"])
        part = cut(part)
        index.destroy()
        found = part if found is None else found.unionByName(part)
    both = found.groupBy("doc_id", "hit_text").agg(F.collect_list("items").alias("items"), F.collect_list("spans").alias("spans"))
    return both.mapInArrow(_union, _KEYED)


def find_windows(docs: DataFrame, benchmark: DataFrame, *, window: int = WINDOW, id_col: str = "doc_id", text_col: str = "text", item_col: str = "item_id", item_text: str = "text") -> DataFrame:
    """Hits of benchmark windows in each document: doc_id, n_words, items (sorted strings), spans.

    Words are lower-cased runs of ASCII letters and digits and characters beyond ASCII. A span gives first
    and last (exclusive) word and start and stop byte. A null text has no words; an item without words has no
    window; an item shorter than the window is one window. Each row is judged by its own text and gives one row, at
    every size of the benchmark: rows that are repeated, share an id or have none too. Other columns are not read. An
    empty benchmark gives no hits. Indexes are broadcast one at a time for blocks of BLOCK_BYTES, so their size never
    grows with the data.
    """
    sc = docs.sparkSession.sparkContext
    rows = docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).cast("string").alias("text"))
    blocks = _blocks(benchmark, item_col, item_text, window)
    first, second = next(blocks), next(blocks, None)
    if second is None:
        return rows.mapInArrow(_scan(sc.broadcast(WindowIndex(first, window))), _SCHEMA)
    keyed = rows.withColumn("hit_text", F.xxhash64("text"))
    hits = _block_hits(keyed, chain([first, second], blocks), window)
    plain = keyed.mapInArrow(_scan(sc.broadcast(WindowIndex([], window))), f"{_SCHEMA}, hit_text long").drop("items", "spans").withColumnRenamed("hit_text", "own_text")
    none = [F.expr(f"cast(array() as {t})") for t in ("array<string>", "array<struct<first:long,last:long,start:long,stop:long>>")]
    joined = plain.join(hits, F.col("doc_id").eqNullSafe(F.col("hit_id")) & (F.col("own_text") == F.col("hit_text")), "left")
    return joined.select("doc_id", "n_words", F.coalesce("hit_items", none[0]).alias("items"), F.coalesce("hit_spans", none[1]).alias("spans"))


def digest(found: DataFrame) -> DataFrame:
    """Counts and the digest of the item ids."""
    n_hit = F.aggregate("spans", F.lit(0).cast("long"), lambda a, x: a + x["last"] - x["first"])
    return found.select("doc_id", "n_words", n_hit.alias("n_hit"), F.size("items").cast("long").alias("n_items"), F.sha2(F.array_join("items", ","), 256).alias("items_sha256"), (F.size("items") > 0).alias("contaminated"))


def _clean(index, mode: str, text_at: int, chars_at: int, spans_at: int):
    """Whole rows without hits or with the hits cut out; hits are looked for, or read from a last column of spans."""

    @kernel.tidy
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            if spans_at >= 0:
                spans = batch.column(spans_at).to_pylist()
                batch = pa.RecordBatch.from_arrays(batch.columns[:spans_at], names=batch.schema.names[:spans_at])
            else:
                spans = [x for _, _, some in _rows(index.value, batch.column(text_at)) for x in some]
            hit = [i for i, x in enumerate(spans) if x]
            if hit and mode == "document":
                keep = np.ones(batch.num_rows, bool)
                keep[hit] = False
                yield from kernel.kept(batch, keep)
                continue
            elif hit:
                texts = batch.column(text_at).to_pylist()
                chars = batch.column(chars_at).to_pylist() if chars_at >= 0 else None
                for i in hit:
                    raw = texts[i].encode()
                    edges = [0, *(p for x in spans[i] for p in (x["start"], x["stop"])), len(raw)]
                    texts[i] = b"".join(raw[a:b] for a, b in zip(edges[::2], edges[1::2], strict=True)).decode()
                    if chars is not None:
                        chars[i] = len(texts[i])
                columns = list(batch.columns)
                columns[text_at] = pa.array(texts, columns[text_at].type)
                if chars is not None:
                    columns[chars_at] = pa.array(chars, columns[chars_at].type)
                batch = pa.RecordBatch.from_arrays(columns, names=batch.schema.names)
            yield batch

    return run


def decontaminate(docs: DataFrame, benchmark: DataFrame, *, mode: str = "document", window: int = WINDOW) -> DataFrame:
    """Documents without benchmark passages, with the columns they came with.

    mode 'document' drops each document with a hit; 'span' cuts the hit bytes out of its text and keeps the rest
    (n_chars follows if there is such a column). Documents without hits, null texts included, stay as they are. Each
    row is judged by its own text, whatever its id and however often it is repeated. With one block of benchmark this is one pass without exchange.
    """
    if mode not in ("document", "span"):
        raise ValueError(f"mode {mode!r}: 'document' or 'span'")
    names = docs.columns
    at, chars = names.index("text"), names.index("n_chars") if "n_chars" in names else -1
    blocks = _blocks(benchmark, "item_id", "text", window)
    first, second = next(blocks), next(blocks, None)
    if second is None:
        index = docs.sparkSession.sparkContext.broadcast(WindowIndex(first, window))
        return docs.mapInArrow(_clean(index, mode, at, chars, -1), docs.schema)
    id_, hash_, items, spans = fresh(names, "hit_id", "hit_text", "hit_items", "hit_spans")
    keyed = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text"), F.xxhash64(F.col("text").cast("string")).alias("hit_text"))
    hits = _block_hits(keyed, chain([first, second], blocks), window).toDF(id_, hash_, items, spans).drop(items)
    joined = docs.join(hits, F.col("doc_id").cast("long").eqNullSafe(F.col(id_)) & (F.xxhash64(F.col("text").cast("string")) == F.col(hash_)), "left")
    return joined.select(*names, spans).mapInArrow(_clean(None, mode, at, chars, len(names)), docs.schema)


def sha_of(items: set[str]) -> str:
    return hashlib.sha256(",".join(sorted(items)).encode()).hexdigest()
