"""SentencePiece encoding and decoding as a weighted finite-state transducer.

The model file is compiled into three transducers that are composed with each text: a normaliser, whose arcs are the
character map of the file (longest source first, other characters as they are) and whose states drop repeated spaces, add the
leading gap and write spaces as gap signs; arcs from characters to pieces, over a trie; and byte arcs, which write a
character that has no piece as its bytes. The composition is a lattice over the text's positions, built as far as the
search reads it; the tropical shortest path through it is the encoding.

Weights follow the model type. In a unigram model a piece costs minus its score. In a merge model the weight of a
piece depends on the one before it (states remember it): zero if merging the two side by side gives just these two,
infinite if not. A sequence of pieces is what merging yields exactly if each neighbouring pair is, so the path of
weight zero is unique and equals the merge result.

Texts are cut where no piece can span, so most words come from a cache of bounded size.
"""

from __future__ import annotations

import hashlib
import re
import struct
import sys
from array import array
from collections.abc import Iterator
from functools import lru_cache

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, functions as F

GAP = "▁"
assert sys.byteorder == "little" and array("i").itemsize == 4
NORMAL, UNKNOWN, CONTROL, USER, UNUSED, BYTE = 1, 2, 3, 4, 5, 6  # piece types of the file format
UNIGRAM, MERGE = 1, 2
#: Entries of the caches of words (two generations) and of pairs, and characters of a word that is kept.
WORDS, PAIRS, LONGEST = 100_000, 500_000, 40


def _number(data: bytes, at: int) -> tuple[int, int]:
    value = shift = 0
    while True:
        byte = data[at]
        at += 1
        value |= (byte & 127) << shift
        shift += 7
        if byte < 128:
            return value, at


def _fields(data: bytes) -> Iterator[tuple[int, int | bytes]]:
    """Field numbers and values of a message in protocol-buffer wire format."""
    at = 0
    while at < len(data):
        tag, at = _number(data, at)
        if tag & 7 == 0:
            value, at = _number(data, at)
        else:
            if tag & 7 == 2:
                size, at = _number(data, at)
            else:
                size = 4 if tag & 7 == 5 else 8
            value, at = data[at : at + size], at + size
        yield tag >> 3, value


def character_map(blob: bytes) -> dict[str, str]:
    """Sources and targets of a file's character map: the size of a trie in a double array, the trie, and targets that end in zero."""
    size = int.from_bytes(blob[:4], "little")
    units, targets = np.frombuffer(blob[4 : 4 + size], "<u4"), blob[4 + size :]
    labels = np.arange(256, dtype=np.uint32)
    below = lambda at: int(at ^ ((units[at] >> 10) << ((units[at] & 512) >> 6)))
    out: dict[str, str] = {}
    todo = [(below(0), b"")] if len(units) else []
    while todo:
        base, source = todo.pop()
        near = base ^ labels
        near = near[near < len(units)]
        for at in near[(units[near] & np.uint32(0x800000FF)) == (near ^ base)].tolist():
            text = source + bytes([at ^ base])
            if at ^ base:
                if units[at] >> 8 & 1:
                    start = int(units[below(at)] & 0x7FFFFFFF)
                    out[text.decode()] = targets[start : targets.index(0, start)].decode()
                todo.append((below(at), text))
    return out


class Normaliser:
    """The first transducer. prefix: add a leading gap; squeeze: drop spaces at the ends and repeated ones."""

    def __init__(self, sources: dict[str, str], prefix: bool, squeeze: bool):
        self.prefix, self.squeeze = prefix, squeeze
        self.one = {ord(k): v for k, v in sources.items() if len(k) == 1}
        more = sorted((k for k in sources if len(k) > 1), key=len, reverse=True)
        #: Sources by their first character, longest first; they matter only where a later character of one is seen.
        self.heads: dict[str, list[str]] = {}
        for k in more:
            self.heads.setdefault(k[0], []).append(k)
        self.later = frozenset(c for k in more for c in k[1:])
        self.sources = sources

    def __call__(self, text: str) -> str:
        if self.heads and not self.later.isdisjoint(text):
            out, i = [], 0
            while i < len(text):
                k = next((k for k in self.heads.get(text[i], ()) if text.startswith(k, i)), text[i])
                out.append(self.sources.get(k, k))
                i += len(k)
            text = "".join(out)
        elif self.one:
            text = text.translate(self.one)
        if self.squeeze:
            text = re.sub(" +", " ", text.strip(" "))
        if not text:
            return ""
        return (GAP if self.prefix else "") + text.replace(" ", GAP)


class Transducer:
    """A compiled model file."""

    def __init__(self, model: bytes):
        self.kind, self.prefix, self.squeeze = UNIGRAM, True, True
        sources: dict[str, str] = {}
        pieces: list[tuple[str, float, int]] = []
        for key, value in _fields(model):
            if key == 1:
                d = dict(_fields(value))
                pieces.append((d[1].decode(), struct.unpack("<f", d[2])[0] if 2 in d else 0.0, d.get(3, NORMAL)))
            elif key == 2:
                self.kind = dict(_fields(value)).get(3, UNIGRAM)
            elif key == 3:
                d = dict(_fields(value))
                self.prefix, self.squeeze = bool(d.get(3, 1)), bool(d.get(4, 1))
                if d.get(2):
                    sources = character_map(d[2])
        if self.kind not in (UNIGRAM, MERGE):
            raise ValueError("only unigram and merge models are compiled")
        self.normalise = Normaliser(sources, self.prefix, self.squeeze)
        self.pieces = pieces
        self.ids = {p: i for i, (p, _, t) in enumerate(pieces) if t in (NORMAL, USER)}
        self.score = [s for _, s, _ in pieces]
        self.rank = {p: self.score[i] for p, i in self.ids.items()}
        self.unknown = next((i for i, p in enumerate(pieces) if p[2] == UNKNOWN), 0)
        self.byte = {int(p[3:5], 16): i for i, (p, _, t) in enumerate(pieces) if t == BYTE}
        if self.kind == MERGE:  # pieces that merging their characters doesn't give never occur
            self.ids = {p: i for p, i in self.ids.items() if self.merges(p) == [p]}
        self.trie: dict = {}  # for each character, the nodes below it and the id of the piece that ends there, or None
        for p, i in self.ids.items():
            node = self.trie
            for c in p[:-1]:
                node = node.setdefault(c, [{}, None])[0]
            node.setdefault(p[-1], [{}, None])[1] = i
        self.bytes_of = [bytes([int(p[3:5], 16)]) if t == BYTE else b"" if t == CONTROL else p.replace(GAP, " ").encode() for p, _, t in pieces]
        joins = {c for p in self.ids if len(p) > 1 for c in p}
        runs = all(GAP not in p.lstrip(GAP) for p in self.ids)
        alone = "" if "\n" in joins or "\n" in self.ids else "\n"
        # No piece has a sign (what is no word character) right after a word character, but for a few (glue), so no
        # piece spans that place, and a word and the sign after it are separate parts.
        sign = re.compile(rf"[^\w{GAP}]")
        glue = re.escape("".join(sorted({x for p in self.ids for x, c in zip(p, p[1:], strict=False) if sign.match(c) and x != GAP and not sign.match(x)} | {"_"})))
        other, word = rf"(?:[^\w{GAP}{alone}]|[{glue}])", rf"[^\W{glue}]"
        own = f"{GAP}*{other}*{word}+(?:[{glue}]{other}*{word}*)*|{GAP}*{other}+|{GAP}+"
        self.parts = re.compile(own + (f"|{alone}" if alone else "")) if runs else None
        self.least = min((s for p, s, t in pieces if t == NORMAL), default=0.0) - 10
        self.words: dict[str, bytes] = {}
        self.older: dict[str, bytes] = {}
        self.after: list[dict[int, bool]] = [{} for _ in pieces]  # for each piece, whether another may follow
        self.known = 0

    def merges(self, text: str, edge: int = -1) -> list[str] | None:
        """Merging by score, leftmost first, on a short string; None as soon as a merge spans the edge.

        This defines the weights of pairs of pieces.
        """
        rank, none = self.rank, float("-inf")
        parts = list(text)
        score = [rank.get(a + b, none) for a, b in zip(parts, parts[1:], strict=False)]
        while score:
            best = max(score)
            if best == none:
                break
            i = score.index(best)
            if i == edge - 1:
                return None
            if i < edge:
                edge -= 1
            parts[i : i + 2] = [parts[i] + parts[i + 1]]
            del score[i]
            if i:
                score[i - 1] = rank.get(parts[i - 1] + parts[i], none)
            if i < len(score):
                score[i] = rank.get(parts[i] + parts[i + 1], none)
        return parts

    def follows(self, a: int, b: int) -> bool:
        """Whether the merge model leaves piece b after piece a as they are."""
        known = self.after[a].get(b)
        if known is None:
            if self.known >= PAIRS:
                self.known = 0
                for row in self.after:
                    row.clear()
            self.known += 1
            x, y = self.pieces[a][0], self.pieces[b][0]
            known = self.after[a][b] = self.merges(x + y, len(x)) == [x, y]
        return known

    def shortest(self, text: str) -> list[int]:
        """The ids along the tropical shortest path over a normalised text."""
        pieces, starts = self._merge_path(text) if self.kind == MERGE else self._cheapest_path(text)
        if not pieces or min(pieces) >= 0:
            return pieces
        out: list[int] = []
        for p, i in zip(pieces, starts, strict=True):
            if p >= 0:
                out.append(p)
            elif self.byte:
                out.extend(self.byte[b] for b in text[i].encode())
            else:
                out.append(self.unknown)
        return out

    def _merge_path(self, text: str) -> tuple[list[int], list[int]]:
        """Pieces (-2: the bytes of a character) and starts along the path of weight zero.

        Weights are zero or infinite, and at most one path into a position weighs zero. So the lattice is searched depth
        first, long pieces first, and a position that led nowhere once is never entered again.
        """
        n, trie, after = len(text), self.trie, self.after
        dead = bytearray(n + 1)
        pieces: list[int] = []
        starts: list[int] = []
        stack: list[list] = []
        i, before, arcs = 0, -1, None
        while i < n:
            if arcs is None:
                arcs, k, node = [], i, trie
                while k < n:
                    found = node.get(text[k])
                    if found is None:
                        break
                    k += 1
                    node, p = found
                    if p is not None:
                        arcs.append((k, p))
                if not arcs or arcs[0][0] > i + 1:
                    arcs.insert(0, (i + 1, -2))
            row = after[before] if before >= 0 else None
            while arcs:
                j, p = arcs.pop()
                if dead[j]:
                    continue
                if row is not None and p >= 0:
                    fits = row.get(p)
                    if fits is None:
                        fits = self.follows(before, p)
                    if not fits:
                        continue
                pieces.append(p)
                starts.append(i)
                stack.append(arcs)
                i, before, arcs = j, p, None
                break
            else:
                dead[i] = 1
                pieces.pop()
                i, arcs = starts.pop(), stack.pop()
                before = pieces[-1] if pieces else -1
        return pieces, starts

    def _cheapest_path(self, text: str) -> tuple[list[int], list[int]]:
        """The same with minus the scores as weights; a character without piece costs more than any."""
        n = len(text)
        cost = [0.0] + [float("inf")] * n
        last, back = [-1] * (n + 1), [0] * (n + 1)
        for i in range(n):
            k, node = i, self.trie
            if node.get(text[i], (None, None))[1] is None and cost[i] - self.least < cost[i + 1]:
                cost[i + 1], last[i + 1], back[i + 1] = cost[i] - self.least, -2, i
            while k < n:
                found = node.get(text[k])
                if found is None:
                    break
                k += 1
                node, p = found
                if p is not None and cost[i] - self.score[p] < cost[k]:
                    cost[k], last[k], back[k] = cost[i] - self.score[p], p, i
        pieces, starts = [], []
        j = n
        while j:
            pieces.append(last[j])
            starts.append(back[j])
            j = back[j]
        return pieces[::-1], starts[::-1]

    def encode(self, text: str) -> bytes:
        """Ids of a text as 32-bit little-endian numbers."""
        s = self.normalise(text)
        if not s:
            return b""
        parts = self.parts.findall(s) if self.parts else [s]
        out = list(map(self.words.get, parts))
        if None in out:
            for k, got in enumerate(out):
                if got is None:
                    out[k] = self._word(parts[k])
        return b"".join(out)

    def _word(self, part: str) -> bytes:
        got = self.words.get(part) or self.older.get(part)
        if got is None:
            got = array("i", self.shortest(part)).tobytes()
        if len(part) <= LONGEST:
            if len(self.words) >= WORDS:
                self.older, self.words = self.words, {}
            self.words[part] = got
        return got

    def decode(self, ids: np.ndarray) -> str:
        """The text of ids; bytes that make no character become the replacement sign."""
        raw = b"".join(map(self.bytes_of.__getitem__, ids.tolist()))
        text = raw.decode("utf-8", "replace")
        return text[1:] if self.prefix and text.startswith(" ") else text


@lru_cache(maxsize=2)
def load(path: str) -> Transducer:
    with open(path, "rb") as f:
        return Transducer(f.read())


def _round(path: str, with_text: bool):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        fst = load(path)
        for batch in batches:
            at, n = 0, batch.num_rows
            while at < n:
                ids, texts, same, digest = [], [], [], []
                load_ = 0
                start = at
                while at < n and load_ < 4 << 20:
                    text = batch.column(1)[at].as_py() or ""
                    raw = fst.encode(text)
                    one = np.frombuffer(raw, "<i4")
                    back = fst.decode(one)
                    ids.append(one)
                    texts.append(back if with_text else None)
                    same.append(back == text)
                    digest.append(hashlib.sha256(raw).hexdigest())
                    load_ += len(raw) + len(back)
                    at += 1
                lengths = np.concatenate([[0], np.cumsum([len(x) for x in ids])])
                yield pa.record_batch(
                    [batch.column(0).slice(start, at - start).cast(pa.int64()), pa.ListArray.from_arrays(pa.array(lengths, pa.int32()), pa.array(np.concatenate(ids))), pa.array(np.diff(lengths), pa.int64()), pa.array(digest), pa.array(texts, pa.string()), pa.array(same)],
                    names=["doc_id", "ids", "n_pieces", "ids_sha256", "decoded", "lossless"],
                )

    return run


def encode_decode(docs: DataFrame, model: str, *, with_text: bool = True, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """doc_id, ids, n_pieces, ids_sha256 (of little-endian 32-bit ids), decoded, lossless for each document.

    model is a .model file that every executor has. Null and empty texts have no pieces and decode to an empty text.
    Without with_text, decoded texts are compared with the input but not returned. Decoding gives the text back except for
    literal gap signs, which become spaces, and what the normaliser changes (then lossless is false). Every row gives one,
    rows that are repeated, share an id or have none too; other columns are not read, and an empty table gives an empty result.
    """
    rows = docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).cast("string").alias("text"))
    out = rows.mapInArrow(_round(model, with_text), "doc_id long, ids array<int>, n_pieces long, ids_sha256 string, decoded string, lossless boolean")
    return out if with_text else out.drop("decoded")
