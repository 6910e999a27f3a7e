"""Toxicity scores of restored text: a noisy channel undone by Viterbi decoding, then a word classifier.

1. A character language model counts the letter trigrams of every document, over the small letters of all scripts with case.
2. In a text, spans that look disguised (signs inside words, spaced-out letters, letters three times over) become
   a lattice: each character may stand for itself or for the letters it imitates, separators may vanish, a run of
   one letter may be one or two. The cheapest path under channel costs and language model is the restored word.
3. A logistic regression on words and stems of the text and its restored spans gives the score. They are those
   found in clearly more toxic than other labelled documents, counted once per group of copies: whole words, and
   beginnings that many different words share. Their number grows with the labels.
"""

from __future__ import annotations

import math
import re
import unicodedata
from collections.abc import Iterator
from dataclasses import dataclass, field
from functools import lru_cache

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, functions as F

from gridalg.llm import kernel
from gridalg.llm.lineage import cut

#: Labelled rows to fit on: more are thinned by a hash of their id. The only sample taken.
FIT_ROWS = 20_000
#: A word or stem marks toxic texts if at least GROUPS of them (copies counted once) hold it, LIFT times the share of
#: other texts, and if a test of all words at once expects no more than this share of the chosen ones to be chance.
GROUPS, LIFT, CHANCE = 3, 4.0, 0.01
#: Bytes of the beginnings of longer words that may be stems, and occurrences that are told apart.
STEMS, TIMES = (4, 5, 6, 7, 8), 3
RIDGE = 0.01
THRESHOLD = 0.7

#: Letters that a sign imitates, and cost (nats) of reading it so.
IMITATES = {"0": "o", "1": "il", "3": "e", "4": "a", "5": "s", "7": "t", "8": "b", "9": "g", "@": "a", "$": "s", "!": "i", "|": "il", "+": "t"}
READ, DROP, SHORTEN, HALVE, KEEP, ACCENT = 0.4, 0.2, 0.3, 6.0, 8.0, 0.7
SEPARATORS = " .-_*"
_BETWEEN = re.compile(f"(?<=[^{re.escape(SEPARATORS)}])[{re.escape(SEPARATORS)}]+(?=[^{re.escape(SEPARATORS)}])")


def _text(points: np.ndarray) -> str:
    return points.astype("<u4").tobytes().decode("utf-32-le")


@lru_cache(maxsize=1)
def tables() -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """For each code point: its small letter, whether that is a letter of a script with case, and whether it is a combining mark."""
    fold, letter, mark = np.arange(0x110000, dtype=np.uint32), np.zeros(0x110000, bool), np.zeros(0x110000, bool)
    for i in range(0x110000):
        c = chr(i)
        low = c.lower()
        if len(low) == 1:
            fold[i] = ord(low)
        letter[i] = low != c.upper() and c.isalpha()
        mark[i] = i > 127 and unicodedata.combining(c) > 0
    return fold, letter, mark


def folded(raw: np.ndarray, own: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """UTF-8 bytes and row offsets of small letters with composed accents, and the same as code points."""
    if not len(raw) or raw.max() < 128:
        part = kernel._LOWER[raw]
        return part, own, part, own
    fold, _, mark = tables()
    points = np.frombuffer(raw.tobytes().decode("utf-8", "replace").encode("utf-32-le"), np.uint32)
    at = np.concatenate([[0], np.cumsum((raw & 0xC0) != 0x80)])[own]  # code points that begin before each row
    if mark[points].any():
        rows = [unicodedata.normalize("NFC", _text(points[a:b])) for a, b in zip(at, at[1:], strict=False)]
        points = np.frombuffer("".join(rows).encode("utf-32-le"), np.uint32)
        at = np.concatenate([[0], np.cumsum([len(x) for x in rows])])
    points = fold[points]
    size = 1 + (points > 0x7F) + (points > 0x7FF) + (points > 0xFFFF)
    part = np.frombuffer(_text(points).encode(), np.uint8)
    return part, np.concatenate([[0], np.cumsum(size)])[at], points, at


_SIGN = np.zeros(0x110000, bool)
_SIGN[[ord(c) for c in IMITATES]] = True
_SEP = np.zeros(0x110000, bool)
_SEP[[ord(c) for c in SEPARATORS]] = True


class Trigrams:
    """log p(c | a, b) over the letters of the corpus (a to z are 1 to 26, others follow) and the gap (0); only what was seen is stored."""

    def __init__(self, count: dict[str, int]):
        self.code = {chr(96 + i): i for i in range(1, 27)} | {" ": 0}
        for c in sorted({c for t in count for c in t} - set(self.code)):
            self.code[c] = len(self.code)
        #: Letters with accents that a sign may imitate as well as the plain one.
        self.accented: dict[str, str] = {}
        for c in self.code:
            base = unicodedata.normalize("NFD", c)[0]
            if base != c:
                self.accented[base] = self.accented.get(base, "") + c
        self.known: dict[tuple[int, int, int], int] = {}
        first: dict[tuple[int, int], int] = {}
        two: dict[tuple[int, int], int] = {}
        one: dict[int, int] = {}
        for t, n in count.items():
            x, y, z = (self.code[c] for c in t)
            if x or y or z:  # runs of gaps tell nothing
                self.known[x, y, z] = n
                first[x, y] = first.get((x, y), 0) + n
                two[y, z] = two.get((y, z), 0) + n
                one[y] = one.get(y, 0) + n
        self.first, self.two, self.one = first, two, one
        self.cache: dict[tuple[int, int, int], float] = {}

    def __getitem__(self, xyz: tuple[int, int, int]) -> float:
        found = self.cache.get(xyz)
        if found is None:
            x, y, z = xyz
            low = (self.two.get((y, z), 0) + 0.1) / (self.one.get(y, 0) + 0.1 * len(self.code))
            found = self.cache[xyz] = math.log((self.known.get(xyz, 0) + 5 * low) / (self.first.get((x, y), 0) + 5))
        return found

    def __getstate__(self):
        return self.__dict__ | {"cache": {}}


@kernel.tidy
def _trigrams(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    total: dict[int, int] = {}
    _, letter, _ = tables()
    for batch in batches:
        raw, offsets = kernel.buffers(batch.column(0))
        for lo, hi in kernel.pieces(offsets):
            _, _, points, _ = folded(raw[offsets[lo] : offsets[hi]], offsets[lo : hi + 1] - offsets[lo])
            for at in range(0, max(0, len(points) - 2), kernel.PIECE):
                c = points[at : at + kernel.PIECE + 2]
                c = np.where(letter[c], c, 32).astype(np.int64)
                if c.max() < 128:  # by far the most
                    n = np.bincount((c[:-2] - 32 << 14) + (c[1:-1] - 32 << 7) + c[2:] - 32)
                    code = np.flatnonzero(n)
                    n, parts = n[code], [(code >> 14) + 32, (code >> 7 & 127) + 32, (code & 127) + 32]
                else:
                    code, n = np.unique((c[:-2] << 42) + (c[1:-1] << 21) + c[2:], return_counts=True)
                    parts = [code >> 42, code >> 21 & 0x1FFFFF, code & 0x1FFFFF]
                for key, k in zip(((parts[0] << 42) + (parts[1] << 21) + parts[2]).tolist(), n.tolist(), strict=True):
                    total[key] = total.get(key, 0) + k
    yield pa.record_batch([pa.array(list(total), pa.int64()), pa.array(list(total.values()), pa.int64())], names=["code", "n"])


def language_model(docs: DataFrame, text_col: str = "text") -> Trigrams:
    """The letter trigrams of all documents; as large as the alphabets in them make it."""
    rows = docs.select(F.col(text_col).cast("string").alias("text")).mapInArrow(_trigrams, "code long, n long").groupBy("code").agg(F.sum("n").alias("n")).collect()
    return Trigrams({"".join(chr(r["code"] >> k & 0x1FFFFF) for k in (42, 21, 0)): r["n"] for r in rows})


def restore(text: str, lm) -> str:
    """The cheapest reading of a disguised span (lower case): letters and single gaps."""
    options: list[list[tuple[str, float]]] = []
    i = 0
    between = [len(x) for x in _BETWEEN.findall(text)]
    usual = max(set(between), key=lambda k: (between.count(k), -k)) if between else 0  # separators from letter to letter
    while i < len(text):
        c = text[i]
        j = i
        while j < len(text) and text[j] in SEPARATORS:
            j += 1
        if j > i:
            options.append([("", KEEP), (" ", DROP)] if j - i > usual else [("", DROP), (" ", KEEP)])
            i = j
            continue
        while j < len(text) and text[j] == c:
            j += 1
        n = j - i
        if c.isalpha():
            options.append([(c, SHORTEN if n > 2 else HALVE), (c + c, SHORTEN * (n > 2))] if n > 1 else [(c, 0.0)])
        elif c in IMITATES:
            meant = [(y, READ) for y in IMITATES[c]] + [(z, READ + ACCENT) for y in IMITATES[c] for z in lm.accented.get(y, "")]
            options.append(meant + ([(y + y, price) for y, price in meant] if n > 1 else []) + [(" ", KEEP)])
        else:
            options.append([("", DROP), (" ", READ)])
        i = j
    code = lm.code
    # the readings so far form a tree of (what was added, the reading before), so that memory grows with the length only
    beam: dict[tuple[int, int], tuple[float, tuple | None]] = {(0, 0): (0.0, None)}
    for choice in [*options, [(" ", 0.0)]]:
        following: dict[tuple[int, int], tuple[float, tuple | None]] = {}
        for (a, b), (cost, out) in beam.items():
            for add, price in choice:
                x, y, total = a, b, cost + price
                for ch in add:
                    z = code.get(ch, -1)  # -1: a letter that no document has
                    if z == 0 and y == 0:
                        continue
                    total -= lm[x, y, z]
                    x, y = y, z
                known = following.get((x, y))
                if known is None or total < known[0]:
                    following[x, y] = (total, (add, out))
        beam = following
    parts = []
    back = min(beam.values(), key=lambda v: v[0])[1]
    while back is not None:
        add, up = back
        parts.append(add)
        back = up
    return "".join(reversed(parts)).strip()


def disguised(x: np.ndarray) -> list[tuple[int, int]]:
    """Ranges of a folded text (code points) that look disguised."""
    n = len(x)
    if n < 3:
        return []
    letter, sign = tables()[1][x], _SIGN[x]
    unit = letter | sign
    found = np.zeros(n, bool)
    mixed = letter[:-1] & sign[1:] | sign[:-1] & letter[1:]
    found[:-1] |= mixed
    triple = letter[:-2] & (x[:-2] == x[1:-1]) & (x[1:-1] == x[2:])
    found[:-2] |= triple
    out: list[tuple[int, int]] = []
    for at in np.flatnonzero(found).tolist():
        if out and at < out[-1][1]:
            continue
        lo = hi = at
        while lo > 0 and unit[lo - 1]:
            lo -= 1
        while hi < n and unit[hi]:
            hi += 1
        while hi > lo and sign[hi - 1] and chr(x[hi - 1]) in "!$+|":  # what closes a word is punctuation
            hi -= 1
        if hi - lo >= 3 and letter[lo:hi].any() and (sign[lo:hi].any() or triple[lo : hi - 2].any()):
            out.append((lo, hi))
    if n >= 5:
        edge = np.concatenate([[True], ~unit])
        one = np.zeros(n, bool)  # single characters between separators
        one[:] = unit & edge[:n] & np.concatenate([~unit[1:], [True]])
        single = np.flatnonzero(one)
        other = np.concatenate([[0], np.cumsum(~_SEP[x])])
        # from one to the next there are one to three separators, and nothing else
        near = (np.diff(single) <= 4) & (np.diff(single) >= 2) & (other[single[1:]] == other[single[:-1] + 1])
        for at in single[:-2][near[:-1] & near[1:]].tolist() if len(single) > 2 else []:
            if out and at < out[-1][1]:
                continue
            hi = at + 1
            while hi < n and (one[hi] or _SEP[x[hi]]):
                hi += 1
            while not one[hi - 1]:
                hi -= 1
            out.append((at, hi))
    return out


#: Characters of a span whose reading is remembered; longer ones are read each time.
_KEPT = 64


@dataclass
class Model:
    """What scoring needs; of fixed size."""

    lm: Trigrams
    features: np.ndarray = field(default_factory=lambda: np.zeros(0, np.uint64))  # sorted hashes of words and stems
    weights: np.ndarray = field(default_factory=lambda: np.zeros((0, TIMES)))  # of at least one, two, three occurrences
    bias: float = -30.0

    def __post_init__(self):
        self.long = lambda t: restore(t, self.lm)
        self.read = lru_cache(maxsize=20_000)(self.long)

    def __getstate__(self):
        return {k: v for k, v in self.__dict__.items() if k not in ("read", "long")}

    def __setstate__(self, state):
        self.__dict__.update(state)
        self.__post_init__()


def readings(column: pa.Array, model: Model) -> Iterator[tuple[np.ndarray, np.ndarray, list[str], list[int]]]:
    """For runs of rows: their folded bytes and offsets, the restored spans and the row of each."""
    raw, offsets = kernel.buffers(column)
    for lo, hi in kernel.pieces(offsets):
        own = offsets[lo : hi + 1] - offsets[lo]
        part, own, points, at = folded(raw[offsets[lo] : offsets[hi]], own)
        more: list[str] = []
        owner: list[int] = []
        for d in range(hi - lo):
            x = points[at[d] : at[d + 1]]
            for a, b in disguised(x):
                more.append((model.read if b - a <= _KEPT else model.long)(_text(x[a:b])))
                owner.append(d)
        yield part, own, more, owner


def _stems(part: np.ndarray, s: np.ndarray, e: np.ndarray) -> Iterator[tuple[np.ndarray, np.ndarray, np.ndarray]]:
    """For each stem length, the words that go on after it, the hashes of the stems and those of stems a byte shorter."""
    power, inverse = kernel._power(len(part) + 1)
    total = np.zeros(len(part) + 1, np.uint64)
    with np.errstate(over="ignore"):
        np.cumsum(kernel._VALUE[part] * power[: len(part)], out=total[1:])
        for n in STEMS:
            at = np.flatnonzero(e - s > n)
            first = s[at]
            stem = lambda k: kernel.mix((total[first + k] - total[first]) * inverse[first] + np.uint64(k << 32))  # noqa: E731, B023
            yield at, stem(n), stem(n - 1)


def _occurrences(part: np.ndarray, own: np.ndarray, stems: bool) -> Iterator[tuple[np.ndarray, np.ndarray]]:
    """(row, hash) of every word, and then of the stems of each length."""
    s, e, h, first = kernel.words(part, own, kernel.ALNUM)
    row = np.repeat(np.arange(len(own) - 1), np.diff(first))
    yield row, h
    if stems and len(h):
        for at, x, _ in _stems(part, s, e):
            yield row[at], x


def _shorter(column: pa.Array, model: Model, keys: np.ndarray) -> dict[int, int]:
    """The stem a byte shorter of each of the sorted keys that the texts and their restored spans hold."""
    out: dict[int, int] = {}

    def note(part: np.ndarray, own: np.ndarray) -> None:
        s, e, _, _ = kernel.words(part, own, kernel.ALNUM)
        if len(s):
            for _, x, up in _stems(part, s, e):
                at = np.flatnonzero(np.isin(x, keys))
                out.update(zip(x[at].tolist(), up[at].tolist(), strict=True))

    for part, own, more, _ in readings(column, model):
        note(part, own)
        if more:
            note(*kernel.buffers(pa.array(more, pa.string())))
    return out


def occurrences(column: pa.Array, model: Model, stems: bool = True) -> Iterator[tuple[int, int, list[tuple[np.ndarray, np.ndarray]]]]:
    """For runs of rows lo..hi: (row - lo, hash) of the words and stems of each text and of its restored spans."""
    lo = 0
    for part, own, more, owner in readings(column, model):
        found = list(_occurrences(part, own, stems))
        if more:
            whose = np.array(owner)
            found += [(whose[r], h) for r, h in _occurrences(*kernel.buffers(pa.array(more, pa.string())), stems)]
        yield lo, lo + len(own) - 1, found
        lo += len(own) - 1


def _counts(found: list[tuple[np.ndarray, np.ndarray]]) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Distinct (row, hash) and how often each occurs."""
    row, h = (np.concatenate(x) for x in zip(*found, strict=True))
    turn = np.lexsort((h, row))
    row, h = row[turn], h[turn]
    new = np.ones(len(h), bool)
    new[1:] = (h[1:] != h[:-1]) | (row[1:] != row[:-1])
    at = np.flatnonzero(new)
    return row[at], h[at], np.diff(np.append(at, len(h)))


def _among(found: list[tuple[np.ndarray, np.ndarray]], keys: np.ndarray, bits: np.ndarray) -> list[tuple[np.ndarray, np.ndarray]]:
    """Those occurrences whose hash is one of the sorted keys."""
    out = []
    for row, h in found:
        maybe = np.flatnonzero(bits[(h >> np.uint64(44)).astype(np.int64)])
        x = h[maybe]
        hit = keys[np.minimum(np.searchsorted(keys, x), len(keys) - 1)] == x if len(keys) else np.zeros(0, bool)
        out.append((row[maybe[hit]], x[hit]))
    return out


def _bits(keys: np.ndarray) -> np.ndarray:
    bits = np.zeros(1 << 20, bool)
    bits[(keys >> np.uint64(44)).astype(np.int64)] = True
    return bits


#: Of the two sums of a word set's digest.
_SALTS = np.array([0, 0xA0761D6478BD642F], np.uint64)


def _group(model):
    """text, toxic and a 128-bit digest of the word set of each text: copies share it, so that they can count once."""

    @kernel.tidy
    def run(batches):
        m = model.value
        for batch in batches:
            sums = np.zeros((2, batch.num_rows), np.uint64)
            for lo, hi, found in occurrences(batch.column(0), m, stems=False):
                row, h, _ = _counts(found)
                for side, salt in zip(sums, _SALTS, strict=True):
                    np.add.at(side[lo:hi], row, kernel.mix(h ^ salt))
            yield pa.record_batch([batch.column(0), batch.column(1), *(pa.array(x.view(np.int64)) for x in sums)], names=["text", "toxic", "grp", "grp2"])

    return run


def _tally(model, keys):
    """hash and number of texts that hold it: of all words and stems, or of the keys only."""

    @kernel.tidy
    def run(batches):
        m, want = model.value, keys.value if keys else None
        bits = None if want is None else _bits(want)
        total: dict[int, int] = {}
        for batch in batches:
            for _, _, found in occurrences(batch.column(0), m):
                _, h, _ = _counts(found if want is None else _among(found, want, bits))
                u, n = np.unique(h, return_counts=True)
                for a, b in zip(u.view(np.int64).tolist(), n.tolist(), strict=True):
                    total[a] = total.get(a, 0) + b
        yield pa.record_batch([pa.array(list(total), pa.int64()), pa.array(list(total.values()), pa.int64())], names=["h", "n"])

    return run


def _patterns(model):
    """toxic and the active features of each text: number * TIMES + occurrences - 1."""

    @kernel.tidy
    def run(batches):
        m = model.value
        bits = _bits(m.features)
        for batch in batches:
            out: list[list[int]] = []
            for lo, hi, found in occurrences(batch.column(0), m):
                row, h, n = _counts(_among(found, m.features, bits))
                own: list[list[int]] = [[] for _ in range(hi - lo)]
                for r, k, c in zip(row.tolist(), np.searchsorted(m.features, h).tolist(), n.tolist(), strict=True):
                    own[r] += [k * TIMES + t for t in range(min(c, TIMES))]
                out += [sorted(x) for x in own]
            yield pa.record_batch([batch.column(1), pa.array(out, pa.list_(pa.int64()))], names=["toxic", "f"])

    return run


def in_fold(id_col: str = "doc_id"):
    """True where a row may be learned from."""
    return F.pmod(F.crc32(F.col(id_col).cast("string").cast("binary")), F.lit(3)) != 1


def _chance(a: np.ndarray, b: np.ndarray, share: float) -> np.ndarray:
    """log of an upper bound (Chernoff's) of the probability that a or more of a + b texts are toxic by chance, for a > 0."""
    n = a + b
    q = a / n
    other = np.where(b > 0, b * np.log(np.maximum(1 - q, 1e-300) / max(1 - share, 1e-300)), 0.0)
    return np.where(q > share, -(a * np.log(q / share) + other), 0.0)


def _longest(ids: list[int], a: dict[int, int], b: dict[int, int], shorter: dict[int, int]) -> list[int]:
    """Of stems that begin one another, the longest that explains all toxic texts of the shorter, and none that is only a part of a shorter one."""
    kept = set(ids)
    below: dict[int, list[int]] = {}
    for x in ids:
        if shorter.get(x) in kept:
            below.setdefault(shorter[x], []).append(x)
    # a longer stem with the same toxic texts says it as well
    kept -= {x for x, more in below.items() if any(a[y] == a[x] for y in more)}
    out = []
    for x in kept:
        up, part = shorter.get(x), False
        while up in a and not part:
            part = up in kept and (a[up] + 0.5) / (b.get(up, 0) + 0.5) >= (a[x] + 0.5) / (b.get(x, 0) + 0.5)
            up = shorter.get(up)
        if not part:
            out.append(x)
    return out


def _telling(seen: DataFrame, model, n0: int, n1: int) -> np.ndarray:
    """Sorted hashes of all words and stems that toxic texts hold more often than chance allows."""
    spark = seen.sparkSession
    share = n1 / (n0 + n1)
    pos = cut(seen.filter("toxic = 1").mapInArrow(_tally(model, None), "h long, n long").groupBy("h").agg(F.sum("n").alias("n1")))
    tests = pos.count()
    top = {r["h"]: r["n1"] for r in pos.filter(F.col("n1") >= GROUPS).collect()}
    if not top:
        return np.zeros(0, np.uint64)
    keys = np.sort(np.array(list(top), np.int64).view(np.uint64))
    neg = seen.filter("toxic = 0").mapInArrow(_tally(model, spark.sparkContext.broadcast(keys)), "h long, n long").groupBy("h").agg(F.sum("n").alias("n0")).collect()
    g0 = {r["h"]: r["n0"] for r in neg}
    ids = np.array(list(top), np.int64)
    a, b = np.array([top[x] for x in ids.tolist()], float), np.array([g0.get(x, 0) for x in ids.tolist()], float)
    lift = (a / n1) / ((b + 0.5) / (n0 + 1))
    p = _chance(a, b, share)
    # false discovery rate: the k-th smallest probability is held against k times that of a single test
    rank = np.sort(p) <= np.log(CHANCE / tests) + np.log(np.arange(1, len(p) + 1))
    limit = np.sort(p)[np.flatnonzero(rank)[-1]] if rank.any() else -np.inf
    best = np.sort(ids[(p <= limit) & (lift > LIFT)].view(np.uint64))
    if len(best):
        held = spark.sparkContext.broadcast(best)

        def chains(batches):
            for batch in batches:
                up = _shorter(batch.column(0), model.value, held.value)
                yield pa.record_batch([pa.array(np.array(list(x), np.uint64).view(np.int64)) for x in (up.keys(), up.values())], names=["h", "up"])

        shorter = {r["h"]: r["up"] for r in seen.filter("toxic = 1").mapInArrow(chains, "h long, up long").distinct().collect()}
        best = np.sort(np.array(_longest(best.view(np.int64).tolist(), top, g0, shorter), np.int64).view(np.uint64))
    return best


def fit(docs: DataFrame, labels: DataFrame) -> Model:
    """The language model from all documents, the classifier from labelled rows of the learning folds."""
    spark = docs.sparkSession
    model = Model(language_model(docs))
    rows = labels.filter(F.col("toxic").isin(0, 1) & F.col("doc_id").isNotNull() & in_fold()).groupBy("doc_id").agg(F.max("toxic").cast("int").alias("toxic"))
    n = rows.count()
    if n > FIT_ROWS:
        rows = rows.filter(F.pmod(F.xxhash64("doc_id"), F.lit(1 << 20)) < int(FIT_ROWS / n * (1 << 20)))
    texts = docs.select("doc_id", "text").join(F.broadcast(rows), "doc_id").select(F.col("text").cast("string").alias("text"), "toxic")
    held = spark.sparkContext.broadcast(model)
    seen = cut(texts.mapInArrow(_group(held), "text string, toxic int, grp long, grp2 long").dropDuplicates(["toxic", "grp", "grp2"]).select("text", "toxic"))
    total = dict(seen.groupBy("toxic").count().collect())
    n0, n1 = total.get(0, 0), total.get(1, 0)
    if not n1:
        return model
    model.features = _telling(seen, held, n0, n1)
    m = len(model.features) * TIMES
    got = seen.mapInArrow(_patterns(spark.sparkContext.broadcast(model)), "toxic int, f array<long>").groupBy("f", "toxic").agg(F.count("*").alias("n")).collect()
    x = np.zeros((len(got), m + 1))
    x[:, -1] = 1
    for i, r in enumerate(got):
        x[i, r["f"]] = 1
    y, k = np.array([r["toxic"] for r in got], float), np.array([r["n"] for r in got], float)
    used = np.flatnonzero(x.any(0))
    x = x[:, used]
    w = np.zeros(len(used))
    ridge = np.append(np.full(len(used) - 1, RIDGE), 1e-3)
    for _ in range(40):
        q = 1 / (1 + np.exp(-np.clip(x @ w, -30, 30)))
        step = np.linalg.solve((x * (k * q * (1 - q))[:, None]).T @ x + np.diag(ridge), x.T @ (k * (y - q)) - ridge * w)
        w += np.clip(step, -2, 2)
        if np.abs(step).max() < 1e-6:
            break
    full = np.zeros(m + 1)
    full[used] = w
    model.weights, model.bias = full[:-1].reshape(-1, TIMES), float(full[-1])
    return model


def _scores(m: Model, bits: np.ndarray, sums: np.ndarray, column: pa.Array) -> np.ndarray:
    z = np.full(len(column), m.bias)
    if len(m.features):
        for lo, _, found in occurrences(column, m):
            row, h, n = _counts(_among(found, m.features, bits))
            np.add.at(z, lo + row, sums[np.searchsorted(m.features, h), np.minimum(n, TIMES) - 1])
    return 1 / (1 + np.exp(-np.clip(z, -30, 30)))


def _score(model):
    @kernel.tidy
    def run(batches):
        m = model.value
        bits, sums = _bits(m.features), np.cumsum(m.weights, axis=1)
        for batch in batches:
            yield pa.record_batch([batch.column(0).cast(pa.int64()), pa.array(_scores(m, bits, sums, batch.column(1)))], names=["doc_id", "score"])

    return run


def _keep(model, text_at: int):
    @kernel.tidy
    def run(batches):
        m = model.value
        bits, sums = _bits(m.features), np.cumsum(m.weights, axis=1)
        for batch in batches:
            yield from kernel.kept(batch, _scores(m, bits, sums, batch.column(text_at)) < THRESHOLD)

    return run


def score(docs: DataFrame, labels: DataFrame) -> DataFrame:
    """doc_id, held_out, score, predicted for each document.

    Learns from labelled rows of the folds 0 and 2 of crc32(doc_id as text) mod 3, at most FIT_ROWS of them. Null and
    empty texts get the score of a text without telling words. Without toxic labels all scores are near zero. Other
    columns of both tables, lang and source among them, are not read. Each row is scored by its own text, rows that are
    repeated, share an id or have none too; a row without id is not held out, as it has no fold, and no label meets it.
    """
    model = docs.sparkSession.sparkContext.broadcast(fit(docs, labels))
    rows = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("text").cast("string").alias("text"))
    out = rows.mapInArrow(_score(model), "doc_id long, score double")
    return out.select("doc_id", F.coalesce(~in_fold(), F.lit(False)).alias("held_out"), "score", (F.col("score") >= THRESHOLD).cast("int").alias("predicted"))


def drop_toxic(docs: DataFrame, labels: DataFrame) -> DataFrame:
    """The documents that are not predicted toxic, with their columns, in one pass without exchange.

    Each row is judged by its own text, whatever its id and however often it is repeated; null and empty texts stay.
    """
    model = docs.sparkSession.sparkContext.broadcast(fit(docs, labels))
    return docs.mapInArrow(_keep(model, docs.columns.index("text")), docs.schema)
