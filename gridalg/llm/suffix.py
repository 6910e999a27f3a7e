"""Burrows-Wheeler transforms of text shards, and their merge by refinement of an interleave.

A shard is taken as a circle: its text and a run of zero bytes. Its transform lists, in the order of its rotations, the
symbol before each rotation. Symbols are STEP bytes wide instead of one, so that a depth of 100 takes four rounds
in place of a hundred; each is held as its number in the shard's sorted list of symbols.

Two transforms are merged from these lists alone, without comparing or sorting rotations again. An interleave says for
each place of the common order which shard it is filled from. At first all of one shard come before the other; a round
reads the symbols along the interleave and deals them out stably by symbol, which orders the places by STEP bytes
more. Places that fall apart in a round end a common prefix there, so the rounds also give the common prefix of neighbours
in steps, and the intervals with DEPTH bytes in common.
"""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np

DEPTH = 100
STEP = 25
#: Prefix lengths in the sort of a single shard; each is at most twice the one before.
LENGTHS = (8, 16, STEP, 2 * STEP, DEPTH)
WORD = f"S{STEP}"


def _pad(text: np.ndarray) -> np.ndarray:
    return np.concatenate([text, np.zeros(DEPTH, np.uint8)])


@dataclass
class Transform:
    """symbol[j] is the number in words of the STEP bytes before the rotation that starts at order[j]."""

    order: np.ndarray
    symbol: np.ndarray
    words: np.ndarray
    size: int
    steps: np.ndarray  # common prefix with the place before, in whole steps, up to DEPTH

    def intervals(self) -> np.ndarray:
        """Number of the interval of each place; the places of one have DEPTH bytes in common."""
        return np.cumsum(self.steps < DEPTH // STEP)

    def bwt(self) -> np.ndarray:
        """The byte before each rotation in order: the usual transform."""
        return self.words.view(np.uint8).reshape(-1, STEP)[self.symbol, -1] if len(self.words) else np.zeros(0, np.uint8)


def _apart(key: np.ndarray) -> np.ndarray:
    new = np.zeros(len(key), bool)
    new[1:] = key[1:] != key[:-1]
    return new


def shard(text: np.ndarray) -> Transform:
    """The transform of one shard, whose rotations are sorted by doubled prefixes."""
    x = _pad(text)
    n = len(x)
    at = np.arange(n)
    far = np.concatenate([x, x[:8]])
    key = np.zeros(n, np.uint64)
    for k in range(8):
        key |= far[k : k + n].astype(np.uint64) << np.uint64(56 - 8 * k)
    rank, before = at, 0
    known: dict[int, np.ndarray] = {}
    order = at
    for length in LENGTHS:
        if before:
            key = rank * n + np.roll(rank, before - length)
        order = np.argsort(key)
        rank = np.empty(n, np.int64)
        rank[order] = np.cumsum(_apart(key[order]))
        known[length] = rank
        before = length
    one, two = known[STEP], known[2 * STEP]
    first = np.empty(int(one.max(initial=-1)) + 1, np.int64)
    first[one] = at
    words = np.concatenate([x, x[:STEP]])[first[:, None] + np.arange(STEP)].view(WORD).ravel()
    steps = np.zeros(n, np.int8)
    for rank_of in (one, two, two + n * np.roll(two, -STEP), rank):
        steps += ~_apart(rank_of[order])
    steps[:1] = 0
    return Transform(order, one[order - STEP].astype(np.int32), words, n, steps)


def _deal(symbol: np.ndarray, kinds: int) -> np.ndarray:
    """Places in the order of their symbols, stably: counting by the low and then the high half of the number."""
    turn = np.argsort(symbol.astype(np.uint16), kind="stable")
    return turn if kinds <= 1 << 16 else turn[np.argsort((symbol >> 16).astype(np.uint16)[turn], kind="stable")]


def merge(a: Transform, b: Transform) -> Transform:
    """The transform of both shards; the places of b come after those of a's text."""
    both = np.concatenate([a.words, b.words])
    turn = np.argsort(both, kind="stable")  # two sorted lists
    new = _apart(both[turn])
    number = np.empty(len(both), np.int32)
    number[turn] = np.cumsum(new, dtype=np.int32)
    new[:1] = True
    words = both[turn[new]]
    one, two = number[: len(a.words)][a.symbol], number[len(a.words) :][b.symbol]
    n = len(one) + len(two)
    second = np.arange(n) >= len(one)
    group, steps = np.zeros(n, np.int32), np.zeros(n, np.int8)

    def along(first_values: np.ndarray, second_values: np.ndarray) -> np.ndarray:
        out = np.empty(n, first_values.dtype)
        out[~second], out[second] = first_values, second_values
        return out

    for _ in range(DEPTH // STEP):
        symbol = along(one, two)
        turn = _deal(symbol, len(words))
        new = _apart(symbol[turn]) | _apart(group[turn])
        second, group = second[turn], np.cumsum(new, dtype=np.int32)
        steps += ~new
    steps[:1] = 0
    return Transform(along(a.order, b.order + a.size), along(one, two), words, a.size + b.size, steps)


def classes(texts: list[np.ndarray], shard_bytes: int = 1 << 19) -> tuple[np.ndarray, np.ndarray]:
    """Class of each position of each text, and where each text starts among them; equal classes mean equal DEPTH bytes.

    Only positions with DEPTH bytes left in their own text mean anything. Shards of whole texts are merged in pairs
    until one is left.
    """
    sizes = np.array([len(t) for t in texts], np.int64)
    groups: list[list[int]] = [[]]
    load = 0
    for i, n in enumerate(sizes.tolist()):
        if load + n > shard_bytes and groups[-1]:
            groups.append([])
            load = 0
        groups[-1].append(i)
        load += n
    at = np.zeros(len(texts), np.int64)
    parts: list[Transform] = []
    begin = 0
    for g in groups:
        t = shard(np.concatenate([texts[i] for i in g]) if g else np.zeros(0, np.uint8))
        at[g] = begin + np.concatenate([[0], np.cumsum(sizes[g])])[:-1]
        begin += t.size
        parts.append(t)
    while len(parts) > 1:
        parts = [merge(*parts[k : k + 2]) if k + 1 < len(parts) else parts[k] for k in range(0, len(parts), 2)]
    rank = np.empty(begin, np.int64)
    rank[parts[0].order] = parts[0].intervals()
    return rank, at
