"""Nearest neighbours by vantage-point trees, one per shard, with relaxed triangle-inequality pruning.

1. A small vantage-point tree over a bounded sample, the router, deals every vector to a region: a ball around each of its
   vantage points, or what lies outside. Exact bounds of each region's distances to those points come from all its vectors.
   A region beyond the size of a shard is split into shards by a hash of the vectors.
2. Each query searches the shards of its own region first. Its k-th distance there then tells which other regions can hold
   anything nearer, by the triangle inequality, and only their shards are searched.
3. A task streams the vectors of a shard, builds its tree once, and streams the queries through it. Bounds of nodes are
   carried down the tree.

A region or node is skipped where its lower bound times the factor exceeds the current k-th distance: factor one is
exact search, larger factors skip more. Of equal vectors only the k + 1 smallest ids can be among the nearest, so copies
are folded in the tasks that read them and again in their shard.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute
from pyspark.sql import DataFrame, functions as F

from gridalg.llm.lineage import cut

LEAF = 32
#: Slack of bounds and of the quick distances against rounding, relative to the squared lengths at hand.
SLACK = 1e-9
#: Vectors of a shard: what one task holds at once.
SHARD = 20_000
#: Vectors (thinned by a hash of their id) that the router is built on, and regions that it has at most.
SAMPLE, REGIONS = 16_384, 1024


class Tree:
    """A vantage-point tree over rows of a matrix; nodes are (rows, point, inner, outer, near, far, left, right)."""

    def __init__(self, x: np.ndarray, leaf: int = LEAF, seed: int = 11):
        self.x = x
        self.square = np.einsum("ij,ij->i", x, x)
        self.rng = np.random.default_rng(seed)
        self.nodes: list[list] = []
        self.seen = self.pairs = 0  # pairs whose distance was looked at, and all pairs
        self.root = self._build(np.arange(len(x)), leaf) if len(x) else -1

    def _build(self, rows: np.ndarray, leaf: int) -> int:
        todo = [(rows, -1, 0)]
        while todo:  # no recursion: depth may reach the number of rows if distances are tied
            rows, parent, side = todo.pop()
            me = len(self.nodes)
            if parent >= 0:
                self.nodes[parent][side] = me
            node = [rows, None, 0.0, 0.0, 0.0, 0.0, -1, -1]
            self.nodes.append(node)
            if len(rows) <= leaf:
                continue
            v = int(rows[self.rng.integers(len(rows))])
            d = np.sqrt(np.einsum("ij,ij->i", self.x[rows] - self.x[v], self.x[rows] - self.x[v]))
            mu = float(np.median(d))
            near = d <= mu
            if near.all():  # ties: every row at most mu away, so split off those at exactly mu if some are nearer
                near = d < mu
                if not near.any():
                    continue
            node[:6] = [None, v, float(d[near].max()), float(d[~near].min()), float(d.min()), float(d.max())]
            todo += [(rows[near], me, 6), (rows[~near], me, 7)]
        return 0

    def search(self, q: np.ndarray, k: int, factor: float, ids: np.ndarray, limit: np.ndarray | None = None) -> tuple[np.ndarray, np.ndarray]:
        """ids and distances of up to k+1 nearest of each query, by distance then id (one more, as the query may be among them).

        limit holds a distance for each query beyond which nothing is wanted.
        """
        m, k = len(q), k + 1
        best = np.full((m, k), np.inf)
        name = np.full((m, k), np.iinfo(np.int64).max)
        if self.root < 0 or not m:
            return name, best
        self.pairs += m * len(self.x)
        bar = np.full(m, np.inf) if limit is None else limit.astype(float)
        own = np.einsum("ij,ij->i", q, q)
        home = self._homes(q)
        for at in np.unique(home).tolist():
            self._leaf(at, np.flatnonzero(home == at), q, own, bar, k, ids, best, name)
        # all queries go through the tree together, with the limits that their own leaves gave them
        todo: list[tuple[int, np.ndarray, np.ndarray]] = [(self.root, np.arange(m), np.zeros(m))]
        while todo:
            at, who, bound = todo.pop()
            fits = bound * factor <= np.minimum(best[who, -1], bar[who]) * (1 + SLACK) + SLACK
            who, bound = who[fits], bound[fits]
            if not len(who):
                continue
            some, v, inner, outer, near, far, left, right = self.nodes[at]
            if some is None:
                d = np.sqrt(np.einsum("ij,ij->i", q[who] - self.x[v], q[who] - self.x[v]))
                todo.append((right, who, np.maximum(bound, np.maximum(outer - d, d - far))))
                todo.append((left, who, np.maximum(bound, np.maximum(d - inner, near - d))))
                continue
            who = who[home[who] != at]
            if len(who):
                self._leaf(at, who, q, own, bar, k, ids, best, name)
        return name, best

    def _homes(self, q: np.ndarray) -> np.ndarray:
        """The leaf on whose side of every vantage point a query lies."""
        out = np.zeros(len(q), np.int64)
        todo = [(self.root, np.arange(len(q)))]
        while todo:
            at, who = todo.pop()
            some, v, inner, outer, _, _, left, right = self.nodes[at]
            if some is not None:
                out[who] = at
            elif len(who):
                d = np.sqrt(np.einsum("ij,ij->i", q[who] - self.x[v], q[who] - self.x[v]))
                first = d <= (inner + outer) / 2
                todo += [(left, who[first]), (right, who[~first])]
        return out

    def _leaf(self, at: int, who: np.ndarray, q, own, bar, k: int, ids, best, name) -> None:
        """The rows of a leaf taken into the best of some queries."""
        some = self.nodes[at][0]
        self.seen += len(who) * len(some)
        for part in range(0, len(some), 4096):
            rows = some[part : part + 4096]
            quick = own[who, None] + self.square[rows] - 2 * (q[who] @ self.x[rows].T)
            least = np.minimum(best[who, -1], bar[who]) ** 2
            if len(rows) > k:
                least = np.minimum(least, np.partition(quick, k - 1, axis=1)[:, k - 1])
            i, j = np.nonzero(quick <= (least + SLACK * (own[who] + self.square[rows].max()))[:, None])
            if not len(i):
                continue
            exact = distances(q[who[i]], self.x[rows[j]])
            hit = np.unique(i)
            place = np.concatenate([np.repeat(hit, k), i])
            score = np.concatenate([best[who[hit]].ravel(), exact])
            names = np.concatenate([name[who[hit]].ravel(), ids[rows[j]]])
            turn = np.lexsort((names, score, place))
            first = np.searchsorted(place[turn], hit)
            keep = turn[(first[:, None] + np.arange(k)).ravel()]
            best[who[hit]], name[who[hit]] = score[keep].reshape(-1, k), names[keep].reshape(-1, k)


def distances(a: np.ndarray, b: np.ndarray) -> np.ndarray:
    """Euclidean distances of rows to rows in double precision, squares summed in the order of the components."""
    out = np.zeros(len(a))
    d = (a - b) ** 2
    for k in range(d.shape[1]):
        out += d[:, k]
    return np.sqrt(out)


class Router:
    """Regions of a tree over a sample: for each, the vantage points above it (path) and which side of them it is."""

    def __init__(self, sample: np.ndarray, regions: int):
        tree = Tree(sample, leaf=max(1, -(-len(sample) // max(1, regions)))) if len(sample) and regions > 1 else None
        self.size = sample.shape[1] if len(sample) else 0
        self.nodes: list[tuple[np.ndarray, float, int, int]] = []  # point, where it parts, children (regions from ~0 down)
        self.paths: list[list[int]] = []
        if tree is None:
            self.paths.append([])
            return
        todo: list[tuple[int, list[int], int, int]] = [(tree.root, [], -1, 0)]
        while todo:
            at, path, parent, side = todo.pop()
            some, v, inner, outer, _, _, left, right = tree.nodes[at]
            if some is None:
                me = len(self.nodes)
                self.nodes.append([sample[v], (inner + outer) / 2, 0, 0])
                todo += [(left, [*path, me], me, 2), (right, [*path, me], me, 3)]
            else:
                me = ~len(self.paths)
                self.paths.append(path)
            if parent >= 0:
                self.nodes[parent][side] = me

    def regions(self, x: np.ndarray) -> np.ndarray:
        """The region of each vector."""
        out = np.zeros(len(x), np.int64)
        todo = [(0 if self.nodes else ~0, np.arange(len(x)))]
        while todo:
            at, rows = todo.pop()
            if at < 0:
                out[rows] = ~at
            elif len(rows):
                point, part, left, right = self.nodes[at]
                near = np.sqrt(np.einsum("ij,ij->i", x[rows] - point, x[rows] - point)) <= part
                todo += [(left, rows[near]), (right, rows[~near])]
        return out

    def far(self, x: np.ndarray) -> np.ndarray:
        """Distances to all vantage points."""
        if not self.nodes:
            return np.zeros((len(x), 0))
        p = np.stack([n[0] for n in self.nodes])
        return np.sqrt(np.stack([np.einsum("ij,ij->i", x - q, x - q) for q in p], axis=1))

    def bounds(self, x: np.ndarray, least: np.ndarray, most: np.ndarray) -> np.ndarray:
        """Lower bounds of the distances of vectors to regions, whose members are least to most away from each point."""
        d = self.far(x)
        out = np.zeros((len(x), len(self.paths)))
        for r, path in enumerate(self.paths):
            for n in path:
                np.maximum(out[:, r], np.maximum(least[r, n] - d[:, n], d[:, n] - most[r, n]), out=out[:, r])
        return out


def _matrix(column: pa.Array, size: int) -> np.ndarray:
    """The vectors of a list column, all of one length."""
    flat = column.flatten()
    return np.asarray(flat, np.float64).reshape(len(column), size) if size else np.zeros((len(column), 0))


def _by_size(batch: pa.RecordBatch, column: int) -> Iterator[tuple[int, pa.RecordBatch]]:
    sizes = np.asarray(pyarrow.compute.list_value_length(batch.column(column)))
    for size in np.unique(sizes).tolist():
        yield size, batch.filter(pa.array(sizes == size))


def _hashes(x: np.ndarray) -> np.ndarray:
    """A number that equal vectors share; minus zero counts as zero."""
    x = np.ascontiguousarray(x + 0.0)
    return np.array([int.from_bytes(hashlib.blake2b(r.tobytes(), digest_size=8).digest(), "little", signed=True) for r in x], np.int64)


def _first_copies(ids: np.ndarray, h: np.ndarray, x: np.ndarray, k: int) -> np.ndarray:
    """Rows that are among the k + 1 smallest ids of their vector, each id once; rows of one hash are compared whole."""
    turn = np.lexsort((ids, h))
    keep = np.ones(len(ids), bool)
    twice = np.zeros(len(ids), bool)
    twice[1:] = (h[turn][1:] == h[turn][:-1]) & (ids[turn][1:] == ids[turn][:-1])
    keep[turn[twice]] = False
    turn = turn[~twice]
    edges = np.append(np.flatnonzero(h[turn][1:] != h[turn][:-1]) + 1, len(turn))
    for start, stop in zip([0, *edges.tolist()], edges.tolist(), strict=False):
        if stop - start > k + 1:
            rows = turn[start:stop]
            alike = (x[rows] == x[rows[0]]).all(axis=1)
            keep[rows[alike][k + 1 :]] = False
    return keep


def _deal(router, k: int, shards):
    """vec_id, hash, vector and shard of each vector, copies beyond k + 1 in a batch left out; without shards the region's bounds."""

    def bounds(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        r = router.value
        for batch in batches:
            for size, own in _by_size(batch, 1):
                if size != r.size:
                    yield pa.record_batch([pa.array([-size]), pa.array([0]), pa.array([0.0]), pa.array([0.0]), pa.array([own.num_rows])], names=["region", "point", "least", "most", "n"])
                    continue
                x = _matrix(own.column(1), size)
                region, d = r.regions(x), r.far(x)
                rows = []
                for g in np.unique(region).tolist():
                    mine = d[region == g]
                    rows += [(g, n, mine[:, n].min(), mine[:, n].max(), len(mine)) for n in r.paths[g]] or [(g, 0, 0.0, 0.0, len(mine))]
                yield pa.record_batch([pa.array(c) for c in zip(*rows, strict=True)], names=["region", "point", "least", "most", "n"])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        r, split = router.value, shards.value
        for batch in batches:
            for size, own in _by_size(batch, 1):
                x, ids = _matrix(own.column(1), size), np.asarray(own.column(0))
                h = _hashes(x)
                keep = _first_copies(ids, h, x, k)
                x, ids, h = x[keep], ids[keep], h[keep]
                region = r.regions(x) if size == r.size else np.full(len(x), -size)
                first = np.array([split[g][0] for g in region.tolist()], np.int64)
                many = np.array([split[g][1] for g in region.tolist()], np.int64)
                yield pa.record_batch([pa.array(ids), pa.array(h), own.column(1).filter(pa.array(keep)), pa.array(first + h % many)], names=["vec_id", "h", "v", "shard"])

    return run if shards else bounds


def _route(router, shards, bounds, factor: float):
    """One row for each shard that a query asks: those of its own region without a limit, or those of others within it."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        r, split = router.value, shards.value
        for batch in batches:
            for size, own in _by_size(batch, 1):
                x, limit = _matrix(own.column(1), size), np.asarray(own.column(2), np.float64)
                home = r.regions(x) if size == r.size else np.full(len(x), -size)
                if bounds is None:
                    asks = [(i, g) for i, g in enumerate(home.tolist())]
                elif size == r.size:
                    low = r.bounds(x, *bounds.value)
                    i, g = np.nonzero(low * factor <= limit[:, None] * (1 + SLACK) + SLACK)
                    asks = [(a, b) for a, b in zip(i.tolist(), g.tolist(), strict=True) if b != home[a] and b in split]
                else:
                    asks = []
                pairs = [(i, s) for i, g in asks for s in range(split[g][0], split[g][0] + split[g][1])]
                if pairs:
                    i, s = zip(*pairs, strict=True)
                    take = pa.array(i, pa.int64())
                    yield pa.record_batch([own.column(0).take(take), own.column(1).take(take), own.column(2).take(take), pa.array(s, pa.int64())], names=["vec_id", "v", "score", "shard"])

    return run


_FOUND = "query_id long, vec_id long, score double"


def _search(k: int, factor: float):
    """Streams shard after shard: its vectors (kind 0, by hash and id), then its queries (kind 1)."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        now, rows, trees = None, [], {}

        def built() -> dict[int, tuple[Tree, np.ndarray]]:
            out = {}
            for size in {s for s, *_ in rows}:
                ids, h, x = (np.concatenate(c) for c in zip(*(r[1:] for r in rows if r[0] == size), strict=True))
                keep = _first_copies(ids, h, x, k)
                out[size] = Tree(x[keep]), ids[keep]
            return out

        for batch in batches:
            shard = np.asarray(batch.column(0))
            edges = np.flatnonzero(np.diff(shard)) + 1
            for lo, hi in zip([0, *edges], [*edges, len(shard)], strict=True):
                if hi == lo:
                    continue
                part = batch.slice(lo, hi - lo)
                if shard[lo] != now:
                    now, rows, trees = shard[lo], [], None
                kind = np.asarray(part.column(1))
                for size, base in _by_size(part.filter(pa.array(kind == 0)), 4):
                    rows.append((size, np.asarray(base.column(2)), np.asarray(base.column(3)), _matrix(base.column(4), size)))
                for size, asked in _by_size(part.filter(pa.array(kind == 1)), 4):
                    if trees is None:
                        trees, rows = built(), []
                    if size not in trees:
                        continue
                    tree, ids = trees[size]
                    name, best = tree.search(_matrix(asked.column(4), size), k, factor, ids, np.asarray(asked.column(5), np.float64))
                    who = np.repeat(np.asarray(asked.column(2)), name.shape[1])
                    keep = np.isfinite(best.ravel()) & (name.ravel() != who)
                    yield pa.record_batch([pa.array(who[keep]), pa.array(name.ravel()[keep]), pa.array(best.ravel()[keep])], names=["query_id", "vec_id", "score"])

    return run


def nearest(vectors: DataFrame, *, every: int = 100, k: int = 10, factor: float = 1.0, shard: int = SHARD, id_col: str = "vec_id", vec_col: str = "embedding") -> DataFrame:
    """query_id, rank, vec_id, score: the k nearest other vectors of each whose id is divisible by `every`.

    Score is the Euclidean distance in double precision; ties go to the smaller id; fewer than k candidates are all
    returned. Vectors that are null, empty, zero, or hold null, NaN or infinite components take no part; nor do rows
    without id. factor 1 is exact, larger factors trade recall for time. Equal vectors of different ids stay apart; a row
    that is given twice counts once, but one id must not stand for different vectors. Other columns are not read; an empty
    table gives an empty result.
    """
    if factor < 1:
        raise ValueError("factor is at least 1")
    sc = vectors.sparkSession.sparkContext
    v = F.col(vec_col).cast("array<double>")
    # x - x is NaN for NaN and infinities, so these never equal zero
    clean = v.isNotNull() & F.coalesce(F.forall(v, lambda x: x.isNotNull() & (x - x == 0)), F.lit(False)) & F.exists(v, lambda x: x != 0)
    rows = vectors.filter(F.col(id_col).isNotNull()).filter(clean).select(F.col(id_col).cast("long").alias("vec_id"), v.alias("v"))
    n = vectors.count()
    thin = rows if n <= SAMPLE else rows.filter(F.pmod(F.xxhash64("vec_id"), F.lit(1 << 20)) < int(SAMPLE / n * (1 << 20)))
    sample = [r["v"] for r in thin.select("v").collect()]
    sizes = [len(x) for x in sample]
    usual = max(set(sizes), key=lambda s: (sizes.count(s), s)) if sizes else 1
    router = Router(np.array([x for x in sample if len(x) == usual], np.float64).reshape(-1, usual), min(REGIONS, -(-n // shard)))
    held = sc.broadcast(router)

    told = rows.mapInArrow(_deal(held, k, None), "region long, point long, least double, most double, n long").groupBy("region", "point").agg(F.min("least").alias("least"), F.max("most").alias("most"), F.sum("n").alias("n")).collect()
    least, most = np.full((len(router.paths), max(1, len(router.nodes))), np.inf), np.zeros((len(router.paths), max(1, len(router.nodes))))
    count: dict[int, int] = {}
    for r in told:
        count[r["region"]] = r["n"]
        if r["region"] >= 0:
            least[r["region"], r["point"]], most[r["region"], r["point"]] = r["least"], r["most"]
    split, at = {}, 0
    for g, m in sorted(count.items()):
        split[g] = at, -(-m // shard)
        at += split[g][1]
    shards = sc.broadcast(split)

    dealt = rows.mapInArrow(_deal(held, k, shards), "vec_id long, h long, v array<double>, shard long").select("shard", F.lit(0).alias("kind"), "vec_id", "h", "v", F.lit(0.0).alias("score"))
    asked = rows.filter(F.col("vec_id") % every == 0).dropDuplicates(["vec_id"]).select("vec_id", "v", F.lit(float("inf")).alias("score"))

    def visit(queries: DataFrame) -> DataFrame:
        both = dealt.unionByName(queries.select("shard", F.lit(1).alias("kind"), "vec_id", F.lit(0).cast("long").alias("h"), "v", "score"))
        found = both.repartition(max(1, at), "shard").sortWithinPartitions("shard", "kind", "h", "vec_id").mapInArrow(_search(k, factor), _FOUND)
        return found.groupBy("query_id").agg(F.slice(F.array_sort(F.collect_set(F.struct("score", "vec_id"))), 1, k).alias("x"))

    ask = "vec_id long, v array<double>, score double, shard long"
    found = visit(asked.mapInArrow(_route(held, shards, None, factor), ask))
    if len([g for g in split if g >= 0]) > 1:
        found = cut(found)
        limit = found.filter(F.size("x") == k).select(F.col("query_id").alias("vec_id"), F.element_at("x", -1)["score"].alias("limit"))
        more = asked.drop("score").join(limit, "vec_id", "left").select("vec_id", "v", F.coalesce("limit", F.lit(float("inf"))).alias("score"))
        other = visit(more.mapInArrow(_route(held, shards, sc.broadcast((least, most)), factor), ask))
        found = found.unionByName(other).groupBy("query_id").agg(F.slice(F.array_sort(F.flatten(F.collect_list("x"))), 1, k).alias("x"))
    return found.select("query_id", F.posexplode("x").alias("p", "x")).select("query_id", (F.col("p") + 1).cast("int").alias("rank"), F.col("x.vec_id").alias("vec_id"), F.col("x.score").alias("score"))
