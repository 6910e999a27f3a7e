"""Poisson non-negative factorisation by multiplicative updates at the nonzeros of the input."""

from __future__ import annotations

import math
from dataclasses import dataclass

from pyspark.sql import DataFrame, functions as F

from gridalg.api import Matrix
from gridalg.functions.lineage import cut
from gridalg.operators.cells import NONZERO, masked_product, nonzeros


@dataclass(frozen=True)
class Factors:
    """w: row vectors (id, vec) of A's rows; h: column vectors (id, vec) of A's columns."""

    w: DataFrame
    h: DataFrame
    k: int


def start(a: Matrix, k: int) -> Factors:
    """Fixed positive start values ((7 i + 3 j) mod 11 + 1) / 11, so that runs can be compared."""
    vec = lambda x, y: F.transform(F.sequence(F.lit(0), F.lit(k - 1)), lambda j: ((x * F.col("id") + y * j) % 11 + 1) / F.lit(11.0))
    m, n = a.shape
    return Factors(a.spark.range(m).select("id", vec(7, 3).alias("vec")), a.spark.range(n).select("id", vec(3, 7).alias("vec")), k)


def _sums(rows: DataFrame, k: int) -> DataFrame:
    """One row: the element-wise sum of all vectors."""
    return rows.agg(F.array(*[F.sum(F.col("vec")[i]) for i in range(k)]).alias("total"))


def _updated(own: DataFrame, top: DataFrame, other: DataFrame, k: int) -> DataFrame:
    """Each vector times its row of top, over the sum of the other side's vectors."""
    new = F.zip_with(F.zip_with("vec", F.coalesce("top", F.array(*[F.lit(0.0)] * k)), lambda x, y: x * y), "total", lambda x, t: F.when(t > 0, x / t).otherwise(0.0))
    return own.join(top, "id", "left").crossJoin(F.broadcast(_sums(other, k))).select("id", new.alias("vec"))


def _half(a: DataFrame, f: Factors, side: str) -> DataFrame:
    """The next w (or h), with both vectors brought to every nonzero."""
    key, own, other = ("rid", f.w, f.h) if side == "w" else ("cid", f.h, f.w)
    s = masked_product(a, f.w, f.h)
    theirs = "hv" if side == "w" else "wv"
    q = F.try_divide("val", "s")
    top = s.groupBy(F.col(key).alias("id")).agg(F.array(*[F.sum(q * F.col(theirs)[i]) for i in range(f.k)]).alias("top"))
    return _updated(own, top, other, f.k)


@dataclass(frozen=True)
class Grid:
    """The nonzeros dealt to side x side parts by hashes of row and column, so that a heavy line spreads over side parts.

    They are written once as columns of bytes: a half step moves some rows a part instead of one row a nonzero.
    """

    packed: DataFrame  # part, rid, cid, val: bytes of up to CHUNK nonzeros
    side: int

    @staticmethod
    def of(a: DataFrame, parts: int) -> Grid:
        side = max(1, math.ceil(math.sqrt(parts)))
        line = lambda c: F.pmod(F.xxhash64(c), F.lit(side)).cast("int")
        cells = nonzeros(a).select((line("rid") * side + line("cid")).alias("part"), F.col("rid").cast("long"), F.col("cid").cast("long"), F.col("val").cast("double"))
        return Grid(cut(cells.repartition(side * side, "part").groupBy("part").applyInArrow(_packed, "part int, rid binary, cid binary, val binary")), side)

    @property
    def cells(self) -> DataFrame:
        """part, rid, cid, val, one row a nonzero."""
        return self.packed.mapInArrow(_unpacked, "part int, rid long, cid long, val double")

    def half(self, f: Factors, side: str) -> DataFrame:
        """The next w (or h): each vector goes once to each part of its grid line, and sums of parts come back."""
        line = F.pmod(F.xxhash64("id"), F.lit(self.side)).cast("int")
        other = F.explode(F.sequence(F.lit(0), F.lit(self.side - 1)))
        bound = lambda rows: rows.select(line.alias("line"), "id", "vec").groupBy("line").applyInArrow(_bundled, "line int, id binary, vec binary")
        rows = bound(f.w).select(F.lit(0).alias("kind"), "id", "vec", F.col("line").alias("r"), other.alias("c"))
        columns = bound(f.h).select(F.lit(1).alias("kind"), "id", "vec", F.col("line").alias("c"), other.alias("r"))
        vectors = rows.unionByName(columns).select((F.col("r") * self.side + F.col("c")).cast("int").alias("part"), "kind", "id", "vec").repartition(self.side**2, "part")
        found = self.packed.groupBy("part").cogroup(vectors.groupBy("part")).applyInArrow(_kernel(f.k, side), "id long, " + ", ".join(f"t{i} double" for i in range(f.k)))
        top = found.groupBy("id").agg(F.array(*[F.sum(f"t{i}") for i in range(f.k)]).alias("top"))
        return _updated(f.w, top, f.h, f.k) if side == "w" else _updated(f.h, top, f.w, f.k)


#: Nonzeros or vectors of a row of bytes.
CHUNK = 1 << 18


def _packed(cells):
    """The nonzeros of a part as bytes."""
    import numpy as np
    import pyarrow as pa

    cols = [np.asarray(cells[c]) for c in ("rid", "cid", "val")]
    at = range(0, cells.num_rows, CHUNK)
    return pa.table({"part": cells["part"].slice(0, 1).take(pa.array([0] * len(at))), **{c: pa.array([x[lo : lo + CHUNK].tobytes() for lo in at], pa.binary()) for c, x in zip(("rid", "cid", "val"), cols, strict=True)}})


def _unpacked(batches):
    import numpy as np
    import pyarrow as pa

    for batch in batches:
        for row in batch.to_pylist():
            rid, cid, val = (np.frombuffer(row[c], t) for c, t in (("rid", np.int64), ("cid", np.int64), ("val", float)))
            yield pa.record_batch([pa.array(np.full(len(rid), row["part"], np.int32)), pa.array(rid), pa.array(cid), pa.array(val)], names=["part", "rid", "cid", "val"])


def _bundled(rows):
    """The vectors of a line as bytes, in order of their ids."""
    import numpy as np
    import pyarrow as pa

    ids = np.asarray(rows["id"])
    vec = np.asarray(rows["vec"].combine_chunks().flatten()).reshape(len(ids), -1)
    turn = np.argsort(ids)
    cuts = [turn[lo : lo + CHUNK] for lo in range(0, len(ids), CHUNK)]
    return pa.table({"line": rows["line"].slice(0, 1).take(pa.array([0] * len(cuts))), "id": pa.array([ids[x].tobytes() for x in cuts], pa.binary()), "vec": pa.array([vec[x].tobytes() for x in cuts], pa.binary())})


def _kernel(k: int, side: str):
    """Sums of (a / wh) times the other side's vectors over the nonzeros of a part, for each line of one side."""

    def run(cells, vectors):
        import numpy as np
        import pyarrow as pa

        names = ["id", *(f"t{i}" for i in range(k))]

        def table(ids, sums):
            return pa.table([pa.array(ids, pa.int64()), *(pa.array(sums[:, i]) for i in range(k))], names=names)

        def joined(column, dtype):
            return np.concatenate([np.frombuffer(x.as_buffer(), dtype) for x in column])

        if not cells.num_rows or not vectors.num_rows:
            return table(np.zeros(0, np.int64), np.zeros((0, k)))
        kind = np.asarray(vectors["kind"])
        held = []
        for n, key in ((0, "rid"), (1, "cid")):
            some = vectors.take(pa.array(np.flatnonzero(kind == n)))
            ids, flat = joined(some["id"], np.int64), joined(some["vec"], float).reshape(-1, k)
            turn = np.argsort(ids, kind="stable")
            held.append((flat[turn], ids[turn], np.searchsorted(ids[turn], joined(cells[key], np.int64))))
        (w, wi, r), (h, hi, c) = held
        val = joined(cells["val"], float)
        own, mine, theirs, there = (wi, r, h, c) if side == "w" else (hi, c, w, r)
        sums = np.zeros((len(own), k))
        for lo in range(0, len(val), 1 << 18):
            some = slice(lo, lo + (1 << 18))
            s = np.einsum("ij,ij->i", w[r[some]], h[c[some]])
            q = np.divide(val[some], s, out=np.zeros(len(s)), where=s != 0)
            for i in range(k):
                sums[:, i] += np.bincount(mine[some], weights=q * theirs[there[some], i], minlength=len(own))
        hit = np.flatnonzero(np.bincount(mine, minlength=len(own)))
        return table(own[hit], sums[hit])

    return run


#: Nonzeros of a part of a grid.
PART = 2_000_000


def prepare(a: Matrix, k: int) -> Grid | None:
    """The grid to iterate over, or None where bringing vectors to nonzeros moves less: hardly any entries in a line."""
    cells = nonzeros(a.cells())
    nnz = a.meta().nnz if a.meta().stored is not None else cells.count()
    parts = max(int(a.spark.conf.get("spark.sql.shuffle.partitions")), -(-nnz // PART))
    side = math.ceil(math.sqrt(parts))
    m, n = a.shape
    return Grid.of(cells, parts) if (m + n) * side < 3 * nnz else None


def step(a: Matrix, f: Factors, grid: Grid | None = None) -> Factors:
    """One iteration: w first, then h with the new w, which is written in between as the second half reads it twice."""
    half = (lambda f, side: grid.half(f, side)) if grid else (lambda f, side: _half(a.cells(), f, side))
    f = Factors(cut(half(f, "w")), f.h, f.k)
    return Factors(f.w, half(f, "h"), f.k)


def step_w(a: Matrix, f: Factors) -> Factors:
    return Factors(_half(a.cells(), f, "w"), f.h, f.k)


def step_full(a: Matrix, f: Factors) -> Factors:
    """The same iteration with wh built in full, as engines without a masked product do: m x n entries instead of the nonzeros."""
    ones = lambda n: F.broadcast(a.spark.range(n).select("id"))

    def full(f: Factors, side: str) -> DataFrame:
        grid = f.w.select(F.col("id").alias("rid"), F.col("vec").alias("wv")).crossJoin(ones(a.shape[1]).withColumnRenamed("id", "cid")).join(f.h.select(F.col("id").alias("cid"), F.col("vec").alias("hv")), "cid")
        s = grid.select("rid", "cid", F.aggregate(F.zip_with("wv", "hv", lambda x, y: x * y), F.lit(0.0), lambda acc, v: acc + v).alias("s"), "wv", "hv")
        q = F.try_divide(F.coalesce("val", F.lit(0.0)), "s")
        key, own, other, theirs = ("rid", f.w, f.h, "hv") if side == "w" else ("cid", f.h, f.w, "wv")
        both = s.join(a.cells(), ["rid", "cid"], "left")
        top = both.groupBy(F.col(key).alias("id")).agg(F.array(*[F.sum(q * F.col(theirs)[i]) for i in range(f.k)]).alias("top"))
        return _updated(own, top, other, f.k)

    f = Factors(cut(full(f, "w")), f.h, f.k)
    return Factors(f.w, full(f, "h"), f.k)


def objective(a: Matrix, f: Factors) -> DataFrame:
    """One value: the sum of wh, from column sums of w and row sums of h alone, minus the sum of a * log(wh) at a's nonzeros."""
    w, h = _sums(f.w, f.k).withColumnRenamed("total", "x"), _sums(f.h, f.k).withColumnRenamed("total", "y")
    whole = w.crossJoin(h).select(F.aggregate(F.zip_with("x", "y", lambda p, q: p * q), F.lit(0.0), lambda acc, v: acc + v).alias("whole"))
    at = masked_product(nonzeros(a.cells()), f.w, f.h).agg(F.sum(F.col("val") * F.ln("s")).alias("fit"))
    return whole.crossJoin(at).select((F.col("whole") - F.coalesce("fit", F.lit(0.0))).alias("objective"))


def pnmf(a: Matrix, k: int, iterations: int = 10, tolerance: float = 0.0, checkpoint: int = 1) -> tuple[Factors, list[float]]:
    """Factors after the iterations, or earlier once the objective falls by less than tolerance of itself; its history.

    Lineage is cut every few iterations. The driver sees one number an iteration.
    """
    f = start(a, k)
    history = [objective(a, f).first()[0]]
    grid = prepare(a, k)
    for i in range(iterations):
        f = step(a, f, grid)
        if (i + 1) % checkpoint == 0:
            f = Factors(cut(f.w), cut(f.h), k)
        history.append(objective(a, f).first()[0])
        if tolerance and history[-2] - history[-1] <= tolerance * abs(history[-2]):
            break
    return f, history


def matrices(a: Matrix, f: Factors) -> tuple[Matrix, Matrix]:
    """w (m x k) and h (k x n) as matrices."""
    flat = lambda rows: rows.select("id", F.posexplode("vec").alias("p", "val"))
    m, n = a.shape
    w = flat(f.w).select(F.col("id").alias("rid"), F.col("p").alias("cid"), "val")
    h = flat(f.h).select(F.col("p").alias("rid"), F.col("id").alias("cid"), "val")
    return Matrix.of(w, m, f.k, engine=a.engine), Matrix.of(h, f.k, n, engine=a.engine)


#: Users and items of a block that are scored together: the arrays of a pair take some 100 MB at rank 4.
USERS, ITEMS = 20_000, 2_000_000
#: Items of a leaf and users of a group; leaves that a group scores at first, and in each later round.
LEAF, GROUP, FIRST, ROUND = 256, 256, 16, 64
#: Entries of all item vectors up to which they are sent everywhere.
SENT = 32_000_000


def _blocks(vectors: DataFrame, size: int, name: str) -> tuple[DataFrame, int]:
    """Rows of up to some `size` ids with their vectors, as arrays, and the rows behind; ids are dealt by a hash, so blocks have about that size."""
    rows = vectors.count()
    n = -(-rows // size) or 1
    return vectors.groupBy(F.pmod(F.xxhash64("id"), F.lit(n)).alias(f"{name}_block")).agg(*[F.collect_list(F.struct(*vectors.columns)).alias(name)]), rows


def _halved(x, size: int) -> list:
    """The rows of x as groups of at most `size`, by medians of the widest column: near rows share a group."""
    import numpy as np

    out, todo = [], [np.arange(len(x))]
    while todo:
        own = todo.pop()
        if len(own) <= size:
            out.append(own)
            continue
        part = x[own]
        turn = np.argpartition(part[:, np.argmax(part.max(0) - part.min(0))], len(own) // 2)
        todo += [own[turn[len(own) // 2 :]], own[turn[: len(own) // 2]]]
    return [np.sort(own) for own in out if len(own)]


def _scores(h, w):
    """h times the turned w, added column by column: equal vectors get equal scores wherever they stand, as ties need."""
    import numpy as np

    total = np.multiply.outer(h[:, 0], w[:, 0])
    for j in range(1, h.shape[1]):
        total += np.multiply.outer(h[:, j], w[:, j])
    return total


def _first(score, k: int):
    """Columns of the k largest of each row; of equal ones, the first."""
    import numpy as np

    if score.shape[1] <= k:
        return np.broadcast_to(np.arange(score.shape[1]), score.shape)
    kth = np.partition(score, score.shape[1] - k, axis=1)[:, score.shape[1] - k, None]
    over, tie = score > kth, score == kth
    keep = over | (tie & (np.cumsum(tie, axis=1) <= k - over.sum(1, keepdims=True)))
    return np.nonzero(keep)[1].reshape(len(score), k)


def _search(h, row, had, w, topk: int):
    """Positions in w and scores of the topk best for each row of h, without the pairs (row, had); -inf where there are fewer.

    Items lie in leaves of near vectors. The corners of a leaf's box bound each user's scores in it, so a group of near
    users scores the leaves that promise most, then only those whose bound reaches what one of the group has found.
    """
    import numpy as np

    leaves = _halved(w, LEAF)
    low, high = (np.array([f(w[own], axis=0) for own in leaves]) for f in (np.min, np.max))
    best, at = np.full((len(h), topk), -np.inf), np.zeros((len(h), topk), np.int64)
    size = np.abs(h).sum(1)
    way = h / np.where(size > 0, size, 1)[:, None]
    start = np.searchsorted(row, np.arange(len(h) + 1))
    for own in _halved(way, GROUP):
        u, found, where = h[own], best[own], at[own]
        bound = np.maximum(way[own], 0) @ high.T + np.minimum(way[own], 0) @ low.T
        bound += 1e-9 * np.abs(way[own]) @ np.maximum(np.abs(low), np.abs(high)).T  # more than rounding takes
        bound *= size[own, None]
        n = np.diff(start)[own]
        mine = np.repeat(np.arange(len(own)), n)
        seen = had[np.repeat(start[own] - np.cumsum(n) + n, n) + np.arange(n.sum())]
        left, many = np.argsort(-(bound / np.where(size[own] > 0, size[own], 1)[:, None]).max(0), kind="stable"), FIRST
        while len(left):
            some, left = np.sort(np.concatenate([leaves[i] for i in left[:many]])), left[many:]
            score = _scores(u, w[some])
            place = np.minimum(np.searchsorted(some, seen), len(some) - 1)
            hit = some[place] == seen
            score[mine[hit], place[hit]] = -np.inf
            live = np.flatnonzero((score >= found[:, -1:]).any(0))
            score, some = score[:, live], some[live]
            cols = _first(score, topk)
            val = np.hstack([found, np.take_along_axis(score, cols, 1)])
            pos = np.hstack([where, some[cols]])
            turn = np.lexsort((pos, -val), axis=-1)[:, :topk]
            found, where = np.take_along_axis(val, turn, 1), np.take_along_axis(pos, turn, 1)
            left, many = left[(bound[:, left] >= found[:, -1:]).any(0)], ROUND
        best[own], at[own] = found, where
    return at, best


def _best(topk: int):
    """user, item, val: the topk unseen items of a block of items for each user of a block of users."""

    def run(batches):
        import numpy as np
        import pyarrow as pa

        def vectors(x):
            ids = np.asarray(x.field("id"))
            vec = np.asarray(x.field("vec").flatten()).reshape(len(ids), -1)
            return ids, vec, np.isfinite(vec).all(1)

        for batch in batches:
            for users, items in zip(batch.column(0), batch.column(1), strict=True):
                uid, h, good = vectors(users.values)
                iid, w, fine = vectors(items.values)
                turn = np.flatnonzero(fine)
                turn = turn[np.argsort(iid[turn])]  # by id, so that of equal scores the smaller id is first
                iid, w = iid[turn], w[turn]
                if not len(iid) or not good.any():
                    continue
                seen = users.values.field("seen")
                row = np.repeat(np.arange(len(uid)), np.diff(np.asarray(seen.offsets)))
                had = np.asarray(seen.flatten())
                place = np.minimum(np.searchsorted(iid, had), len(iid) - 1)
                known = (iid[place] == had) & good[row]
                at, val = _search(h[good], (np.cumsum(good) - 1)[row[known]], place[known], w, topk)
                keep = np.isfinite(val)
                yield pa.record_batch([pa.array(np.repeat(uid[good], keep.sum(1))), pa.array(iid[at[keep]]), pa.array(val[keep])], names=["user", "item", "val"])

    return run


def recommend(ratings: Matrix, features: Matrix, k: int, topk: int, iterations: int = 5) -> DataFrame:
    """user, rank, item, val: the best unseen items of each user. ratings is item x user, features item x feature.

    Features keep their columns with entries only, scaled to at most one, and stand beside the users as further columns
    of the factored matrix, so that items that look alike get alike factors. Users that have ratings are scored: blocks
    of users meet blocks of items as small matrices, a block pair gives each user's topk of it, and only those are merged.
    Within a pair, bounds rule out the items that cannot be among a user's topk; the result is that of all scores.
    Ties go to the smaller item.
    """
    x = features.select_nonempty_cols().cells()
    top = x.groupBy("cid").agg(F.max(F.abs("val")).alias("top"))
    n_items, n_users = ratings.shape
    side = x.join(top, "cid").filter("top > 0").select("rid", (F.col("cid") + n_users).alias("cid"), (F.abs("val") / F.col("top")).alias("val"))
    both = Matrix.of(cut(ratings.cells().unionByName(side)), n_items, n_users + features.shape[1], engine=ratings.engine)
    f = start(both, k)
    grid = prepare(both, k)
    for _ in range(iterations):
        f = step(both, f, grid)
        f = Factors(f.w, cut(f.h), k)
    users = both.cells().filter(F.col("cid") < n_users).groupBy(F.col("cid").alias("id")).agg(F.collect_list(F.when(F.expr(NONZERO), F.col("rid"))).alias("seen"))
    people, _ = _blocks(cut(f.h.join(users, "id").select("id", "vec", "seen")), USERS, "users")
    things, n = _blocks(f.w, ITEMS, "items")
    pairs = people.select("users").crossJoin(F.broadcast(things.select("items")) if n * (k + 1) <= SENT else things.select("items"))
    best = pairs.mapInArrow(_best(topk), "user long, item long, val double").groupBy("user").agg(F.slice(F.sort_array(F.collect_list(F.struct("val", (-F.col("item")).alias("neg"))), False), 1, topk).alias("x"))
    return best.select("user", F.posexplode("x").alias("p", "x")).select("user", (F.col("p") + 1).alias("rank"), (-F.col("x.neg")).alias("item"), F.col("x.val").alias("val"))
