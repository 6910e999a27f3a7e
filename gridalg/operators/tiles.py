"""Matrices as blocks: dense, or sparse by rows or columns, multiplied by NumPy in Arrow batches."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame, functions as F

#: Side of a block: a million cells, or 8 MB dense, fit a cache and an Arrow batch.
SIDE = 1000
DENSE, BY_ROW, BY_COLUMN = 0, 1, 2
#: Share of nonzeros above which a block is dense. Both forms take the same space at 2/3; dense ones multiply faster.
DENSE_FROM = 1 / 3
TILE = "rblk long, cblk long, fmt int, nr int, nc int, ptr array<int>, idx array<int>, vals array<double>"


def pack(x: np.ndarray, fmt: int | None = None) -> dict:
    """A block in the form that its density asks for, or in the given one."""
    nr, nc = x.shape
    if fmt is None:
        fmt = DENSE if np.count_nonzero(x) > DENSE_FROM * x.size else BY_ROW
    if fmt == DENSE:
        return {"fmt": 0, "nr": nr, "nc": nc, "ptr": None, "idx": None, "vals": x.ravel().tolist()}
    y = x if fmt == BY_ROW else x.T
    r, c = np.nonzero(y)
    return {"fmt": fmt, "nr": nr, "nc": nc, "ptr": np.concatenate([[0], np.cumsum(np.bincount(r, minlength=len(y)))]).astype(int).tolist(), "idx": c.tolist(), "vals": y[r, c].tolist()}


def unpack(fmt: int, nr: int, nc: int, ptr, idx, vals) -> np.ndarray:
    if fmt == DENSE:
        return np.asarray(vals, float).reshape(nr, nc)
    lines, width = (nr, nc) if fmt == BY_ROW else (nc, nr)
    x = np.zeros((lines, width))
    x[np.repeat(np.arange(lines), np.diff(np.asarray(ptr))), np.asarray(idx, int)] = vals
    return x if fmt == BY_ROW else x.T


def to_tiles(cells: DataFrame, nrows: int, ncols: int, side: int = SIDE) -> DataFrame:
    """Blocks of the nonzeros; blocks without any are not stored.

    Entries come in order of their block, and all blocks of a batch are made at once; one that goes on into the next
    batch waits for the rest.
    """

    def build(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: list[list[np.ndarray]] = []
        for batch in batches:
            x = [np.asarray(batch.column(i)) for i in range(5)]
            if not len(x[0]):
                continue
            new = np.flatnonzero((np.diff(x[0]) != 0) | (np.diff(x[1]) != 0)) + 1
            if held and (held[-1][0][-1] != x[0][0] or held[-1][1][-1] != x[1][0]):
                new = np.concatenate([[0], new])
            if not len(new):
                held.append(x)
                continue
            done = [*held, [c[: new[-1]] for c in x]]
            yield from _packed([np.concatenate(c) for c in zip(*done, strict=True)], nrows, ncols, side)
            held = [[c[new[-1] :] for c in x]]
        if held:
            yield from _packed([np.concatenate(c) for c in zip(*held, strict=True)], nrows, ncols, side)

    keyed = cells.filter("val IS NOT NULL AND val <> 0").select(F.floor(F.col("rid") / side).alias("rblk"), F.floor(F.col("cid") / side).alias("cblk"), F.col("rid").cast("long"), F.col("cid").cast("long"), F.col("val").cast("double"))
    return keyed.repartition("rblk", "cblk").sortWithinPartitions("rblk", "cblk", "rid", "cid").mapInArrow(build, TILE)


def _packed(entries: list[np.ndarray], nrows: int, ncols: int, side: int) -> Iterator[pa.RecordBatch]:
    """Whole blocks, given as entries in order: sparse ones all at once, dense ones one by one."""
    rblk, cblk, rid, cid, val = entries
    at = np.concatenate([[0], np.flatnonzero((np.diff(rblk) != 0) | (np.diff(cblk) != 0)) + 1, [len(val)]])
    r, c, size = rblk[at[:-1]], cblk[at[:-1]], np.diff(at)
    nr, nc = np.minimum(side, nrows - r * side), np.minimum(side, ncols - c * side)
    full = size > DENSE_FROM * nr * nc
    for i in np.flatnonzero(full):
        x = np.zeros((nr[i], nc[i]))
        own = slice(at[i], at[i + 1])
        x[rid[own] - r[i] * side, cid[own] - c[i] * side] = val[own]
        yield _tiles(r[i : i + 1], c[i : i + 1], DENSE, nr[i : i + 1], nc[i : i + 1], None, None, _lists(np.array([0, x.size]), x.ravel()))
    thin = ~full
    if thin.any():
        entry = np.repeat(thin, size)
        r, c, nr, nc, size = r[thin], c[thin], nr[thin], nc[thin], size[thin]
        rid, cid, val = rid[entry], cid[entry], val[entry]
        first = np.concatenate([[0], np.cumsum(nr + 1)])
        line = np.repeat(first[:-1] - r * side, size) + rid + 1
        ends = np.cumsum(np.bincount(line, minlength=first[-1]))
        start = np.concatenate([[0], np.cumsum(size)])
        ptr = (ends - np.repeat(start[:-1], nr + 1)).astype(np.int32)
        idx = (cid - np.repeat(c * side, size)).astype(np.int32)
        yield _tiles(r, c, BY_ROW, nr, nc, _lists(first, ptr), _lists(start, idx), _lists(start, val))


def _lists(at: np.ndarray, flat: np.ndarray) -> pa.Array:
    return pa.ListArray.from_arrays(pa.array(at.astype(np.int32)), pa.array(flat))


def _tiles(r, c, fmt: int, nr, nc, ptr, idx, vals) -> pa.RecordBatch:
    n, ints = len(r), pa.list_(pa.int32())
    columns = [pa.array(r, pa.int64()), pa.array(c, pa.int64()), pa.array(np.full(n, fmt, np.int32)), pa.array(nr.astype(np.int32)), pa.array(nc.astype(np.int32)), pa.nulls(n, ints) if ptr is None else ptr, pa.nulls(n, ints) if idx is None else idx, vals]
    return pa.record_batch(columns, names=[x.split()[0] for x in TILE.split(", ")])


def to_cells(tiles: DataFrame, side: int = SIDE) -> DataFrame:
    """The nonzeros of blocks, in SQL functions only."""
    line = F.transform(F.sequence(F.lit(0), F.size("ptr") - 2), lambda i: F.array_repeat(i, F.get("ptr", i + 1) - F.get("ptr", i)))
    dense = F.transform("vals", lambda v, p: F.struct(F.floor(p / F.col("nc")).cast("int").alias("r"), (p % F.col("nc")).cast("int").alias("c"), v.alias("val")))
    sparse = F.transform(F.arrays_zip(F.flatten(line).alias("l"), F.col("idx").alias("i"), F.col("vals").alias("v")), lambda x: F.struct(F.when(F.col("fmt") == BY_ROW, x["l"]).otherwise(x["i"]).alias("r"), F.when(F.col("fmt") == BY_ROW, x["i"]).otherwise(x["l"]).alias("c"), x["v"].alias("val")))
    each = tiles.select("rblk", "cblk", F.inline(F.when(F.col("fmt") == DENSE, dense).otherwise(sparse)))
    return each.filter("val <> 0").select((F.col("rblk") * side + F.col("r")).alias("rid"), (F.col("cblk") * side + F.col("c")).alias("cid"), "val")


def transpose(tiles: DataFrame) -> DataFrame:
    """Sparse blocks turn by name alone: rows of one are columns of the other. Dense ones are turned."""

    def turn(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for pdf in frames:
            rows = []
            for t in pdf.itertuples(index=False):
                x = {"fmt": {DENSE: DENSE, BY_ROW: BY_COLUMN, BY_COLUMN: BY_ROW}[t.fmt], "nr": t.nc, "nc": t.nr, "ptr": t.ptr, "idx": t.idx, "vals": t.vals}
                if t.fmt == DENSE:
                    x["vals"] = np.asarray(t.vals).reshape(t.nr, t.nc).T.ravel().tolist()
                rows.append({"rblk": t.cblk, "cblk": t.rblk} | x)
            yield pd.DataFrame(rows, columns=[c.split()[0] for c in TILE.split(", ")])

    return tiles.mapInPandas(turn, TILE)


def multiply(a: DataFrame, b: DataFrame) -> DataFrame:
    """The product of blocked matrices: blocks meet on the inner id and are multiplied where they meet.

    Partial products of one output block are added in the batch that makes them; the rest of the sum is a pass over the
    partial products in order of their output block, which holds one block at a time.
    """
    names = ["fmt", "nr", "nc", "ptr", "idx", "vals"]
    x = a.select("rblk", F.col("cblk").alias("k"), *[F.col(c).alias(f"a_{c}") for c in names])
    y = b.select(F.col("rblk").alias("k"), "cblk", *[F.col(c).alias(f"b_{c}") for c in names])
    columns = [c.split()[0] for c in TILE.split(", ")]

    def partial(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for pdf in frames:
            for (r, c), own in pdf.groupby(["rblk", "cblk"], sort=False):
                total = sum(unpack(t.a_fmt, t.a_nr, t.a_nc, t.a_ptr, t.a_idx, t.a_vals) @ unpack(t.b_fmt, t.b_nr, t.b_nc, t.b_ptr, t.b_idx, t.b_vals) for t in own.itertuples(index=False))
                yield pd.DataFrame([{"rblk": r, "cblk": c} | pack(total)], columns=columns)

    def add(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        at, total = None, None
        for pdf in frames:
            for t in pdf.itertuples(index=False):
                if at != (t.rblk, t.cblk):
                    if at is not None:
                        yield pd.DataFrame([{"rblk": at[0], "cblk": at[1]} | pack(total)], columns=columns)
                    at, total = (t.rblk, t.cblk), 0.0
                total = total + unpack(t.fmt, t.nr, t.nc, t.ptr, t.idx, t.vals)
        if at is not None:
            yield pd.DataFrame([{"rblk": at[0], "cblk": at[1]} | pack(total)], columns=columns)

    made = x.join(y, "k").mapInPandas(partial, TILE)
    return made.repartition("rblk", "cblk").sortWithinPartitions("rblk", "cblk").mapInPandas(add, TILE)


def tensor_tiles(a: DataFrame, b: DataFrame, on: tuple[str, str], side: int = SIDE) -> DataFrame:
    """d1, b2, b3 and a block for each: the outer product of two lines that meet on a dimension. d1 is exact, the others blocked."""
    (p, q), free = on, {"rid": "cid", "cid": "rid"}
    x = a.filter("val <> 0").select(F.col(p).alias("d1"), F.floor(F.col(free[p]) / side).alias("b2"), F.struct((F.col(free[p]) % side).alias("i"), F.col("val").alias("v")).alias("e")).groupBy("d1", "b2").agg(F.collect_list("e").alias("xs"))
    y = b.filter("val <> 0").select(F.col(q).alias("d1"), F.floor(F.col(free[q]) / side).alias("b3"), F.struct((F.col(free[q]) % side).alias("i"), F.col("val").alias("v")).alias("e")).groupBy("d1", "b3").agg(F.collect_list("e").alias("ys"))
    cells = F.flatten(F.transform("xs", lambda s: F.transform("ys", lambda t: F.struct(s["i"].alias("i"), t["i"].alias("j"), (s["v"] * t["v"]).alias("val")))))
    return x.join(y, "d1").select("d1", "b2", "b3", cells.alias("tile"))
