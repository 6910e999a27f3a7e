"""Matrices with a lazy algebra over Spark."""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass, field, replace

from pyspark.sql import Column, DataFrame, SparkSession, functions as F

from gridalg.catalog import NULL, ZERO, MatrixMeta, Scheme, dimensions, measured
from gridalg.functions.merge import Flags, MergeFn
from gridalg.functions.predicate import CID, RID, VAL, Theta
from gridalg.operators.cells import Limits, TooLarge, densify, lower
from gridalg.operators.joins import Operand, fused_sum, fused_totals, join_cells, output_size, place, result_dims
from gridalg.plans.cost import SHAPES, Placement, assign_schemes, shape_of
from gridalg.plans.nodes import Agg, Elem, Inverse, Map, MatMul, Node, NonEmpty, Ones, Scalar, Select, ShapeError, Source, Transpose
from gridalg.plans.rewrite import rewrite

__all__ = ["CID", "Choice", "NULL", "RID", "VAL", "ZERO", "Engine", "Limits", "Matrix", "MergeFn", "Scheme", "ShapeError", "Tensor", "TooLarge"]


@dataclass(frozen=True)
class Engine:
    """Options. rules: ids of the rewrites that apply (None: all); workers: N of the cost model."""

    rules: frozenset[str] | None = None
    strategy: str = "auto"
    placement: bool = True
    workers: int = 8
    limits: Limits = field(default_factory=Limits)


class Matrix:
    """A lazy matrix: a plan, lowered to a DataFrame (rid, cid, val) by cells()."""

    def __init__(self, node: Node, spark: SparkSession, engine: Engine = Engine()):
        self.node, self.spark, self.engine = node, spark, engine

    @staticmethod
    def of(cells: DataFrame, nrows: int | None = None, ncols: int | None = None, *, absent: str = ZERO, stats: bool = False, name: str = "A", engine: Engine = Engine(), nullable: bool = False, at_most: int | None = None) -> Matrix:
        """A matrix of entries that are unique in (rid, cid). Dimensions that are not given are looked up in one job.

        at_most bounds the stored entries where that is known for free; stats measures the matrix in one pass.
        """
        cells = cells.select(F.col("rid").cast("long").alias("rid"), F.col("cid").cast("long").alias("cid"), F.col("val").cast("double").alias("val"))
        if nrows is None or ncols is None:
            m, n = dimensions(cells)
            nrows, ncols = nrows if nrows is not None else m, ncols if ncols is not None else n
        meta = MatrixMeta(nrows, ncols, absent, nullable, at_most=at_most)
        return Matrix(Source(cells, measured(cells, meta) if stats else meta, name), cells.sparkSession, engine)

    @staticmethod
    def ones(spark: SparkSession, m: int, n: int, engine: Engine = Engine()) -> Matrix:
        return Matrix(Ones(m, n), spark, engine)

    def _new(self, node: Node) -> Matrix:
        return Matrix(node, self.spark, self.engine)

    def using(self, engine: Engine) -> Matrix:
        return Matrix(self.node, self.spark, engine)

    @property
    def shape(self) -> tuple[int, int]:
        return self.node.shape

    # linear algebra

    @property
    def T(self) -> Matrix:
        return self._new(Transpose(self.node))

    def __add__(self, other):
        return self._new(Elem("+", self.node, other.node) if isinstance(other, Matrix) else Scalar(self.node, "+", float(other)))

    __radd__ = __add__

    def __sub__(self, other):
        return self + (other * -1.0 if isinstance(other, Matrix) else -float(other))

    def __mul__(self, other):
        return self._new(Elem("*", self.node, other.node) if isinstance(other, Matrix) else Scalar(self.node, "*", float(other)))

    __rmul__ = __mul__

    def __truediv__(self, other):
        return self._new(Elem("/", self.node, other.node) if isinstance(other, Matrix) else Scalar(self.node, "*", 1.0 / float(other)))

    def __matmul__(self, other: Matrix) -> Matrix:
        return self._new(MatMul(self.node, other.node))

    def matmul(self, other: Matrix, strategy: str = "auto", **options) -> Matrix:
        """The product by a given physical strategy, beyond the reach of rewrites."""
        from gridalg.operators.cells import multiply

        product = MatMul(self.node, other.node)
        cells = multiply(self.cells(), other.cells(), strategy=strategy, **options)
        return Matrix.of(cells, *product.shape, engine=self.engine)

    def inverse(self) -> Matrix:
        return self._new(Inverse(self.node))

    def map(self, fn: Callable[[Column], Column], name: str = "map", keeps_zero: bool = False) -> Matrix:
        return self._new(Map(self.node, fn, name, keeps_zero))

    def log(self) -> Matrix:
        """Logarithms of the stored entries; zeros have none."""
        return self._new(Map(self.node, F.ln, "log", True))

    # selections

    def select(self, theta: Theta) -> Matrix:
        return self._new(Select(self.node, theta))

    def row(self, i: int) -> Matrix:
        return self.select(RID == i)

    def col(self, j: int) -> Matrix:
        return self.select(CID == j)

    def rows(self, first: int, last: int) -> Matrix:
        return self.select((RID >= first) & (RID <= last))

    def cols(self, first: int, last: int) -> Matrix:
        return self.select((CID >= first) & (CID <= last))

    def entry(self, i: int, j: int) -> Matrix:
        return self.select((RID == i) & (CID == j))

    def diag(self) -> Matrix:
        return self.select(RID == CID)

    def rows_in(self, ids: DataFrame) -> Matrix:
        """Rows whose id is in the first column of a DataFrame."""
        key = ids.select(ids.columns[0]).distinct().toDF("rid")
        return self._cells(self.cells().join(key, "rid", "left_semi"))

    def select_nonempty_rows(self, treat_absent_as: str = NULL) -> Matrix:
        return self._new(NonEmpty(self.node, "r", treat_absent_as))

    def select_nonempty_cols(self, treat_absent_as: str = NULL) -> Matrix:
        return self._new(NonEmpty(self.node, "c", treat_absent_as))

    def kfold(self, k: int, seed: int | None = None) -> list[tuple[Matrix, Matrix]]:
        """(train, test) for each of k disjoint sets of rows: by a seeded hash, or by the id modulo k without a seed."""
        cells = self.cells()
        fold = F.pmod(F.xxhash64("rid", F.lit(seed)), F.lit(k)) if seed is not None else F.pmod("rid", F.lit(k))
        return [(self._cells(cells.filter(fold != i)), self._cells(cells.filter(fold == i))) for i in range(k)]

    def reindex(self, dim: str = "r") -> Matrix:
        """Ids of the lines that have entries renumbered from 0 in order, without one task over all of them."""
        from gridalg.functions.encode import dense_codes

        key = "rid" if dim == "r" else "cid"
        cells = self.cells()
        codes, n = dense_codes(cells.select(key))
        out = cells.join(codes, key).drop(key).withColumnRenamed("code", key)
        m, k = self.shape
        return Matrix.of(out, n if dim == "r" else m, k if dim == "r" else n, absent=self.node.absent, engine=self.engine)

    # aggregates

    def agg(self, fn: str, dim: str) -> Matrix:
        return self._new(Agg(self.node, fn, dim))

    def avg_dense(self, dim: str = "r") -> Matrix:
        """Sums over the full length of a line, zeros included (agg avg divides by nonzeros)."""
        m, n = self.shape
        return self.agg("sum", dim) * (1.0 / {"r": n, "c": m, "d": m, "a": m * n}[dim])

    def argmax(self, dim: str = "r") -> DataFrame:
        """The id of the largest stored entry of each line; ties go to the smaller id."""
        return self.top(1, dim).drop("rank")

    def outliers(self, sigma: float = 3.0, dim: str = "r") -> DataFrame:
        """Stored entries more than sigma standard deviations from the mean of their line's stored entries, with z."""
        key = "rid" if dim == "r" else "cid"
        cells = self.cells()
        line = cells.groupBy(key).agg(F.avg("val").alias("mean"), F.stddev_pop("val").alias("sd"))
        z = F.try_divide(F.col("val") - F.col("mean"), F.col("sd"))
        return cells.join(line, key).select("rid", "cid", "val", z.alias("z")).filter(F.abs("z") > sigma)

    def row_sums(self) -> Matrix:
        return self.agg("sum", "r")

    def col_sums(self) -> Matrix:
        return self.agg("sum", "c")

    def trace(self) -> Matrix:
        return self.agg("sum", "d")

    def total(self) -> Matrix:
        return self.agg("sum", "a")

    def top(self, k: int, dim: str = "r") -> DataFrame:
        """The k largest entries of each row (or column), with rank; ties go to the smaller id."""
        key, other = ("rid", "cid") if dim == "r" else ("cid", "rid")
        best = self.cells().groupBy(key).agg(F.slice(F.array_sort(F.collect_list(F.struct((-F.col("val")).alias("neg"), F.col(other).alias("o")))), 1, k).alias("x"))
        return best.select(key, F.posexplode("x").alias("p", "x")).select(key, (F.col("p") + 1).alias("rank"), F.col("x.o").alias(other), (-F.col("x.neg")).alias("val"))

    # joins

    def meta(self) -> MatrixMeta:
        """What is known of the matrix; of a plan that is not a source, its cells bound the entries and its density estimates them."""
        if isinstance(self.node, Source):
            return self.node.meta
        m, n = self.shape
        return MatrixMeta(m, n, self.node.absent, self.node.nullable, nnz=int(self.node.density * m * n))

    def measured(self) -> Matrix:
        """The same matrix with statistics from one pass over its entries."""
        cells = self.cells()
        return Matrix(Source(cells, measured(cells, replace(self.meta(), nnz=None))), self.spark, self.engine)

    def choose(self, other: Matrix, gamma: str | tuple, f: MergeFn, strategy: str | None = None) -> Choice:
        """How a join would run: strategy, sizes, selectivity, placement and a bound of its rows. No job reads data for it."""
        shape, flags, limits = shape_of(gamma), f.flags(self.spark), self.engine.limits
        strategy = strategy or self.engine.strategy
        p, q = self.meta(), other.meta()
        dense = strategy in ("densify", "nested_loop")
        on_values = shape == "val=val"
        sparse = (flags.z0, flags.z0) if on_values else (flags.sx, flags.sy)
        # at most so many entries take part: nonzeros where the merge function's zeros fall away, all cells where not
        a, b = (m.nrows * m.ncols if dense or not s else m.size() for m, s in ((p, sparse[0]), (q, sparse[1])))
        most = tuple(m.nrows * m.ncols if dense or not s else m.bound() for m, s in ((p, sparse[0]), (q, sparse[1])))
        pairs = SHAPES[shape]
        eta = 1.0
        if len(pairs) == 1 and not on_values and "val" in pairs[0]:
            (x, y), = pairs
            eta = p.selectivity(q.nrows if y == "rid" else q.ncols) if x == "val" else q.selectivity(p.nrows if x == "rid" else p.ncols)
        placement = assign_schemes(shape, p.scheme, q.scheme, a, b, self.engine.workers, eta, tuple(m <= limits.broadcast for m in most)) if self.engine.placement else None
        if strategy == "auto" and len(pairs) == 1 and "val" in pairs[0] and not (placement and Scheme.B in (placement.sa, placement.sb)):
            # a filter pays where one side is small enough for it and the other is much larger; a full dimension rules out no value
            small, large = min(most), max(a, b)
            if not on_values:
                (x, y), = pairs
                dim, n = (a, p.nrows if x == "rid" else p.ncols) if x != "val" else (b, q.nrows if y == "rid" else q.ncols)
                small, large = (min(n, dim), b if x != "val" else a) if 2 * dim <= n else (large, 0)
            if small <= limits.bloom and large >= 4 * small and (not on_values or flags.z0):
                strategy = "bloom_sparse"
        rows = None
        if len(pairs) == 1 and not on_values and "val" not in pairs[0]:
            free = lambda m, k: m.ncols if k == "rid" else m.nrows
            (x, y), = pairs
            rows = min(most[0] * free(q, y), most[1] * free(p, x))
        return Choice(shape, flags, strategy, (a, b), most, eta, placement, rows)

    def join(self, other: Matrix, gamma: str | tuple, f: MergeFn, strategy: str | None = None) -> Tensor | Matrix:
        """The join on a predicate, with f merging the two values; overlays give a matrix, others a tensor.

        Strategy and placement come from the cost model unless they are given: see choose.
        """
        c = self.choose(other, gamma, f, strategy)
        a, b = (Operand(m.cells(), *m.shape, size=n) for m, n in ((self, c.most[0]), (other, c.most[1])))
        schemes = (c.placement.sa, c.placement.sb) if c.placement else None
        limits = self.engine.limits

        def cells() -> DataFrame:
            if c.rows is not None and c.rows > limits.output and c.flags.sx and c.flags.sy:
                rows = output_size(a, b, c.shape)
                if rows > limits.output:
                    raise TooLarge(f"a join of {rows} entries is over the limit of {limits.output}; sums of it need no rows: see Tensor.agg")
            return join_cells(a, b, c.shape, f, c.flags, strategy=c.strategy, limits=limits, schemes=schemes)

        if c.shape in ("overlay", "transpose"):
            return self._cells(cells())
        sizes = {("a", "rid"): a.nrows, ("a", "cid"): a.ncols, ("b", "rid"): b.nrows, ("b", "cid"): b.ncols}
        dims = tuple(result_dims(c.shape))
        return Tensor(cells, tuple(sizes[d] for d in dims), dims, (self, other, gamma, f, strategy), c)

    def explain_join(self, other: Matrix, gamma: str | tuple, f: MergeFn) -> str:
        return str(self.choose(other, gamma, f))

    def placement(self, other: Matrix, gamma: str | tuple, eta: float | None = None) -> Placement:
        """The cheapest placement of the operands of a join on nonzeros, from known sizes."""
        p, q = self.meta(), other.meta()
        small = tuple(m.bound() <= self.engine.limits.broadcast for m in (p, q))
        return assign_schemes(shape_of(gamma), p.scheme, q.scheme, p.size(), q.size(), self.engine.workers, 1.0 if eta is None else eta, small)

    def kron(self, other: Matrix) -> Matrix:
        """The Kronecker product, as the cross product with one row and one column id."""
        from gridalg.functions.merge import MUL

        t = self.join(other, "cross", MUL)
        p, q = other.shape
        m, n = self.shape
        cells = t.cells.select((F.col("d1") * p + F.col("d3")).alias("rid"), (F.col("d2") * q + F.col("d4")).alias("cid"), "val")
        return Matrix.of(cells, m * p, n * q, engine=self.engine)

    # results

    def _cells(self, cells: DataFrame) -> Matrix:
        meta = MatrixMeta(*self.shape, absent=self.node.absent, nullable=True)
        return Matrix(Source(cells, meta), self.spark, self.engine)

    def plan(self) -> Node:
        return rewrite(self.node, self.engine.rules)[0]

    def explain(self) -> str:
        """The plan as written, the rules that fire, and the plan that runs."""
        new, fired = rewrite(self.node, self.engine.rules)
        return f"{self.node.show()}\n{' '.join(fired)}\n{new.show()}"

    def cells(self) -> DataFrame:
        return lower(self.plan(), self.spark, self.engine.limits)

    def dense(self) -> DataFrame:
        return densify(self.cells(), *self.shape, self.engine.limits.grid)

    def scalar(self) -> float | None:
        """The value of a 1 x 1 matrix, brought to the driver."""
        r = self.cells().agg(F.max("val")).first()
        return r[0]

    def placed(self, scheme: Scheme, n: int | None = None) -> Matrix:
        meta = self.node.meta if isinstance(self.node, Source) else MatrixMeta(*self.shape, absent=self.node.absent, nullable=self.node.nullable)
        return Matrix(Source(place(self.cells(), scheme, n), replace(meta, scheme=scheme)), self.spark, self.engine)

    def create_view(self, name: str) -> None:
        self.cells().createOrReplaceTempView(name)


@dataclass(frozen=True)
class Choice:
    """What the cost model says of a join: sizes are estimates, most and rows are bounds."""

    shape: str
    flags: Flags
    strategy: str
    sizes: tuple[int, int]
    most: tuple[int, int]
    eta: float
    placement: Placement | None
    rows: int | None

    def __str__(self) -> str:
        place = f"{self.placement.sa.value},{self.placement.sb.value} moving {self.placement.cost:.0f}" if self.placement else "as they lie"
        return f"{self.shape}: {self.strategy}, sizes {self.sizes[0]} and {self.sizes[1]}, selectivity {self.eta:.3g}, placed {place}"


class Tensor:
    """A lazy tensor of order 3 or 4: cells (d1.., val), sizes, and the side and attribute behind each dimension.

    parts are the operands, predicate, merge function and strategy of the join behind it; aggregates and selections use them
    to avoid the join's rows.
    """

    def __init__(self, cells: DataFrame | Callable[[], DataFrame], sizes: tuple[int, ...], origin: tuple[tuple[str, str], ...], parts: tuple | None = None, choice: Choice | None = None):
        self._make, self.sizes, self.origin, self.parts, self.choice = cells, sizes, origin, parts, choice
        self._made: DataFrame | None = None if callable(cells) else cells

    @property
    def cells(self) -> DataFrame:
        if self._made is None:
            self._made = self._make()
        return self._made

    def dims(self) -> list[str]:
        return [f"d{i + 1}" for i in range(len(self.sizes))]

    def _product(self) -> tuple[Operand, Operand, str] | None:
        """The operands, if this is a join on one dimension that multiplies values and rule R40 is on."""
        if self.parts is None or len(self.sizes) != 3:
            return None
        a, b, gamma, f, strategy = self.parts
        if f.name != "mul" or strategy is not None or (a.engine.rules is not None and "R40" not in a.engine.rules):
            return None
        return Operand(a.cells(), *a.shape), Operand(b.cells(), *b.shape), shape_of(gamma)

    def agg(self, fn: str, over: tuple[str, ...]) -> DataFrame:
        """An aggregate over some dimensions.

        A sum over one dimension of a product is fused with the join (R40): over the shared dimension it is a matrix
        product, over a free one that side is summed first. Other aggregates group what the join leaves; where the shared
        dimension stays, the rows of a group are in one task already and nothing is dealt again.
        """
        parts = self._product()
        if fn == "sum" and len(over) == 1 and parts is not None:
            return fused_sum(*parts, over[0])
        stay = [d for d in self.dims() if d not in over]
        value = {"sum": F.sum("val"), "max": F.max("val"), "min": F.min("val"), "nnz": F.count_if(F.col("val") != 0).cast("double"), "avg": F.try_divide(F.sum("val"), F.count_if(F.col("val") != 0))}[fn]
        return self.cells.groupBy(*stay).agg(value.alias("val"))

    def totals(self) -> DataFrame:
        """One row: n, the number of rows that a join on nonzeros gives, and total, their sum; without those rows for products."""
        parts = self._product()
        if parts is not None:
            return fused_totals(*parts)
        return self.cells.agg(F.count("*").alias("n"), F.sum("val").alias("total"))

    def select(self, **wanted: int | tuple[int, int]) -> Tensor:
        """The cells where each named dimension has an id or lies between two (R36); selections go to the operand behind it."""
        if self.parts is None:
            cells = self.cells
            for d, x in wanted.items():
                lo, hi = x if isinstance(x, tuple) else (x, x)
                cells = cells.filter(F.col(d).between(lo, hi))
            return Tensor(cells, self.sizes, self.origin)
        a, b, gamma, f, strategy = self.parts
        pairs = SHAPES[shape_of(gamma)]
        sides = {"a": a, "b": b}
        for d, x in wanted.items():
            lo, hi = x if isinstance(x, tuple) else (x, x)
            side, k = self.origin[self.dims().index(d)]
            both = [(side, k)] + [("b", q) for p, q in pairs if side == "a" and p == k and q != "val"]
            for s, key in both:
                t = RID if key == "rid" else CID
                sides[s] = sides[s].select((t >= lo) & (t <= hi))
        return sides["a"].join(sides["b"], gamma, f, strategy)

    def lead(self, over: tuple[str, ...]) -> str:
        """The dimension to deal by: the first that no following aggregate removes."""
        return next(d for d in self.dims() if d not in over)

    def laid_out(self, over: tuple[str, ...]) -> Tensor:
        """The cells dealt by the lead dimension, so that aggregates over the others stay within tasks."""
        return Tensor(self.cells.repartition(self.lead(over)), self.sizes, self.origin)
