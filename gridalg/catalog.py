"""What the catalog knows of a matrix."""

from __future__ import annotations

import json
from dataclasses import asdict, dataclass, replace
from enum import Enum

from pyspark.sql import DataFrame, functions as F

ZERO, NULL = "zero", "null"


class Scheme(str, Enum):
    """Where the entries lie: by row, by column, everywhere, or unknown."""

    R = "r"
    C = "c"
    B = "b"
    XI = "xi"


@dataclass(frozen=True)
class MatrixMeta:
    """Dimensions and statistics; None where not known. absent says what an entry means that is not stored."""

    nrows: int
    ncols: int
    absent: str = ZERO
    nullable: bool = False
    nnz: int | None = None
    stored: int | None = None
    vmin: float | None = None
    vmax: float | None = None
    scheme: Scheme = Scheme.XI
    #: Entries that are stored at most, where a count is not known but a bound is (rows of the table behind, from its footers).
    at_most: int | None = None
    #: Share of the stored values that are whole numbers of zero or more, and so may be ids.
    whole: float | None = None

    def bound(self) -> int:
        """Entries at most: a proven bound, whatever is known."""
        cells = self.nrows * self.ncols
        return min(cells, *(x for x in (self.stored, self.at_most) if x is not None), cells)

    def size(self) -> int:
        """Entries that a move of the matrix sends: nonzeros if known, else the bound."""
        return self.nnz if self.nnz is not None else self.bound()

    def selectivity(self, n: int) -> float:
        """Estimated share of the values that are ids of a dimension of n: whole ones, taken as spread evenly over their range."""
        if self.whole is None or self.vmin is None or self.vmax is None:
            return 1.0
        hit = min(n - 1, self.vmax) - max(0.0, self.vmin)
        span = self.vmax - self.vmin
        return 0.0 if hit < 0 else self.whole * min(1.0, (hit + 1) / (span + 1))

    def density(self) -> float:
        cells = self.nrows * self.ncols
        return 1.0 if self.nnz is None or not cells else self.nnz / cells

    def bytes(self) -> int:
        """Bytes of the dense form."""
        return 8 * self.nrows * self.ncols

    def json(self) -> str:
        return json.dumps(asdict(self))

    @staticmethod
    def parse(text: str) -> MatrixMeta:
        d = json.loads(text)
        return MatrixMeta(**d | {"scheme": Scheme(d["scheme"])})


def measured(cells: DataFrame, meta: MatrixMeta) -> MatrixMeta:
    """meta with statistics from one pass over the entries."""
    v = F.col("val")
    r = cells.agg(F.count("*"), F.count_if(v.isNotNull() & (v != 0)), F.count_if(v.isNull()), F.min("val"), F.max("val"), F.count_if((v == F.floor(v)) & (v >= 0))).first()
    return replace(meta, stored=r[0], nnz=r[1], nullable=r[2] > 0, vmin=r[3], vmax=r[4], whole=r[5] / r[0] if r[0] else 0.0)


def dimensions(cells: DataFrame) -> tuple[int, int]:
    """Largest ids plus one."""
    r = cells.agg(F.max("rid"), F.max("cid")).first()
    return (0 if r[0] is None else r[0] + 1), (0 if r[1] is None else r[1] + 1)
