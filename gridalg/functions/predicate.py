"""Propositional predicates over the row id, the column id and the value of a matrix entry."""

from __future__ import annotations

import operator
from dataclasses import dataclass

from pyspark.sql import Column, functions as F

_OPS = {"<": operator.lt, "<=": operator.le, "=": operator.eq, "!=": operator.ne, ">=": operator.ge, ">": operator.gt}
_NOT = {"<": ">=", "<=": ">", "=": "!=", "!=": "=", ">=": "<", ">": "<="}
_SWAP = {"rid": "cid", "cid": "rid", "val": "val"}


class Theta:
    """A predicate; combine with & | ~."""

    def __and__(self, other: Theta) -> Theta:
        return And(self, other)

    def __or__(self, other: Theta) -> Theta:
        return Or(self, other)

    def __invert__(self) -> Theta:
        return Not(self)

    def uses(self) -> frozenset[str]:
        raise NotImplementedError

    def column(self, val: Column | None = None) -> Column:
        raise NotImplementedError

    def swapped(self) -> Theta:
        raise NotImplementedError

    def dims_only(self) -> bool:
        return "val" not in self.uses()

    def conjuncts(self) -> list[Theta]:
        return [self]


@dataclass(frozen=True, eq=False)
class Symbol:
    name: str

    def _atom(self, op: str, other) -> Theta:
        return Atom(self.name, op, other.name if isinstance(other, Symbol) else None, None if isinstance(other, Symbol) else other)

    def __lt__(self, other):
        return self._atom("<", other)

    def __le__(self, other):
        return self._atom("<=", other)

    def __gt__(self, other):
        return self._atom(">", other)

    def __ge__(self, other):
        return self._atom(">=", other)

    def __eq__(self, other):  # type: ignore[override]
        return self._atom("=", other)

    def __ne__(self, other):  # type: ignore[override]
        return self._atom("!=", other)

    __hash__ = None  # type: ignore[assignment]


RID, CID, VAL = Symbol("rid"), Symbol("cid"), Symbol("val")


@dataclass(frozen=True)
class Atom(Theta):
    left: str
    op: str
    right: str | None
    constant: float | int | None

    def __post_init__(self):
        if self.right == self.left:
            raise ValueError("an atom compares two different attributes, or one with a constant")

    def uses(self):
        return frozenset(x for x in (self.left, self.right) if x)

    def column(self, val=None):
        get = lambda n: val if n == "val" and val is not None else F.col(n)
        return _OPS[self.op](get(self.left), get(self.right) if self.right else F.lit(self.constant))

    def swapped(self):
        return Atom(_SWAP[self.left], self.op, _SWAP[self.right] if self.right else None, self.constant)

    def at_zero(self) -> bool | None:
        """Truth for value zero, None if a dimension decides."""
        return None if self.right else _OPS[self.op](0, self.constant) if self.left == "val" else None


@dataclass(frozen=True)
class And(Theta):
    a: Theta
    b: Theta

    def uses(self):
        return self.a.uses() | self.b.uses()

    def column(self, val=None):
        return self.a.column(val) & self.b.column(val)

    def swapped(self):
        return And(self.a.swapped(), self.b.swapped())

    def conjuncts(self):
        return self.a.conjuncts() + self.b.conjuncts()

    def at_zero(self):
        x, y = self.a.at_zero(), self.b.at_zero()
        return False if False in (x, y) else None if None in (x, y) else True


@dataclass(frozen=True)
class Or(Theta):
    a: Theta
    b: Theta

    def uses(self):
        return self.a.uses() | self.b.uses()

    def column(self, val=None):
        return self.a.column(val) | self.b.column(val)

    def swapped(self):
        return Or(self.a.swapped(), self.b.swapped())

    def at_zero(self):
        x, y = self.a.at_zero(), self.b.at_zero()
        return True if True in (x, y) else None if None in (x, y) else False


@dataclass(frozen=True)
class Not(Theta):
    a: Theta

    def uses(self):
        return self.a.uses()

    def column(self, val=None):
        return ~self.a.column(val)

    def swapped(self):
        return Not(self.a.swapped())

    def conjuncts(self):
        if isinstance(self.a, Atom):
            return [Atom(self.a.left, _NOT[self.a.op], self.a.right, self.a.constant)]
        if isinstance(self.a, Or):
            return Not(self.a.a).conjuncts() + Not(self.a.b).conjuncts()
        return [self]

    def at_zero(self):
        x = self.a.at_zero()
        return None if x is None else not x


def all_of(parts: list[Theta]) -> Theta | None:
    out: Theta | None = None
    for p in parts:
        out = p if out is None else And(out, p)
    return out


def equals_on(theta: Theta, dim: str) -> int | None:
    """The constant that a conjunct fixes a dimension to, if any."""
    for c in theta.conjuncts():
        if isinstance(c, Atom) and c.left == dim and c.op == "=" and c.right is None:
            return int(c.constant)
    return None
