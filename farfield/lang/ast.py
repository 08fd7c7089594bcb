"""Abstract syntax of vertex programs."""

from __future__ import annotations

from dataclasses import dataclass, field
from typing import Any


class Node:
    """Expressions overload operators; `same` is equality as an expression, since == builds nodes for tests of equality."""

    def _bin(self, op: str, other: Any, swap: bool = False) -> "Bin":
        other = lift(other)
        return Bin(op, other, self) if swap else Bin(op, self, other)

    def __add__(self, o):
        return self._bin("+", o)

    def __radd__(self, o):
        return self._bin("+", o, True)

    def __sub__(self, o):
        return self._bin("-", o)

    def __rsub__(self, o):
        return self._bin("-", o, True)

    def __mul__(self, o):
        return self._bin("*", o)

    def __rmul__(self, o):
        return self._bin("*", o, True)

    def __truediv__(self, o):
        return self._bin("/", o)

    def __rtruediv__(self, o):
        return self._bin("/", o, True)

    def __lt__(self, o):
        return self._bin("<", o)

    def __le__(self, o):
        return self._bin("<=", o)

    def __gt__(self, o):
        return self._bin(">", o)

    def __ge__(self, o):
        return self._bin(">=", o)

    def eq(self, o):
        return self._bin("==", o)

    def ne(self, o):
        return self._bin("!=", o)

    def __and__(self, o):
        return self._bin("and", o)

    def __or__(self, o):
        return self._bin("or", o)

    def __invert__(self):
        return Un("not", self)

    def __neg__(self):
        return Un("-", self)


def lift(x: Any) -> Node:
    return x if isinstance(x, Node) else Lit(x)


@dataclass(frozen=True)
class Lit(Node):
    value: Any


@dataclass(frozen=True)
class Inf(Node):
    """Greater than all; NULL in integer columns."""


@dataclass(frozen=True)
class Var(Node):
    """The current vertex, an edge variable, or a let name."""

    name: str

    @property
    def ref(self):
        return Ref(self)

    @property
    def val(self):
        return Val(self)


@dataclass(frozen=True)
class FieldAt(Node):
    """A field read at the vertex that index gives."""

    field: str
    index: Node


@dataclass(frozen=True)
class Bin(Node):
    op: str
    left: Node
    right: Node


@dataclass(frozen=True)
class Un(Node):
    op: str
    arg: Node


@dataclass(frozen=True)
class IfExpr(Node):
    cond: Node
    then: Node
    other: Node


@dataclass(frozen=True)
class Pair(Node):
    first: Node
    second: Node


@dataclass(frozen=True)
class Fst(Node):
    arg: Node


@dataclass(frozen=True)
class Snd(Node):
    arg: Node


@dataclass(frozen=True)
class EdgePair(Node):
    """An edge value built by hand."""

    ref_: Node
    val_: Node


@dataclass(frozen=True)
class Ref(Node):
    arg: Node


@dataclass(frozen=True)
class Val(Node):
    arg: Node


@dataclass(frozen=True)
class Foreign(Node):
    name: str
    args: tuple


@dataclass(frozen=True)
class Reduce(Node):
    """func over body for each edge var in edges that passes the filters."""

    func: str
    body: Node
    var: str
    edges: "EdgeList"
    filters: tuple = ()


@dataclass(frozen=True)
class EdgeList:
    """In, Out or Nbr of a vertex."""

    kind: str
    index: Node

    def where(self, *conds):
        return Filtered(self, conds)

    def __getattr__(self, func):
        if func in REDUCERS:
            return getattr(Filtered(self, ()), func)
        raise AttributeError(func)


@dataclass(frozen=True)
class Filtered:
    edges: EdgeList
    conds: tuple

    def __getattr__(self, func):
        if func not in REDUCERS:
            raise AttributeError(func)
        return lambda body=None, var="e": Reduce(
            func, lift(body(Var(var))) if body else Lit(1), var, self.edges, tuple(lift(c(Var(var))) for c in self.conds)
        )


REDUCERS = frozenset({"minimum", "maximum", "total", "count", "any_", "all_", "product", "argmin", "argmax"})
#: Operators of accumulative writes; each is associative and commutative.
ACCUMULATIVE = frozenset({"min", "max", "+", "*", "or", "and"})


@dataclass(frozen=True)
class Let:
    name: str
    expr: Node


@dataclass(frozen=True)
class LocalSet:
    field: str
    target: Node
    op: str
    expr: Node


@dataclass(frozen=True)
class RemoteSet:
    field: str
    target: Node
    op: str
    expr: Node


@dataclass(frozen=True)
class When:
    cond: Node
    then: tuple
    other: tuple = ()


@dataclass(frozen=True)
class ForEdge:
    var: str
    edges: EdgeList
    block: tuple


class Program:
    def __rshift__(self, other: "Program") -> "Seq":
        return Seq((*(self.parts if isinstance(self, Seq) else (self,)), *(other.parts if isinstance(other, Seq) else (other,))))


@dataclass(frozen=True)
class Step(Program):
    var: str
    block: tuple


@dataclass(frozen=True)
class Stop(Program):
    """Vertices that meet cond take no part any more; their fields stay readable."""

    var: str
    cond: Node


@dataclass(frozen=True)
class Seq(Program):
    parts: tuple


@dataclass(frozen=True)
class Until:
    """kind: stable (fields), rounds (n), change_below (field, eps), no_live, or none_match (vertex name, condition): no vertex that goes on meets it."""

    kind: str
    args: tuple = field(default=())


@dataclass(frozen=True)
class Repeat(Program):
    """The body runs at least once. A loop that is not done after `limit` passes ends there, as the ledger says; without a limit it must end."""

    body: Program
    until: Until
    limit: int | None = None


@dataclass(frozen=True)
class Exit(Program):
    """Leaves the loop around it, in the middle of a pass, if `how` ("none" or "any") of the vertices that go on meet cond."""

    how: str
    var: str
    cond: Node
