"""Embedded builder of vertex programs."""

from __future__ import annotations

from farfield.lang import ast as A


class Field:
    def __init__(self, name: str):
        self.name = name

    def __getitem__(self, index) -> A.FieldAt:
        return A.FieldAt(self.name, A.lift(index))


class _Fields:
    def __getattr__(self, name: str) -> Field:
        return Field(name)


class _Edges:
    def __init__(self, kind: str):
        self.kind = kind

    def __getitem__(self, index) -> A.EdgeList:
        return A.EdgeList(self.kind, A.lift(index))


#: F.D[u] reads field D at u; F.id[u] is its id, F.Live[u] whether it is not stopped.
F = _Fields()
In, Out, Nbr = _Edges("In"), _Edges("Out"), _Edges("Nbr")
inf = A.Inf()


def step(fn) -> A.Step:
    return A.Step("u", tuple(fn(A.Var("u"))))


def stop(fn) -> A.Stop:
    return A.Stop("u", A.lift(fn(A.Var("u"))))


def local(at: A.FieldAt, expr, op: str = "=") -> A.LocalSet:
    return A.LocalSet(at.field, at.index, op, A.lift(expr))


def remote(at: A.FieldAt, op: str, expr) -> A.RemoteSet:
    return A.RemoteSet(at.field, at.index, op, A.lift(expr))


def let(name: str, expr) -> A.Let:
    return A.Let(name, A.lift(expr))


def var(name: str) -> A.Var:
    return A.Var(name)


def when(cond, then, other=()) -> A.When:
    return A.When(A.lift(cond), tuple(then), tuple(other))


def for_edge(edges: A.EdgeList, fn, name: str = "e") -> A.ForEdge:
    return A.ForEdge(name, edges, tuple(fn(A.Var(name))))


def either(cond, then, other) -> A.IfExpr:
    return A.IfExpr(A.lift(cond), A.lift(then), A.lift(other))


def pair(a, b) -> A.Pair:
    return A.Pair(A.lift(a), A.lift(b))


def foreign(name: str, *args) -> A.Foreign:
    return A.Foreign(name, tuple(map(A.lift, args)))


def stable(*fields: str) -> A.Until:
    return A.Until("stable", fields)


def rounds(k: int) -> A.Until:
    return A.Until("rounds", (k,))


def change_below(field: str, eps: float) -> A.Until:
    return A.Until("change_below", (field, eps))


def no_live() -> A.Until:
    return A.Until("no_live")


def none_match(fn) -> A.Until:
    return A.Until("none_match", ("u", A.lift(fn(A.Var("u")))))


def exit_when(how: str, fn) -> A.Exit:
    """how: 'none' or 'any' of the vertices that go on."""
    return A.Exit(how, "u", A.lift(fn(A.Var("u"))))


def repeat(body: A.Program, until: A.Until, limit: int | None = None) -> A.Repeat:
    return A.Repeat(body, until, limit)
