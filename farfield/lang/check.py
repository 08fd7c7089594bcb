"""Static checks of programs, before any job runs."""

from __future__ import annotations

from dataclasses import fields as parts_of
from dataclasses import is_dataclass

from farfield.lang import ast as A


class ProgramError(ValueError):
    pass


def children(n) -> list:
    match n:
        case A.FieldAt(_, i):
            return [i]
        case A.Bin(_, a, b) | A.Pair(a, b) | A.EdgePair(a, b):
            return [a, b]
        case A.Un(_, a) | A.Fst(a) | A.Snd(a) | A.Ref(a) | A.Val(a):
            return [a]
        case A.IfExpr(c, a, b):
            return [c, a, b]
        case A.Foreign(_, args):
            return list(args)
        case A.Reduce(_, body, _, edges, filters):
            return [body, edges.index, *filters]
    return []


def walk(n):
    yield n
    for c in children(n):
        yield from walk(c)


def statements(block):
    for s in block:
        yield s
        if isinstance(s, A.When):
            yield from statements(s.then)
            yield from statements(s.other)
        elif isinstance(s, A.ForEdge):
            yield from statements(s.block)


def expressions(s) -> list:
    match s:
        case A.Let(_, e):
            return [e]
        case A.LocalSet(_, t, _, e) | A.RemoteSet(_, t, _, e):
            return [t, e]
        case A.When(c, _, _):
            return [c]
        case A.ForEdge(_, edges, _):
            return [edges.index]
    return []


def steps(p):
    match p:
        case A.Seq(parts):
            for q in parts:
                yield from steps(q)
        case A.Repeat(body, _, _):
            yield from steps(body)
        case _:
            yield p


def written_fields(p) -> set[str]:
    return {s.field for q in steps(p) if isinstance(q, A.Step) for s in statements(q.block) if isinstance(s, (A.LocalSet, A.RemoteSet))}


def _rooted(e: A.Node, name: str) -> bool:
    while isinstance(e, A.FieldAt):
        e = e.index
    if isinstance(e, A.Ref):
        e = e.arg
    return isinstance(e, A.Var) and e.name == name


def check_program(p: A.Program, fields: set[str] | None = None, profile: str = "full") -> None:
    """Raises ProgramError. profile 'neighbour_only' also rejects remote access, as earlier languages have none."""
    for q in steps(p):
        if isinstance(q, (A.Stop, A.Exit)):
            if any(isinstance(n, A.Reduce) for n in walk(q.cond)):
                raise ProgramError("a condition to stop or to leave a loop looks at the current vertex only")
            if isinstance(q, A.Exit) and q.how not in ("none", "any"):
                raise ProgramError(f"a loop is left when none or any meet a condition, not {q.how}")
            continue
        remote_ops: dict[str, str] = {}
        for s in statements(q.block):
            if isinstance(s, A.LocalSet):
                if s.target != A.Var(q.var):
                    raise ProgramError(f"local write to {s.field} must be to the current vertex")
                if s.op != "=" and s.op not in A.ACCUMULATIVE:
                    raise ProgramError(f"unknown operator {s.op}")
            if isinstance(s, A.RemoteSet):
                if s.op not in A.ACCUMULATIVE:
                    raise ProgramError(f"remote write to {s.field} must be accumulative, not {s.op}")
                if remote_ops.setdefault(s.field, s.op) != s.op:
                    raise ProgramError(f"MixedRemoteOps: {s.field} gets {remote_ops[s.field]} and {s.op} in one step")
                if profile == "neighbour_only":
                    raise ProgramError("this profile has no remote writes")
            if isinstance(s, (A.LocalSet, A.RemoteSet)) and s.field in ("id", "Live", "In", "Out", "Nbr"):
                raise ProgramError(f"{s.field} can't be written")
            if isinstance(s, A.ForEdge):
                if any(isinstance(t, A.ForEdge) for t in statements(s.block)):
                    raise ProgramError("NestedNeighbourhood: loops over edges can't be nested")
                if any(isinstance(t, A.LocalSet) and t.op == "=" for t in statements(s.block)):
                    raise ProgramError("a loop over edges may only accumulate")
            for e in expressions(s):
                for n in walk(e):
                    if isinstance(n, A.Reduce):
                        if n.func not in A.REDUCERS:
                            raise ProgramError(f"unknown reducer {n.func}")
                        if n.edges.index != A.Var(q.var):
                            raise ProgramError("edge lists are read at the current vertex")
                        if any(isinstance(m, A.Reduce) for m in walk(n.body)):
                            raise ProgramError("NestedNeighbourhood: comprehensions can't be nested; allow_two_hop takes them if the inner one hangs on the neighbour only")
                        for m in walk(n.body):
                            if isinstance(m, A.FieldAt) and isinstance(m.index, A.FieldAt) and not _rooted(m, n.var) and not _rooted(m, q.var):
                                raise ProgramError("a chain in a comprehension starts at the neighbour or the current vertex")
                    if isinstance(n, A.FieldAt):
                        if not n.field[0].isupper() and n.field != "id":
                            raise ProgramError(f"field names are capitalised: {n.field}")
                        if isinstance(n.index, (A.Lit, A.Inf)) and not (isinstance(n.index, A.Lit) and isinstance(n.index.value, int)):
                            raise ProgramError("an index must be an id")
                        if profile == "neighbour_only" and isinstance(n.index, A.FieldAt):
                            raise ProgramError("this profile has no chains")
    if fields is not None:
        known = fields | written_fields(p) | {"id", "Live"}
        for q in steps(p):
            es = [q.cond] if isinstance(q, (A.Stop, A.Exit)) else [e for s in statements(q.block) for e in expressions(s)]
            for e in es:
                for n in walk(e):
                    if isinstance(n, A.FieldAt) and n.field not in known:
                        raise ProgramError(f"field {n.field} is read but nowhere written")
    _check_loops(p)


def hoist_two_hops(p):
    """The program with each comprehension inside another computed by a step before, as a field that is read at the neighbour. The inner one must hang on the
    neighbour only: its edge list is the neighbour's, and nothing else of the outer edge or the current vertex is in it."""
    if isinstance(p, A.Seq):
        return A.Seq(tuple(x for q in map(hoist_two_hops, p.parts) for x in (q.parts if isinstance(q, A.Seq) else (q,))))
    if isinstance(p, A.Repeat):
        return A.Repeat(hoist_two_hops(p.body), p.until, p.limit)
    if not isinstance(p, A.Step):
        return p
    found: dict[A.Reduce, str] = {}

    def change(x, edge: str | None):
        if isinstance(x, A.Reduce) and edge is not None:
            here = A.Var(p.var)
            outside = (here,) if x.var == edge else (here, A.Var(edge))
            if x.edges.index != A.Ref(A.Var(edge)) or any(n in outside for e in (x.body, *x.filters) for n in walk(e)):
                raise ProgramError("NestedNeighbourhood: the inner comprehension must hang on the neighbour only")
            inner = A.Reduce(x.func, x.body, x.var, A.EdgeList(x.edges.kind, here), x.filters)
            return A.FieldAt(found.setdefault(inner, f"Hop{len(found)}"), A.Ref(A.Var(edge)))
        if isinstance(x, A.Reduce):
            return A.Reduce(x.func, change(x.body, x.var), x.var, x.edges, tuple(change(c, x.var) for c in x.filters))
        if isinstance(x, tuple):
            return tuple(change(y, edge) for y in x)
        if is_dataclass(x) and not isinstance(x, type):
            return type(x)(*(change(getattr(x, f.name), edge) for f in parts_of(x)))
        return x

    out = change(p, None)
    if not found:
        return p
    return A.Seq((A.Step(p.var, tuple(A.LocalSet(name, A.Var(p.var), "=", r) for r, name in found.items())), out))


def _check_loops(p, inside: bool = False) -> None:
    if isinstance(p, A.Seq):
        for q in p.parts:
            _check_loops(q, inside)
    if isinstance(p, A.Exit) and not inside:
        raise ProgramError("there is no loop to leave")
    if isinstance(p, A.Repeat):
        if p.until.kind == "stable" and (missing := set(p.until.args) - written_fields(p.body)):
            raise ProgramError(f"the loop never writes {sorted(missing)}")
        if p.until.kind not in ("stable", "rounds", "change_below", "no_live", "none_match"):
            raise ProgramError(f"unknown end of loop {p.until.kind}")
        if p.until.kind == "none_match" and any(isinstance(n, A.Reduce) for n in walk(p.until.args[1])):
            raise ProgramError("the end of a loop looks at each vertex only")
        _check_loops(p.body, True)
