"""A step as one DataFrame plan: chain reads, neighbourhoods, local writes, remote writes."""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass, replace

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from farfield.lang import ast as A
from farfield.lang.check import children, walk
from farfield.plans.knowledge import Knows, plan_reads
from farfield.sources.graph import Graph

LIVE = "_live"
#: Readers of a vertex that very many read are dealt to so many tasks.
SALTS = 32

_EMPTY = {"total": 0, "count": 0, "any_": False, "all_": True, "product": 1}
_ACCUMULATED = {"min": "minimum", "max": "maximum", "+": "total", "*": "product", "or": "any_", "and": "all_"}


def fold(op: str, old: Column, new: Column) -> Column:
    """NULL is infinity: least skips it, greatest keeps it."""
    return {
        "=": lambda: new, "min": lambda: F.least(old, new), "max": lambda: F.when(old.isNotNull() & new.isNotNull(), F.greatest(old, new)),
        "+": lambda: old + new, "*": lambda: old * new, "or": lambda: truth(old) | truth(new), "and": lambda: truth(old) & truth(new),
    }[op]()


def aggregate(func: str, c: Column) -> Column:
    return {
        "minimum": F.min, "maximum": F.max, "total": F.sum, "count": lambda _: F.count(F.lit(1)), "any_": F.bool_or, "all_": F.bool_and, "product": lambda x: F.product(x).cast("long"), "argmin": F.min, "argmax": F.max,
    }[func](c)


def truth(c: Column) -> Column:
    return F.coalesce(c, F.lit(False))


def binary(op: str, a: Column, b: Column) -> Column:
    """Comparisons know that NULL is infinity."""
    less = lambda x, y: x.isNotNull() & (y.isNull() | (x < y))
    return {
        "+": lambda: a + b, "-": lambda: a - b, "*": lambda: a * b, "/": lambda: a / b, "<": lambda: truth(less(a, b)), ">": lambda: truth(less(b, a)),
        "<=": lambda: ~truth(less(b, a)), ">=": lambda: ~truth(less(a, b)), "==": lambda: a.eqNullSafe(b), "!=": lambda: ~a.eqNullSafe(b),
        "and": lambda: truth(a) & truth(b), "or": lambda: truth(a) | truth(b),
    }[op]()


def path_of(e: A.Node) -> tuple[A.Node, tuple[str, ...]] | None:
    """(root, fields innermost first) of a chain; id adds nothing."""
    fields: list[str] = []
    while isinstance(e, A.FieldAt):
        if e.field != "id":
            fields.append(LIVE if e.field == "Live" else e.field)
        e = e.index
    return e, tuple(reversed(fields))


def name_of(path: tuple[str, ...]) -> str:
    return "id" if not path else path[0] if len(path) == 1 else "_c_" + "__".join(path)


@dataclass(frozen=True)
class Write:
    guard: A.Node | None
    stmt: A.LocalSet | A.RemoteSet
    loop: A.ForEdge | None = None


def _substitute(e, env: dict):
    match e:
        case A.Var(n):
            return env.get(n, e)
        case A.FieldAt(f, i):
            return A.FieldAt(f, _substitute(i, env))
        case A.Bin(o, a, b):
            return A.Bin(o, _substitute(a, env), _substitute(b, env))
        case A.Un(o, a):
            return A.Un(o, _substitute(a, env))
        case A.IfExpr(c, a, b):
            return A.IfExpr(*(_substitute(x, env) for x in (c, a, b)))
        case A.Pair(a, b) | A.EdgePair(a, b):
            return type(e)(_substitute(a, env), _substitute(b, env))
        case A.Fst(a) | A.Snd(a) | A.Ref(a) | A.Val(a):
            return type(e)(_substitute(a, env))
        case A.Foreign(n, args):
            return A.Foreign(n, tuple(_substitute(a, env) for a in args))
        case A.Reduce(f, body, v, edges, filters):
            inner = {k: x for k, x in env.items() if k != v}
            return A.Reduce(f, _substitute(body, inner), v, edges, tuple(_substitute(c, inner) for c in filters))
    return e


def writes_of(block: tuple) -> list[Write]:
    """All writes with their guards; let names are replaced by what they stand for, as all reads see the snapshot."""
    out: list[Write] = []

    def go(block, guard, env, loop):
        env = dict(env)
        both = lambda g, c: c if g is None else A.Bin("and", g, c)
        for s in block:
            match s:
                case A.Let(n, e):
                    env[n] = _substitute(e, env)
                case A.LocalSet(f, t, op, e):
                    e = _substitute(e, env)
                    if loop is not None:  # accumulating over edges is a comprehension
                        e = A.Reduce(_ACCUMULATED[op], e, loop.var, loop.edges, () if guard is None else (guard,))
                        out.append(Write(None, A.LocalSet(f, t, op, e)))
                    else:
                        out.append(Write(guard, A.LocalSet(f, t, op, e)))
                case A.RemoteSet(f, t, op, e):
                    out.append(Write(guard, A.RemoteSet(f, _substitute(t, env), op, _substitute(e, env)), loop))
                case A.When(c, a, b):
                    c = _substitute(c, env)
                    go(a, both(guard, c), env, loop)
                    go(b, both(guard, A.Un("not", c)), env, loop)
                case A.ForEdge(v, edges, inner):
                    go(inner, guard, {k: x for k, x in env.items() if k != v}, s)

    go(block, None, {}, None)
    return out


class StepPlan:
    """Lowers one step over a graph. combine=False shuffles messages before any is reduced. reads: how chains are read, 'planned' by the messages of the
    read plan, 'request_reply' by asking vertex by vertex, 'doubling' by joins that double the length. peephole: a pointer that comes back is
    seen in one exchange. on_missing: what becomes of writes to vertices that are not there or have stopped, 'drop' or 'error'. count, if
    given, is called with the name and the rows of each kind of message and returns them. hot: readers of one vertex beyond so many rows are dealt to SALTS
    tasks, and what they read is sent to each; at most rows / hot vertices are so, and only their ids are broadcast."""

    def __init__(self, graph: Graph, var: str, writes: list[Write], combine: bool = True, functions: dict[str, Callable] | None = None, reads: str = "planned",
                 peephole: bool = True, on_missing: str = "drop", count: Callable[[str, DataFrame], DataFrame] | None = None, hot: int | None = None):
        self.graph, self.var, self.writes, self.combine, self.functions = graph, var, writes, combine, functions or {}
        self.reads, self.peephole, self.on_missing, self.count, self.hot = reads, peephole, on_missing, count or (lambda _, df: df), hot
        self.reduces: dict[A.Reduce, str] = {}
        self.computed: dict[A.Node, str] = {}

    def _roots(self) -> list[A.Node]:
        return [x for w in self.writes for x in (w.guard, w.stmt.target, w.stmt.expr) if x is not None]

    def paths(self) -> set[tuple[str, ...]]:
        """Chains of two fields or more that are read, at whatever vertex they start."""
        found = set()

        def visit(e: A.Node) -> None:
            if e in self.computed:
                return
            at, fields = path_of(e)
            if fields and isinstance(at, (A.Var, A.Ref)):
                if len(fields) > 1:
                    found.add(fields)
            for c in children(e) if at is e else [at]:
                visit(c)

        for root in self._roots():
            visit(root)
        return found

    def _meet(self, readers: DataFrame, at: str, spread: str, read: DataFrame, how: str, of: DataFrame | None = None) -> DataFrame:
        """readers joined with read, one row a `_k`, where `at` is `_k`. Readers of hot vertices, and those that read nowhere, are dealt by the column `spread`.
        of: what the readers are counted in, if it is cheaper to read than they are."""
        if self.hot is None:
            return readers.join(read, F.col(at) == F.col("_k"), how)
        hot = (readers if of is None else of).groupBy(F.col(at).alias("_hot")).agg(F.count(F.lit(1)).alias("_n")).filter((F.col("_n") > self.hot) & F.col("_hot").isNotNull()).select("_hot")
        dealt = F.pmod(F.xxhash64(spread), F.lit(SALTS)).cast("int")
        salted = readers.join(F.broadcast(hot), F.col(at) == F.col("_hot"), "left")
        salted = salted.withColumn("_salt", F.when(F.col("_hot").isNotNull() | F.col(at).isNull(), dealt).otherwise(0)).drop("_hot")
        each = F.when(F.col("_hot").isNotNull(), F.sequence(F.lit(0), F.lit(SALTS - 1))).otherwise(F.array(F.lit(0)))
        copies = read.join(F.broadcast(hot), F.col("_k") == F.col("_hot"), "left").withColumn("_to_salt", F.explode(each)).drop("_hot")
        return salted.join(copies, (F.col(at) == F.col("_k")) & (F.col("_salt") == F.col("_to_salt")), how).drop("_salt", "_to_salt")

    def _walk(self, e: A.Node):
        """The nodes of e that no column stands for yet."""
        if e not in self.computed:
            yield e
            for c in children(e):
                yield from self._walk(c)

    def with_mutual(self, s: DataFrame) -> DataFrame:
        """Whether the pointer of the vertex that u points to comes back, for each `F[F[u]] == u`. Pointers are sent to where they point, and only the one from
        the own target matters, so both are joined by (receiver, sender), however many point to a vertex."""
        here = A.Var(self.var)
        base = s
        for root in self._roots():
            for n in walk(root):
                match n:
                    case A.Bin("==", A.FieldAt(f, A.FieldAt(g, v)), other) if f == g and f not in ("id", "Live") and v == here and other in (here, A.FieldAt("id", here)) and n not in self.computed:
                        name = f"_m{len(self.computed)}"
                        mail = base.select(F.col(f).alias("_to"), F.col("id").alias("_whose")).filter("_to IS NOT NULL")
                        mail = self.count(f"pointers by {f}", mail).withColumn(name, F.lit(True))
                        s = s.join(mail, (F.col("id") == F.col("_to")) & (F.col(f) == F.col("_whose")), "left").drop("_to", "_whose").withColumn(name, F.coalesce(name, F.lit(False)))
                        self.computed[n] = name
        return s

    def with_chains(self, s: DataFrame) -> DataFrame:
        """Each chain as a column of every vertex."""
        paths = self.paths()
        if self.reads == "doubling" or all(len(p) < 3 for p in paths) and self.reads == "planned":
            return self._doubled(s)  # a plan of two fields is a request and a reply, which is one join
        return self._sent(s, sorted(paths))

    def _sent(self, s: DataFrame, paths: list[tuple[str, ...]]) -> DataFrame:
        """By the messages of the read plan, one join for each send: streams of (address, asker) meet the state at the address, and columns of
        (vertex, value) are what the current vertex has learned."""
        kept = s.columns
        streams: dict[tuple, DataFrame] = {(): s.select(F.col("id").alias("_at"), F.col("id").alias("_asker"))}
        columns: dict[tuple, DataFrame] = {}

        def column(p: tuple) -> DataFrame:
            return columns[p] if len(p) > 1 else s.select(F.col("id").alias("_k"), F.col(name_of(p)).alias("_v"))

        plans = [plan_reads([Knows((), p)], self.reads) for p in paths] if self.reads == "request_reply" else [plan_reads([Knows((), p) for p in paths], self.reads)]
        for plan in plans:
            for x in plan.sends:
                at, value = x.goal.at, x.goal.value
                if value == () and at not in streams:  # at(u) learns of u from those that know both
                    streams[at] = self.count(f"round {x.round}", self._meet(streams[x.via], "_at", "_asker", column(at[len(x.via) :]), "inner").filter("_v IS NOT NULL").select(F.col("_v").alias("_at"), "_asker"))
                elif value != () and value not in columns:
                    columns[value] = self.count(f"round {x.round}", self._meet(streams[x.via], "_at", "_asker", column(value[len(x.via) :]), "inner").filter("_v IS NOT NULL").select(F.col("_asker").alias("_k"), "_v"))
        for p in paths:
            s = s.join(columns[p].withColumnRenamed("_v", name_of(p)), F.col("id") == F.col("_k"), "left").drop("_k")
        return s.select(*kept, *map(name_of, paths))

    def _doubled(self, s: DataFrame) -> DataFrame:
        """A chain is split in the middle, so its joins grow with the logarithm of its length; chains that begin alike share the join."""
        need, todo = set(), [p for p in self.paths()]
        while todo:
            p = todo.pop()
            if len(p) > 1 and p not in need:
                need.add(p)
                k = (len(p) + 1) // 2
                todo += [p[:k], p[k:]]
        done: set = set()
        while need - done:
            ready = [p for p in need - done if all(len(q) < 2 or q in done for q in (p[: (len(p) + 1) // 2], p[(len(p) + 1) // 2 :]))]
            by_left: dict = {}
            for p in ready:
                k = (len(p) + 1) // 2
                by_left.setdefault(p[:k], []).append(p)
            base = s
            for left, some in sorted(by_left.items()):
                far = base.select(F.col("id").alias("_k"), *(F.col(name_of(p[len(left) :])).alias(name_of(p)) for p in sorted(some)))
                s = self.count(f"by {'.'.join(left)}", self._meet(s, name_of(left), "id", far, "left", base).drop("_k"))
            done |= set(ready)
        return s

    def edges(self, kind: str) -> DataFrame:
        """(rc, nb, val): receiver and neighbour."""
        ends = lambda rc, nb: (self.graph.by_dst if nb == "dst" and self.graph.by_dst is not None else self.graph.edges).select(F.col(rc).alias("_rc"), F.col(nb).alias("_nb"), F.col("val").alias("_val"))
        if kind == "Out":
            return ends("src", "dst")
        into = ends("dst", "src")
        return into.union(ends("src", "dst")) if kind == "Nbr" and self.graph.directed else into

    def column(self, e: A.Node, edge: str | None = None, own: str = "", far: str = "_n_") -> Column:
        """edge: the edge variable in scope; own and far prefix the columns of the current vertex and of the neighbour."""
        c = lambda x: self.column(x, edge, own, far)
        if e in self.reduces:
            return F.col(self.reduces[e])
        if e in self.computed:
            return F.col(self.computed[e])
        match e:
            case A.Lit(v):
                return F.lit(v).cast("long") if isinstance(v, int) and not isinstance(v, bool) else F.lit(v)
            case A.Inf():
                return F.lit(None)
            case A.Var(n) if n == self.var:
                return F.col(own + "id")
            case A.Var(n) if n == edge:
                return F.struct(F.col("_nb").alias("ref"), F.col("_val").alias("val"))
            case A.Ref(A.Var(n)) if n == edge:
                return F.col("_nb")
            case A.Val(A.Var(n)) if n == edge:
                return F.col("_val")
            case A.FieldAt():
                at, fields = path_of(e)
                if at == A.Var(self.var):
                    return F.col(own + name_of(fields))
                if isinstance(at, A.Ref) and at.arg == A.Var(edge or ""):
                    return F.col(far + name_of(fields)) if fields else F.col("_nb")
                if not fields:
                    return c(at)
                raise TypeError(f"{e} can't be read here")
            case A.Bin(op, a, b):
                return binary(op, c(a), c(b))
            case A.Un("not", a):
                return ~truth(c(a))
            case A.Un(_, a):
                return -c(a)
            case A.IfExpr(k, a, b):
                return F.when(truth(c(k)), c(a)).otherwise(c(b))
            case A.Pair(a, b):
                return F.struct(c(a).alias("_1"), c(b).alias("_2"))
            case A.EdgePair(a, b):
                return F.struct(c(a).alias("ref"), c(b).alias("val"))
            case A.Fst(a):
                return c(a)["_1"]
            case A.Snd(a):
                return c(a)["_2"]
            case A.Ref(a):
                return c(a)["ref"]
            case A.Val(a):
                return c(a)["val"]
            case A.Foreign(n, args):
                return self.functions[n](*map(c, args))
        raise TypeError(f"{e} can't be lowered")

    def _columns_at(self, exprs: list[A.Node], root: Callable[[A.Node], bool]) -> list[str]:
        got = []
        for e in exprs:
            for n in walk(e):
                if isinstance(n, A.FieldAt):
                    at, fields = path_of(n)
                    if root(at) and fields:
                        got.append(name_of(fields))
        return sorted(set(got))

    def with_reduces(self, s: DataFrame) -> DataFrame:
        """Comprehensions over the same edges with the same filters share one aggregation. Values move from neighbours along edges and are reduced
        before the shuffle; where receiver fields take part they are joined to the edges first."""
        groups: dict = {}
        for root in self._roots():
            for n in walk(root):
                if isinstance(n, A.Reduce):
                    groups.setdefault((n.edges.kind, n.var, n.filters), dict.fromkeys([]))[n] = None
        for k, ((kind, var, filters), some) in enumerate(sorted(groups.items(), key=lambda g: repr(g[0]))):
            exprs = [*filters, *(r.body for r in some)]
            m = self.edges(kind)
            far = self._columns_at(exprs, lambda at: isinstance(at, A.Ref))
            if far:
                m = m.join(s.select(F.col("id").alias("_j"), *(F.col(c).alias("_n_" + c) for c in far)), F.col("_nb") == F.col("_j")).drop("_j")
            own = self._columns_at(exprs, lambda at: at == A.Var(self.var))
            if own or any(n == A.Var(self.var) for e in exprs for n in walk(e)):
                m = m.join(s.select(F.col("id").alias("_o_id"), *(F.col(c).alias("_o_" + c) for c in own)), F.col("_rc") == F.col("_o_id"))
            for f in filters:
                m = m.filter(truth(self.column(f, var, "_o_")))
            names = {r: f"_r{k}_{i}" for i, r in enumerate(some)}
            values = self.count(f"from {kind}", m.select("_rc", *(self.column(r.body, var, "_o_").alias(n) for r, n in names.items())))
            if not self.combine:
                values = values.repartition("_rc")
            reduced = values.groupBy("_rc").agg(*(aggregate(r.func, F.col(n)).alias(n) for r, n in names.items()))
            s = s.join(reduced, F.col("id") == F.col("_rc"), "left").drop("_rc")
            for r, n in names.items():
                if r.func in _EMPTY:
                    s = s.withColumn(n, F.coalesce(n, F.lit(_EMPTY[r.func])))
            self.reduces.update(names)
        return s

    def with_computed(self, s: DataFrame) -> DataFrame:
        """Reads at an index that is itself computed: one more join each."""
        base, found = s, {}
        for root in self._roots():
            for n in self._walk(root):
                if isinstance(n, A.FieldAt) and n.field != "id":
                    at = n.index
                    while isinstance(at, A.FieldAt):
                        at = at.index
                    if not isinstance(at, (A.Var, A.Ref)) and not isinstance(n.index, A.FieldAt):
                        found[n] = f"_x{len(found)}"
        for n, name in found.items():
            far = base.select(F.col("id").alias("_k"), F.col(LIVE if n.field == "Live" else n.field).alias(name))
            s = self._meet(s.withColumn("_at", self.column(n.index)), "_at", "id", far, "left").drop("_k", "_at")
        self.computed.update(found)
        return s

    def run(self, s: DataFrame) -> DataFrame:
        kept = s.columns
        if self.peephole:
            s = self.with_mutual(s)
        s = self.with_computed(self.with_reduces(self.with_chains(s)))
        live = F.col(LIVE)
        on = lambda w, **k: live if w.guard is None else live & truth(self.column(w.guard, **k))
        new: dict[str, Column] = {}
        for w in self.writes:
            if isinstance(w.stmt, A.LocalSet):
                f = w.stmt.field
                old = new.get(f, F.col(f) if f in kept else F.lit(None))
                new[f] = F.when(on(w), fold(w.stmt.op, old, self.column(w.stmt.expr))).otherwise(old)
        sent: dict[tuple[str, str], list[DataFrame]] = {}
        for w in self.writes:
            if isinstance(w.stmt, A.RemoteSet):
                rows = s
                if w.loop is not None:
                    far = self._columns_at([x for x in (w.guard, w.stmt.target, w.stmt.expr) if x is not None], lambda at: isinstance(at, A.Ref))
                    e = self.edges(w.loop.edges.kind)
                    if far:
                        e = e.join(s.select(F.col("id").alias("_j"), *(F.col(c).alias("_n_" + c) for c in far)), F.col("_nb") == F.col("_j")).drop("_j")
                    rows = s.join(e, F.col("id") == F.col("_rc"))
                edge = w.loop.var if w.loop else None
                m = rows.filter(on(w, edge=edge)).select(self.column(w.stmt.target, edge).alias("_dst"), self.column(w.stmt.expr, edge).alias("_v"))
                sent.setdefault((w.stmt.field, w.stmt.op), []).append(m.filter("_dst IS NOT NULL"))
        out = s.select(*(c for c in kept if c not in new), *(c.alias(f) for f, c in new.items()))
        for (f, op), some in sent.items():
            m = some[0]
            for x in some[1:]:
                m = m.union(x)
            m = self.count(f"to {f}", m)
            if not self.combine:
                m = m.repartition("_dst")
            got = m.groupBy("_dst").agg(aggregate(_ACCUMULATED[op], F.col("_v")).alias("_v"))
            if self.on_missing == "error":
                out = out.join(got, F.col("id") == F.col("_dst"), "full_outer")
                lost = F.col("_dst").isNotNull() & ~truth(F.col(LIVE))
                out = out.withColumn("id", F.when(lost, F.raise_error(F.concat(F.lit(f"write to {f} of a vertex that is not there or has stopped: "), F.col("_dst").cast("string"))).cast("long")).otherwise(F.col("id")))
            else:
                out = out.join(got, F.col("id") == F.col("_dst"), "left")
            folded = F.col("_v") if f not in out.columns else fold(op, F.col(f), F.col("_v"))
            mine = F.col(f) if f in out.columns else F.lit(None)
            out = out.withColumn(f, F.when(F.col(LIVE) & F.col("_dst").isNotNull(), folded).otherwise(mine)).drop("_dst", "_v")
        return out


def lower_step(graph: Graph, step: A.Step, s: DataFrame, **options) -> DataFrame:
    return StepPlan(graph, step.var, writes_of(step.block), **options).run(s)


def with_condition(graph: Graph, var: str, cond: A.Node, s: DataFrame, name: str, **options) -> DataFrame:
    """s with whether each vertex that goes on meets a condition."""
    plan = StepPlan(graph, var, [Write(None, A.LocalSet(name, A.Var(var), "=", cond))], **options)
    read = plan.with_mutual(s) if plan.peephole else s
    read = plan.with_computed(plan.with_chains(read))
    return read.withColumn(name, F.col(LIVE) & truth(plan.column(cond))).select(*s.columns, name)


def lower_stop(graph: Graph, p: A.Stop, s: DataFrame, **options) -> DataFrame:
    return with_condition(graph, p.var, p.cond, s, "_gone", **options).withColumn(LIVE, F.col(LIVE) & ~F.col("_gone")).drop("_gone")


def with_state(graph: Graph) -> Graph:
    """The graph with the column that says which vertices go on."""
    return graph if LIVE in graph.vertices.columns else replace(graph, vertices=graph.vertices.withColumn(LIVE, F.lit(True)))
