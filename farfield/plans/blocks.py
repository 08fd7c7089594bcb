"""Loops inside blocks of vertices that no edge leaves: all passes over a block run in one task, without an exchange between passes."""

from __future__ import annotations

from dataclasses import dataclass
from functools import partial

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from farfield.lang import ast as A
from farfield.lang.check import walk
from farfield.plans.lower import LIVE, Write, name_of, path_of, writes_of
from farfield.plans.store import let_workers_import

#: Keys are dealt to so many bins, which are put together to blocks of about BLOCK rows. A graph with a block of more than MOST rows is left to the other way.
BINS, BLOCK, MOST = 4096, 100_000, 4_000_000

_COMPARE = {
    "<": lambda a, b: ~a.null & (b.null | (a.value < b.value)), ">": lambda a, b: ~b.null & (a.null | (b.value < a.value)),
    "<=": lambda a, b: ~(~b.null & (a.null | (b.value < a.value))), ">=": lambda a, b: ~(~a.null & (b.null | (a.value < b.value))),
    "==": lambda a, b: (a.null & b.null) | (~a.null & ~b.null & (a.value == b.value)), "!=": lambda a, b: ~((a.null & b.null) | (~a.null & ~b.null & (a.value == b.value))),
    "and": lambda a, b: a.truth & b.truth, "or": lambda a, b: a.truth | b.truth,
}
_REDUCE = {"minimum": (np.minimum, np.iinfo(np.int64).max), "maximum": (np.maximum, np.iinfo(np.int64).min)}


@dataclass
class Values:
    """A column: 64-bit integers or truths, and where it is NULL."""

    value: np.ndarray
    null: np.ndarray

    @property
    def truth(self) -> np.ndarray:
        return self.value & ~self.null

    def at(self, where: np.ndarray) -> "Values":
        return Values(self.value[where], self.null[where])


def choose(cond: np.ndarray, a: Values, b: Values) -> Values:
    return Values(np.where(cond, a.value, b.value), np.where(cond, a.null, b.null))


def least(a: Values, b: Values) -> Values:
    """NULL is infinity."""
    return choose(~a.null & (b.null | (a.value <= b.value)), a, b)


def supported(p: A.Repeat, s: DataFrame) -> list[Write] | None:
    """The writes of a loop that can run in blocks: one step, until the fields that it writes are stable, with integers and truths that are compared, read
    along chains and from neighbours, and written, locally or by remote least. Arithmetic is left to the other way, which knows overflow."""
    if p.until.kind != "stable" or p.limit is not None or not isinstance(p.body, A.Step):
        return None
    types, var, writes = {f.name: f.dataType for f in s.schema.fields}, p.body.var, writes_of(p.body.block)
    kinds = {T.LongType(): "number", T.BooleanType(): "truth"}

    def of(e: A.Node, edge: str | None = None) -> str | None:
        match e:
            case A.Lit(v):
                return "truth" if isinstance(v, bool) else "number" if isinstance(v, int) else None
            case A.Inf():
                return "number"
            case A.Var(n):
                return "number" if n == var else None
            case A.Ref(A.Var(n)):
                return "number" if n == edge else None
            case A.FieldAt():
                at, fields = path_of(e)
                if not (at == A.Var(var) or edge and at == A.Ref(A.Var(edge))) or any(types.get(f) != T.LongType() for f in fields[:-1]):
                    return None
                return kinds.get(types.get(fields[-1])) if fields else "number"
            case A.Bin(op, a, b) if op in _COMPARE:
                want = ("truth",) if op in ("and", "or") else ("number", "truth") if op in ("==", "!=") else ("number",)
                return "truth" if of(a, edge) in want and of(a, edge) == of(b, edge) else None
            case A.Un("not", a):
                return "truth" if of(a, edge) == "truth" else None
            case A.Reduce(func, body, name, _, filters) if edge is None and func in _REDUCE:
                return "number" if of(body, name) == "number" and all(of(x, name) == "truth" for x in filters) else None
        return None

    for w in writes:
        x = w.stmt
        local = isinstance(x, A.LocalSet)
        kind = kinds.get(types.get(x.field))
        if w.loop is not None or x.field not in p.until.args or kind is None or of(x.expr) != kind or w.guard is not None and of(w.guard) != "truth":
            return None
        if not (local and (x.op == "=" or x.op == "min" and kind == "number") or not local and x.op == "min" and kind == "number" and of(x.target) == "number"):
            return None
    return writes if writes and types["id"] == T.LongType() else None


class Block:
    """The vertices of a block in the order of their ids, and the edges inside. is_open: something points out of it."""

    def __init__(self, var: str, directed: bool, fields: dict[str, Values], src: np.ndarray, dst: np.ndarray):
        self.var, self.fields, self.n, self.is_open = var, fields, len(fields["id"].value), False
        ends = [self.find(Values(x, np.zeros(len(x), bool)))[0] for x in (src, dst)]
        into, out = (ends[1], ends[0]), (ends[0], ends[1])
        near = tuple(map(np.concatenate, zip(into, out))) if directed else into
        self.edges = {kind: self._by_receiver(*x) for kind, x in (("In", into), ("Out", out), ("Nbr", near))} if not self.is_open else {}

    def _by_receiver(self, rc: np.ndarray, nb: np.ndarray):
        order = np.argsort(rc, kind="stable")
        rc, nb = rc[order], nb[order]
        first = np.flatnonzero(np.diff(rc, prepend=-1))
        return rc, nb, first

    def find(self, x: Values) -> tuple[np.ndarray, np.ndarray]:
        """Places of ids, and which were found."""
        ids = self.fields["id"].value
        at = np.minimum(np.searchsorted(ids, x.value), max(self.n - 1, 0))
        found = ~x.null & (ids[at] == x.value) if self.n else np.zeros(len(at), bool)
        self.is_open |= bool((~x.null & ~found).any())
        return at, found

    def chain(self, fields: tuple[str, ...]) -> Values:
        got = self.fields[fields[0] if fields else "id"]
        for f in fields[1:]:
            at, found = self.find(got)
            got = self.fields[f].at(at)
            got = Values(got.value, got.null | ~found)
        return got

    def column(self, e: A.Node, edge: str | None = None, rc: np.ndarray | None = None, nb: np.ndarray | None = None) -> Values:
        """A value for each vertex, or for each edge if one is in scope."""
        here = lambda x: x if edge is None else x.at(rc)
        n = self.n if edge is None else len(rc)
        match e:
            case A.Lit(v):
                return Values(np.full(n, v, bool if isinstance(v, bool) else np.int64), np.zeros(n, bool))
            case A.Inf():
                return Values(np.zeros(n, np.int64), np.ones(n, bool))
            case A.Var():
                return here(self.fields["id"])
            case A.Ref():
                return self.fields["id"].at(nb)
            case A.FieldAt():
                at, fields = path_of(e)
                return self.chain(fields).at(nb) if isinstance(at, A.Ref) else here(self.chain(fields))
            case A.Bin(op, a, b):
                return Values(_COMPARE[op](self.column(a, edge, rc, nb), self.column(b, edge, rc, nb)), np.zeros(n, bool))
            case A.Un(_, a):
                return Values(~self.column(a, edge, rc, nb).truth, np.zeros(n, bool))
            case A.Reduce():
                return self.reduced(e)
        raise TypeError(f"{e} can't run in a block")

    def reduced(self, e: A.Reduce) -> Values:
        rc, nb, first = self.edges[e.edges.kind]
        out = Values(np.zeros(self.n, np.int64), np.ones(self.n, bool))
        if not len(rc):
            return out
        x = self.column(e.body, e.var, rc, nb)
        counts = ~x.null
        for f in e.filters:
            counts = counts & self.column(f, e.var, rc, nb).truth
        fold, nothing = _REDUCE[e.func]
        out.value[rc[first]] = fold.reduceat(np.where(counts, x.value, nothing), first)
        out.null[rc[first]] = ~np.logical_or.reduceat(counts, first)
        return out

    def step(self, writes: list[Write]) -> dict[str, Values]:
        """The fields that the step writes; all reads see those before it."""
        live, new, mail = self.fields[LIVE].truth, {}, []
        for w in writes:
            x = w.stmt
            on = live if w.guard is None else live & self.column(w.guard).truth
            value = self.column(x.expr)
            if isinstance(x, A.LocalSet):
                old = new.get(x.field, self.fields[x.field])
                new[x.field] = choose(on, value if x.op == "=" else least(old, value), old)
            else:
                to = self.column(x.target)
                at, found = self.find(Values(to.value, to.null | ~on))
                mail.append((x.field, at[found & ~value.null], value.value[found & ~value.null]))
        for f, at, value in mail:
            got = Values(np.full(self.n, np.iinfo(np.int64).max), np.ones(self.n, bool))
            np.minimum.at(got.value, at, value)
            got.null[at] = False
            old = new.get(f, self.fields[f])
            new[f] = choose(live, least(old, got), old)
        return new


def run_block(var: str, writes: list[Write], named: tuple[str, ...], directed: bool, most: int, columns: list[str], vertices: pa.Table, edges: pa.Table) -> pa.Table:
    """The vertices of a block as the loop leaves them, with its passes and whether the block is open; then what it holds means nothing."""
    vertices = vertices.select(columns).sort_by("id")

    def values(t: pa.Table, c: str) -> Values:
        x = t.column(c).combine_chunks()
        return Values(x.fill_null(False if pa.types.is_boolean(x.type) else 0).to_numpy(zero_copy_only=False), x.is_null().to_numpy(zero_copy_only=False))

    b = Block(var, directed, {c: values(vertices, c) for c in named}, values(edges, "src").value, values(edges, "dst").value)
    passes = 0
    while b.n and not b.is_open and passes <= most:
        passes += 1
        new = b.step(writes)
        changed = any(_COMPARE["!="](x, b.fields[f]).any() for f, x in new.items())
        b.fields.update(new)
        if not changed:
            break
    if not b.n:  # edges without a vertex
        vertices = pa.table({f.name: pa.nulls(1, f.type) for f in vertices.schema})
    for f in {w.stmt.field for w in writes} if b.n else ():
        k = vertices.column_names.index(f)
        vertices = vertices.set_column(k, vertices.schema.field(f), pa.array(b.fields[f].value, mask=b.fields[f].null))
    n = vertices.num_rows
    return vertices.append_column("_passes", pa.array(np.full(n, passes, np.int32))).append_column("_open", pa.array(np.full(n, b.is_open or not b.n)))


def dealt(df: DataFrame, key: str) -> DataFrame:
    return df.withColumn("_block", F.pmod(F.xxhash64(key), F.lit(BINS)).cast("int"))


def sizes(s: DataFrame, edges: DataFrame, key: str) -> list:
    """Bins with their vertices and edges, the most rows of one id, and rows without an id."""
    ids = dealt(s, key).groupBy("id").agg(F.count(F.lit(1)).alias("n"), F.min("_block").alias("_block"))
    v = ids.groupBy("_block").agg(F.sum("n").alias("n"), F.lit(0).cast("long").alias("e"), F.max("n").alias("most"), F.max(F.col("id").isNull().cast("int")).alias("none"))
    e = dealt(edges, key).groupBy("_block").agg(F.lit(0).cast("long").alias("n"), F.count(F.lit(1)).alias("e"), F.lit(1).cast("long").alias("most"), F.lit(0).alias("none"))
    return v.union(e).groupBy("_block").agg(F.sum("n").alias("n"), F.sum("e").alias("e"), F.max("most").alias("most"), F.max("none").alias("none")).collect()


def in_blocks(p: A.Repeat, writes: list[Write], s: DataFrame, edges: DataFrame, key: str, directed: bool, most: int) -> DataFrame | None:
    """s as the loop leaves it, with _passes and _open, or None if ids are not unique or a block is too large."""
    bins = sizes(s, edges, key)
    n = min(BINS, max(1, sum(r["n"] for r in bins) // BLOCK))
    rows: dict[int, int] = {}
    for r in bins:
        rows[r["_block"] % n] = rows.get(r["_block"] % n, 0) + max(r["n"], r["e"])
    if any(r["most"] > 1 or r["none"] for r in bins) or max(rows.values(), default=0) > MOST:
        return None
    let_workers_import(s.sparkSession)
    roots = [x for w in writes for x in (w.guard, w.stmt.target, w.stmt.expr) if x is not None]
    read = {name_of((f,)) for e in roots for x in walk(e) if isinstance(x, A.FieldAt) for f in path_of(x)[1]}
    named = tuple(sorted({"id", LIVE, *read, *(w.stmt.field for w in writes)}))
    kernel = partial(run_block, p.body.var, writes, named, directed, most, s.columns)
    blocks = [dealt(x, key).withColumn("_block", F.col("_block") % n) for x in (s, edges.filter("src IS NOT NULL AND dst IS NOT NULL"))]
    schema = T.StructType([*(T.StructField(f.name, f.dataType) for f in s.schema.fields), T.StructField("_passes", T.IntegerType()), T.StructField("_open", T.BooleanType())])
    return blocks[0].groupBy("_block").cogroup(blocks[1].select("src", "dst", "_block").groupBy("_block")).applyInArrow(kernel, schema)
