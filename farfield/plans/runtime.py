"""Drives programs: one job per pass of a loop, which writes the new state and tells whether it changed."""

from __future__ import annotations

import time
from dataclasses import dataclass, field

from pyspark.errors import AnalysisException
from pyspark.sql import Column, DataFrame, Observation
from pyspark.sql import functions as F

from farfield.lang import ast as A
from farfield.lang.check import check_program, hoist_two_hops, steps, walk, written_fields
from farfield.plans import blocks, machine
from farfield.plans.lower import LIVE, lower_step, lower_stop, with_condition, with_state, writes_of
from farfield.plans.store import drop, materialise
from farfield.sources.graph import Graph

#: Steps composed lazily before the state is written.
MAX_STEPS = 8
#: A loop without a limit that has not ended after so many passes is an error.
MOST_PASSES = 100_000
#: From so many vertices on, reads of a vertex by more than one in HOT_PART of all are split.
HOT_FROM, HOT_PART = 10_000_000, 1000


@dataclass
class Ledger:
    """What a run cost. supersteps are counted as the states of the program's machine are passed; iterations are the passes of each loop as it ended. With
    measure: exchanges in the plans of the jobs, messages as (kind, sent, receivers), and redundant, those that the shared sending
    states of loops sent when they ended and that nobody reads."""

    supersteps: int = 0
    jobs: int = 0
    iterations: list[int] = field(default_factory=list)
    converged: bool = True
    exchanges: int = 0
    seconds: float = 0.0
    messages: list[tuple[str, int, int]] = field(default_factory=list)
    redundant: int = 0


class Left(Exception):
    """A loop is left in the middle of a pass."""

    def __init__(self, state: DataFrame):
        self.state = state


@dataclass
class Result:
    """carried: the fields that the program names. Those that it does not name stay where they were, and are joined only where all of the state is asked for."""

    carried: DataFrame
    ledger: Ledger
    others: DataFrame | None = None

    @property
    def state(self) -> DataFrame:
        return self.carried if self.others is None else self.carried.join(self.others, "id")

    def select(self, *fields: str | Column) -> DataFrame:
        try:
            return self.carried.select("id", *fields)
        except AnalysisException:  # a field that the program does not name
            return self.state.select("id", *fields)


class Runtime:
    """merge: sequences are composed into one plan, else each part is written. fuse: the test rides on the job that writes a pass,
    else it is a job of its own. combine: messages are reduced before the shuffle. measure: count exchanges and messages, at the price of more
    jobs. reads, peephole, on_missing: see StepPlan. allow_two_hop: comprehensions may hold one over the neighbour's edges. buckets: state and edges are kept
    bucketed by id and by both ends, so that joins leave them where they are. hot: see StepPlan; if not given, loops over HOT_FROM vertices or more
    split from the second pass on, by the rows that the first one saw; the state read by pointers is then exchanged even if bucketed. The edges are written
    once, before the first step. blocks: if the graph names a column of blocks that no edge leaves, loops that `blocks` can run are run inside them, all passes in
    one job; not if merge, fuse, combine or measure are other than they are by themselves."""

    def __init__(self, graph: Graph, merge: bool = True, fuse: bool = True, combine: bool = True, functions: dict | None = None, measure: bool = False, reads: str = "planned",
                 peephole: bool = True, on_missing: str = "drop", allow_two_hop: bool = False, buckets: int | None = None, hot: int | None = None, blocks: bool = False):
        self.graph = with_state(graph)
        self.merge, self.fuse, self.measure, self.allow_two_hop, self.buckets = merge, fuse, measure, allow_two_hop, buckets
        self.blocks = blocks and merge and fuse and combine and not measure and graph.block is not None and graph.edges is not None
        self.options = {"combine": combine, "functions": functions, "reads": reads, "peephole": peephole, "on_missing": on_missing, "hot": hot}
        if measure:
            self.options["count"] = self._count
        self.ledger = Ledger()
        self.steps, self.depth = 0, 0
        self.paths: list[str] = []

    def _count(self, kind: str, messages: DataFrame) -> DataFrame:
        n = messages.agg(F.count(F.lit(1)).alias("sent"), F.countDistinct(messages.columns[0]).alias("receivers")).first()
        self.ledger.messages.append((kind, n["sent"], n["receivers"]))
        return messages

    def _write(self, s: DataFrame) -> DataFrame:
        if self.measure:
            self.ledger.exchanges += s._jdf.queryExecution().executedPlan().toString().count("Exchange hashpartitioning")
        self.ledger.jobs += 1
        self.steps = 0
        out, path = materialise(s, buckets=self.buckets)
        self.paths.append(path)
        if len(self.paths) > 2:  # older generations are read by nothing any more
            drop(s.sparkSession, self.paths.pop(0))
        return out

    def run(self, p: A.Program) -> Result:
        if self.allow_two_hop:
            p = hoist_two_hops(p)
        check_program(p, set(self.graph.vertices.columns))
        began = time.time()
        if any(isinstance(q, A.Repeat) for q in (p.parts if isinstance(p, A.Seq) else (p,))) and reads_edges(p):
            self.graph = self.graph.stored(self.buckets)
        s, others = self.graph.vertices, None
        loops = any(isinstance(q, A.Repeat) for q in (p.parts if isinstance(p, A.Seq) else (p,)))
        named = named_fields(p) | {"id", LIVE} | ({self.graph.block} if self.blocks else set())
        if loops and not named >= set(s.columns):
            others = s.select("id", *(c for c in s.columns if c not in named))
            s = s.select(*(c for c in s.columns if c in named))
        s = self._run(p, machine.build(p, self.options["reads"], self.options["peephole"]), s)
        self.ledger.seconds = time.time() - began
        return Result(s, self.ledger, others)

    def _run(self, p: A.Program, m: machine.Machine, s: DataFrame) -> DataFrame:
        if not isinstance(p, (A.Seq, A.Repeat)):
            self.ledger.supersteps += len(m.states)
        match p:
            case A.Seq(parts):
                for k, (q, of) in enumerate(zip(parts, m.parts)):
                    self.ledger.supersteps -= bool(k and self.merge)
                    s = self._run(q, of, s)
                    if not self.merge and not isinstance(q, (A.Repeat, A.Exit)):
                        s = self._write(s)
                return s
            case A.Step():
                if self.steps >= MAX_STEPS:
                    s = self._write(s)
                self.steps += 1
                return lower_step(self.graph, p, s, **self.options)
            case A.Stop():
                return lower_stop(self.graph, p, s, **self.options)
            case A.Exit(how, var, cond):
                seen = Observation()
                met = with_condition(self.graph, var, cond, s, "_met", **self.options)
                s = self._write(met.observe(seen, F.max(F.col("_met").cast("int")).alias("met")).drop("_met"))
                if bool(seen.get["met"]) == (how == "any"):
                    raise Left(s)
                return s
            case A.Repeat():
                return self._loop(p, m, s)
        raise TypeError(p)

    def _loop(self, p: A.Repeat, m: machine.Machine, s: DataFrame) -> DataFrame:
        until, body = p.until, m.parts[0]
        fields = until.args if until.kind == "stable" else until.args[:1] if until.kind == "change_below" else ()
        self.depth += 1
        old = {f: f"_old{self.depth}_{f}" for f in fields}
        if self.steps:
            s = self._write(s)
        self.ledger.supersteps += 2
        done = self._in_blocks(p, m, s) if self.blocks else None
        if done is not None:
            self.depth -= 1
            return done
        last = until.args[0] if until.kind == "rounds" else p.limit or MOST_PASSES
        for k in range(1, last + 1):
            for f, o in old.items():
                s = s.withColumn(o, F.col(f) if f in s.columns else F.lit(None))
            self.ledger.supersteps += machine.pass_overhead(m, self.merge, self.fuse)
            try:
                s = self._run(p.body, body, s)
            except Left as left:
                s = left.state.drop(*old.values())
                break
            metrics = [F.sum(F.col(LIVE).cast("int")).alias("live"), F.count(F.lit(1)).alias("rows")]
            if until.kind == "stable":
                changed = [~F.col(f).eqNullSafe(F.col(o)) for f, o in old.items()]
                any_ = changed[0]
                for c in changed[1:]:
                    any_ = any_ | c
                metrics.append(F.max(any_.cast("int")).alias("changed"))
            if until.kind == "change_below":
                metrics.append(F.max(F.abs(F.col(fields[0]) - F.col(old[fields[0]]))).alias("most"))
            extra = list(old.values())
            if until.kind == "none_match":
                s = with_condition(self.graph, *until.args, s, "_match", **self.options)
                metrics.append(F.max(F.col("_match").cast("int")).alias("match"))
                extra.append("_match")
            if self.fuse:
                seen = Observation()
                s = self._write(s.observe(seen, *metrics).drop(*extra))
                got = seen.get
            else:
                kept = self._write(s)
                got = kept.agg(*metrics).first().asDict()
                self.ledger.jobs += 1
                s = kept.drop(*extra)
            if self.options["hot"] is None and got["rows"] >= HOT_FROM:
                self.options["hot"] = got["rows"] // HOT_PART
            if (until.kind == "stable" and not got["changed"]) or (until.kind == "no_live" and not got["live"]) or (until.kind == "none_match" and not got["match"]):
                break
            if until.kind == "change_below" and (got["most"] is None or got["most"] < until.args[1]):
                break
        else:
            if until.kind != "rounds":
                self.ledger.converged = False
                if p.limit is None:
                    raise RuntimeError(f"the loop until {until.kind} has not ended after {last} passes")
        self.ledger.iterations.append(k)
        self.depth -= 1
        if self.measure and self.fuse and machine.can_fuse(m):
            self.ledger.redundant += self._unread(p.body, s)
        return s

    def _in_blocks(self, p: A.Repeat, m: machine.Machine, s: DataFrame) -> DataFrame | None:
        """s as the loop leaves it, or None if it can't run in blocks. The passes are those of the block that needs most: a block that is done does not change any more."""
        key, edges, writes = self.graph.block, self.graph.edges, blocks.supported(p, s)
        if writes is None or key not in s.columns or key not in edges.columns:
            return None
        self.ledger.jobs += 1
        out = blocks.in_blocks(p, writes, s, edges, key, self.graph.directed, MOST_PASSES)
        if out is None:
            return None
        seen = Observation()
        out = self._write(out.observe(seen, F.max("_passes").alias("passes"), F.max(F.col("_open").cast("int")).alias("open")).drop("_passes", "_open"))
        got = seen.get
        if got["open"]:
            return None
        k = max(got["passes"] or 1, 1)
        if k > MOST_PASSES:
            raise RuntimeError(f"the loop until {p.until.kind} has not ended after {MOST_PASSES} passes")
        self.ledger.supersteps += k * (machine.pass_overhead(m, self.merge, self.fuse) + len(m.parts[0].states))
        self.ledger.iterations.append(k)
        return out

    def _unread(self, body: A.Program, s: DataFrame) -> int:
        """Messages of the body's first sending state over the final state."""
        while isinstance(body, A.Seq):
            body = body.parts[0]
        if not isinstance(body, A.Step):
            return 0
        got: list[tuple[str, int]] = []

        def count(kind: str, messages: DataFrame) -> DataFrame:
            if kind.startswith(("round 1", "by ", "pointers")) or not any(k.startswith(("round", "by ", "pointers")) for k, _ in got) and kind.startswith("from "):
                got.append((kind, messages.count()))
            return messages

        lower_step(self.graph, body, s, **(self.options | {"count": count}))
        return sum(n for _, n in got)


def named_fields(p: A.Program) -> set[str]:
    """Fields that a program reads or writes, or that ends of its loops look at."""
    found = written_fields(p)

    def look(e: A.Node) -> None:
        found.update(n.field for n in walk(e) if isinstance(n, A.FieldAt))

    def go(q: A.Program) -> None:
        if isinstance(q, A.Seq):
            for x in q.parts:
                go(x)
        elif isinstance(q, A.Repeat):
            if q.until.kind in ("stable", "change_below"):
                found.update(x for x in q.until.args if isinstance(x, str))
            if q.until.kind == "none_match":
                look(q.until.args[1])
            go(q.body)
        elif isinstance(q, (A.Stop, A.Exit)):
            look(q.cond)
        else:
            for w in writes_of(q.block):
                for e in (w.guard, w.stmt.target, w.stmt.expr):
                    if e is not None:
                        look(e)

    go(p)
    return found


def reads_edges(p: A.Program) -> bool:
    return any(w.loop or any(isinstance(n, A.Reduce) for e in (w.guard, w.stmt.target, w.stmt.expr) if e is not None for n in walk(e)) for q in steps(p) if isinstance(q, A.Step) for w in writes_of(q.block))


def run(p: A.Program, graph: Graph, **flags) -> Result:
    return Runtime(graph, **flags).run(p)


def explain(p: A.Program, mode: str = "machine", graph: Graph | None = None) -> str:
    """reads: who sends what to whom in which round; machine: the states; spark: the plan of the program's steps, loops once."""
    m = machine.build(p)
    if mode == "machine":
        return machine.describe(m)
    if mode == "reads":
        def of(m):
            return ([m.reads.derivation()] if m.reads and m.reads.sends else []) + [x for q in m.parts for x in of(q)]
        return "\n--\n".join(of(m))
    once = lambda q: once(q.body) if isinstance(q, A.Repeat) else A.Seq(tuple(once(x) for x in q.parts if not isinstance(x, A.Exit))) if isinstance(q, A.Seq) else q
    rt = Runtime(graph)
    flat = once(p)
    return rt._run(flat, machine.build(flat), rt.graph.vertices)._jdf.queryExecution().toString()
