"""Programs as state machines, and what they cost in supersteps.

A step is a chain of states: one for each message round of its chain reads, a sending state for its neighbourhood (which shares the
last read round, if there is one), the main state, and one that receives remote writes. The first state of a program never looks at
messages, so the last state of one program and the first of the next can run in the same superstep. A loop whose body
begins with a sending state can send at the end of the initial state and of each pass, which takes one state and the separate test out of each
pass, at the price of one batch of messages that nobody reads.
"""

from __future__ import annotations

from dataclasses import dataclass, field

from farfield.lang import ast as A
from farfield.lang.check import children, walk
from farfield.plans.knowledge import Knows, ReadPlan, plan_reads
from farfield.plans.lower import path_of, writes_of


@dataclass
class State:
    kind: str  # read, send, main, update, flag, test, stop
    note: str = ""


@dataclass
class Machine:
    kind: str  # step, stop, seq, loop
    states: list[State] = field(default_factory=list)
    parts: list["Machine"] = field(default_factory=list)
    reads: ReadPlan | None = None
    until: A.Until | None = None

    def begins_with_send(self) -> bool:
        if self.kind == "step":
            return self.states[0].kind in ("read", "send")
        return bool(self.parts) and self.kind == "seq" and self.parts[0].begins_with_send()

    def assert_message_independent(self) -> None:
        """The first state takes nothing that others sent before."""
        first = self
        while first.kind in ("seq", "loop"):
            first = first.parts[0]
        assert first.states[0].kind in ("read", "send", "main", "stop", "test"), first.states[0]


def _is_mutual(n: A.Node, var: str) -> bool:
    here = A.Var(var)
    match n:
        case A.Bin("==", A.FieldAt(f, A.FieldAt(g, v)), other):
            return f == g and f not in ("id", "Live") and v == here and other in (here, A.FieldAt("id", here))
    return False


def step_machine(s: A.Step, strategy: str = "planned", peephole: bool = True) -> Machine:
    """peephole: a pointer that comes back takes one round, in which it is sent to where it points."""
    writes = writes_of(s.block)
    roots = [x for w in writes for x in (w.guard, w.stmt.target, w.stmt.expr) if x is not None]
    own, near, reduces, computed, mutual = set(), 0, False, False, 0

    def rest(n: A.Node):
        nonlocal mutual
        if peephole and _is_mutual(n, s.var):
            mutual = 1
            return
        yield n
        for c in children(n):
            yield from rest(c)

    for r in roots:
        for n in rest(r):
            if isinstance(n, A.Reduce):
                reduces = True
            if isinstance(n, A.FieldAt):
                at, fields = path_of(n)
                if at == A.Var(s.var):
                    own.add(fields)
                elif isinstance(at, A.Ref):
                    near = max(near, plan_reads([Knows((), fields)]).rounds)
                elif fields:
                    computed = True
    plan = plan_reads([Knows((), p) for p in sorted(own)], strategy)
    rounds = max(plan.rounds, near, 2 if computed else 0, mutual)
    loops = any(w.loop for w in writes)
    states = [State("read", f"round {k + 1}") for k in range(rounds)]
    if reduces or loops:
        if states and not near:
            states[-1].note += " and neighbours"
        else:
            states.append(State("send", "to neighbours"))
    states.append(State("main"))
    if any(isinstance(w.stmt, A.RemoteSet) for w in writes):
        states.append(State("update", "remote writes arrive"))
    return Machine("step", states, reads=plan)


def build(p: A.Program, strategy: str = "planned", peephole: bool = True) -> Machine:
    match p:
        case A.Step():
            return step_machine(p, strategy, peephole)
        case A.Stop(v, c) | A.Exit(_, v, c):
            reads = step_machine(A.Step(v, (A.LocalSet("Cond", A.Var(v), "=", c),)), strategy, peephole).states[:-1]
            return Machine("stop", [*reads, State("stop" if isinstance(p, A.Stop) else "test", "leaves the loop" if isinstance(p, A.Exit) else "")])
        case A.Seq(parts):
            return Machine("seq", parts=[build(q, strategy, peephole) for q in parts])
        case A.Repeat(body, until, _):
            return Machine("loop", parts=[build(body, strategy, peephole)], until=until)
    raise TypeError(p)


def can_fuse(m: Machine) -> bool:
    return m.kind == "loop" and m.parts[0].begins_with_send()


def states_of(m: Machine, merge: bool) -> int:
    """States of a program without loops."""
    if m.kind in ("step", "stop"):
        return len(m.states)
    return sum(states_of(q, merge) for q in m.parts) - (len(m.parts) - 1) * merge


def pass_overhead(m: Machine, merge: bool, fuse: bool) -> int:
    """What a pass of a loop takes beyond its body: the test, or less than nothing if the sending state is shared with the pass before."""
    if _loops(m.parts[0]):
        return 1 - merge
    return -1 if fuse and can_fuse(m) else 1


def supersteps(m: Machine, iterations: list[int], merge: bool = True, fuse: bool = True) -> int:
    """Supersteps of a run; iterations: passes of each loop as they were finished, inner loops before the outer pass that holds them."""
    left = list(iterations)

    def run(m: Machine) -> tuple[int, int]:
        """(supersteps, redundant message batches), taking finished loops from the left in the order in which they ran."""
        if m.kind in ("step", "stop"):
            return len(m.states), 0
        if m.kind == "seq":
            got = [run(q) for q in m.parts]
            return sum(g[0] for g in got) - (len(got) - 1) * merge, sum(g[1] for g in got)
        body = m.parts[0]
        inner = _loops(body)
        if not inner:
            k, n = left.pop(0), states_of(body, merge)
            return (2 + k * (n - 1), 1) if fuse and can_fuse(m) else (2 + k * (n + 1), 0)
        # an outer loop: its passes are those of its inner loops
        total, waste, k = 0, 0, 0
        passes = left.pop()  # outer loops finish last
        while k < passes:
            a, b = run(body)
            total, waste, k = total + a + 1 - merge, waste + b, k + 1
        return total + 2, waste

    return run(m)[0]


def _loops(m: Machine) -> int:
    return (m.kind == "loop") + sum(_loops(q) for q in m.parts)


def describe(m: Machine, pad: str = "") -> str:
    if m.kind == "loop":
        how = "fused" if can_fuse(m) else "general"
        return f"{pad}loop ({how}) until {m.until.kind}{m.until.args or ''}\n" + describe(m.parts[0], pad + "  ")
    if m.kind == "seq":
        return "".join(describe(q, pad) for q in m.parts)
    return "".join(f"{pad}{s.kind} {s.note}".rstrip() + "\n" for s in m.states)
