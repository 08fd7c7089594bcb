"""Which vertex can know which value after how many message rounds, and how.

A path is a tuple of field names, innermost first: () is the current vertex u itself, ('D', 'E') is E[D[u]]. Knows(at, value) says
that, for all u, the vertex at(u) knows value(u). u knows itself and its own fields without a message. Any vertex w(u) that knows a value and an
address can send the one to the other, which takes one round after both are known. The planner looks for the fewest rounds over
intermediaries that are prefixes of the value or proper prefixes of the address, as a least fixed point: rounds are lowered until none
falls any more, so goals that lead back to themselves do no harm.
"""

from __future__ import annotations

from dataclasses import dataclass, field
from functools import lru_cache
from math import inf

Path = tuple[str, ...]


@dataclass(frozen=True)
class Knows:
    at: Path
    value: Path

    def stripped(self) -> "Knows":
        """The holder's own view, if holder and value share a beginning: what holds for all u holds for the vertices they share."""
        k = 0
        while k < min(len(self.at), len(self.value)) and self.at[k] == self.value[k]:
            k += 1
        return Knows(self.at[k:], self.value[k:]) if k == len(self.at) or k == len(self.value) else self


def prefixes(path: Path, proper: bool = False) -> list[Path]:
    return [path[:k] for k in range(len(path) + (not proper))]


def intermediaries(goal: Knows) -> list[Path]:
    return list(dict.fromkeys(prefixes(goal.value) + prefixes(goal.at, proper=True)))


def _known(goal: Knows) -> bool:
    return goal.at == () and len(goal.value) <= 1


@dataclass(frozen=True)
class Send:
    """via knows the value and the address and sends in this round; all relative to u."""

    goal: Knows
    via: Path
    round: int


@dataclass
class ReadPlan:
    goals: list[Knows]
    rounds: int
    sends: list[Send] = field(default_factory=list)
    strategy: str = "planned"

    def derivation(self) -> str:
        name = lambda p: "u" if not p else "".join(f"{f}[" for f in reversed(p)) + "u" + "]" * len(p)
        return "\n".join(f"round {s.round}: {name(s.via)} sends {name(s.goal.value)} to {name(s.goal.at)}" for s in self.sends)


@lru_cache(4096)
def _solve(goals: tuple[Knows, ...]) -> tuple[dict[Knows, float], dict[Knows, Path]]:
    """Fewest rounds of each proposition that can matter, and the intermediary; ties by fewer sends, then by a shorter holder."""
    seen, todo = set(), [g.stripped() for g in goals]
    while todo:
        g = todo.pop()
        if g in seen:
            continue
        seen.add(g)
        if not _known(g):
            todo += [x.stripped() for w in intermediaries(g) for x in (Knows(w, g.value), Knows(w, g.at))]
    cost: dict[Knows, tuple[float, float]] = {g: (0, 0) if _known(g) else (inf, inf) for g in seen}
    via: dict[Knows, Path] = {}
    changed = True
    while changed:
        changed = False
        for g in sorted(seen, key=lambda x: (len(x.at) + len(x.value), x.at, x.value)):
            if _known(g):
                continue
            for w in intermediaries(g):
                a, b = cost[Knows(w, g.value).stripped()], cost[Knows(w, g.at).stripped()]
                new = (1 + max(a[0], b[0]), 1 + a[1] + b[1])
                if new < cost[g]:
                    cost[g], via[g], changed = new, w, True
    return {g: c[0] for g, c in cost.items()}, via


def plan_reads(goals: list[Knows], strategy: str = "planned") -> ReadPlan:
    """A plan that brings all goals about; shared parts are sent once. 'request_reply' asks vertex by vertex instead."""
    if strategy == "request_reply":
        deepest = max((len(g.value) for g in goals), default=0)
        sends, path = [], max((g.value for g in goals), key=len, default=())
        for d in range(2, deepest + 1):
            sends += [Send(Knows(path[: d - 1], ()), (), 2 * (d - 2) + 1), Send(Knows((), path[:d]), path[: d - 1], 2 * (d - 2) + 2)]
        return ReadPlan(goals, 2 * max(0, deepest - 1), sends, strategy)
    rounds, via = _solve(tuple(goals))
    sends: dict[Knows, Send] = {}

    def bring(g: Knows) -> None:
        g = g.stripped()
        if _known(g) or g in sends:
            return
        w = via[g]
        bring(Knows(w, g.value))
        bring(Knows(w, g.at))
        sends[g] = Send(g, w, int(rounds[g]))

    for g in goals:
        bring(g)
    return ReadPlan(goals, int(max((rounds[g.stripped()] for g in goals), default=0)), sorted(sends.values(), key=lambda s: (s.round, s.goal.at, s.goal.value)))


def chain_rounds(path: Path) -> int:
    return plan_reads([Knows((), path)]).rounds


def propositions(path: Path) -> int:
    return len(_solve((Knows((), path),))[0])
