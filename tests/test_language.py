import pytest

from farfield.algorithms import programs as P
from farfield.lang import ast as A
from farfield.lang.check import ProgramError, check_program
from farfield.lang.dsl import F, In, Nbr, Out, local, remote, repeat, stable, step, stop, when
from farfield.lang.text import parse, pretty
from farfield.plans import machine
from farfield.plans.knowledge import Knows, intermediaries, plan_reads, propositions

ALL = [P.sssp(), P.components(), P.hashmin(), P.list_rank(), P.roots(), P.pagerank(3), P.scc(), P.bipartite_matching(), P.weight_matching(), P.two_cycles()]


def test_round_table():
    rounds = [plan_reads([Knows((), ("D",) * d)]).rounds for d in range(1, 33)]
    assert rounds == [0, 2, 3, 3, *[4] * 4, *[5] * 8, *[6] * 16]
    mixed = [plan_reads([Knows((), tuple("ABCDEFGH"[:d]))]).rounds for d in range(1, 9)]
    assert mixed == rounds[:8]


def test_depth_four_takes_three_rounds_and_four_sends():
    plan = plan_reads([Knows((), ("D",) * 4)])
    assert (plan.rounds, len(plan.sends)) == (3, 4)
    assert [s.round for s in plan.sends] == [1, 2, 2, 3]
    assert plan_reads([Knows((), ("D",) * 4)], "request_reply").rounds == 6


def test_propositions_and_simplification():
    assert [propositions(("D",) * d) for d in (2, 4, 6)] == [5, 9, 13]
    assert Knows(("A",), ("A", "B")).stripped() == Knows((), ("B",))
    assert Knows(("A", "B"), ("A",)).stripped() == Knows(("B",), ())
    assert ("D", "E") not in intermediaries(Knows(("D", "E"), ()))


def plans_by_search(goal, depth):
    """Rounds by breadth-first search over what can be known, without restriction of the intermediaries."""
    paths = [("D",) * k for k in range(depth + 1)]
    known = {(at, v) for at in paths for v in paths if len(v) - len(at) in (0, 1) and len(at) <= len(v)}
    for r in range(20):
        if goal in known:
            return r
        known |= {(at, v) for w in paths for at in paths for v in paths if (w, v) in known and (w, at) in known}


@pytest.mark.parametrize("d", range(1, 7))
def test_planner_is_never_beaten(d):
    assert plans_by_search(((), ("D",) * d), d) == plan_reads([Knows((), ("D",) * d)]).rounds


def test_shared_chains_are_sent_once():
    a, b = Knows((), ("D", "D")), Knows((), ("D", "D", "D", "D"))
    assert len(plan_reads([a, b]).sends) == len(plan_reads([b]).sends)


@pytest.mark.parametrize("p", ALL)
def test_text_round_trip(p):
    q = parse(pretty(p))
    assert pretty(q) == pretty(p)
    check_program(q)


def test_ledger_formulas():
    for p, k, n in ((P.sssp(), 48, 2), (P.components(), 7, 4), (P.list_rank(), 25, 3)):
        m = machine.build(p)
        m.assert_message_independent()
        assert machine.supersteps(m, [k], True, True) == 2 + k * (n - 1)
        assert machine.supersteps(m, [k], False, False) == 3 + k * (n + 1)
    assert machine.can_fuse(machine.build(P.list_rank()).parts[1])
    assert "fused" in machine.describe(machine.build(P.components()))


@pytest.mark.parametrize(
    "bad",
    [
        step(lambda u: [local(F.D[F.D[u]], 1)]),
        step(lambda u: [A.RemoteSet("D", F.D[u], "=", A.Lit(1))]),
        step(lambda u: [remote(F.D[F.D[u]], "min", 1), remote(F.D[F.E[u]], "max", 1)]),
        step(lambda u: [local(F.id[u], 1)]),
        step(lambda u: [local(F.D[u], In[u].minimum(lambda e: Out[e.ref].minimum(lambda f: F.D[f.ref])))]),
        repeat(step(lambda u: [local(F.D[u], 1)]), stable("E")),
        stop(lambda u: In[u].count() > 0),
    ],
)
def test_checks_reject(bad):
    with pytest.raises(ProgramError):
        check_program(bad)


def test_unknown_field_and_profile():
    with pytest.raises(ProgramError):
        check_program(step(lambda u: [local(F.D[u], F.Nowhere[u])]), {"id"})
    with pytest.raises(ProgramError):
        check_program(P.components(), profile="neighbour_only")
    check_program(P.hashmin(), profile="neighbour_only")
    assert Nbr[A.Var("u")].kind == "Nbr" and when(True, []).then == ()
