import random

import pytest

from farfield.algorithms import programs as P
from farfield.lang import dsl as L
from farfield.lang.dsl import F as V
from farfield.lang.dsl import In, Nbr, Out
from farfield.plans import blocks
from farfield.plans.runtime import run
from farfield.sources.graph import Graph

LOOP = L.repeat(L.step(lambda u: [L.local(V.D[u], Nbr[u].minimum(lambda e: V.D[e.ref]), "min")]), L.stable("D"))
PROGRAMS = {
    "hashmin": P.hashmin(),
    "components": P.components(),
    "stopped": L.step(lambda u: [L.local(V.D[u], V.id[u])]) >> L.stop(lambda u: V.id[u].eq(3) | V.id[u].eq(8)) >> LOOP,
    "infinite": L.step(lambda u: [L.local(V.D[u], L.either(V.id[u] < 12, L.inf, V.id[u]))]) >> LOOP,
    "in_filtered": L.step(lambda u: [L.local(V.D[u], V.id[u])])
    >> L.repeat(L.step(lambda u: [L.local(V.D[u], In[u].where(lambda e: V.Live[e.ref] & (e.ref > 4) & ~(V.D[e.ref].eq(7))).minimum(lambda e: V.D[e.ref]), "min")]), L.stable("D")),
    "out_greatest": L.step(lambda u: [L.local(V.D[u], V.id[u])])
    >> L.repeat(L.step(lambda u: [L.let("most", Out[u].maximum(lambda e: V.D[e.ref])), L.when(L.var("most").ne(L.inf) & (L.var("most") > V.D[u]), [L.local(V.D[u], L.var("most"))])]), L.stable("D")),
}


def blocked(spark, vertices, edges, directed):
    v = spark.createDataFrame(vertices, "id long, Home string")
    e = spark.createDataFrame(edges, "src long, dst long, Home string")
    return Graph.of(v, e, directed, block="Home")


def both_ways(g, p):
    """Rows and ledgers without blocks and with."""
    some = [run(p, g, blocks=x) for x in (False, True)]
    rows = [sorted((tuple(r) for r in x.select("D").collect()), key=repr) for x in some]
    return rows[0], rows[1], some[0].ledger, some[1].ledger


def random_blocks(seed):
    r = random.Random(seed)
    homes = [None, "a", "b", "c", "d"]
    ids = r.sample(range(60), 40)
    vertices = [(i, homes[i % 5]) for i in ids]
    edges = [(a, b, homes[a % 5]) for a, b in ((r.choice(ids), r.choice(ids)) for _ in range(250)) if a % 5 == b % 5]
    return vertices, r.sample(edges, min(len(edges), 30)) + [(None, ids[0], homes[ids[0] % 5])]


@pytest.mark.parametrize("name", PROGRAMS)
@pytest.mark.parametrize("directed", [False, True])
def test_loops_in_blocks_are_the_same(spark, monkeypatch, name, directed):
    monkeypatch.setattr(blocks, "BLOCK", 7)
    vertices, edges = random_blocks(len(name))
    g = blocked(spark, vertices, edges, directed)
    want, found, off, on = both_ways(g, PROGRAMS[name])
    assert found == want and on.iterations == off.iterations and on.supersteps == off.supersteps
    assert on.jobs == 3
    assert sorted(map(tuple, run(PROGRAMS[name], g, blocks=True).state.select("id", "Home").collect())) == sorted(vertices)


def test_many_passes_of_a_long_chain_are_one_job(spark):
    chains = [(k * 100 + i, f"h{k}") for k in range(3) for i in range(8 + 6 * k)]
    edges = [(a, a + 1, h) for a, h in chains if (a + 1, h) in chains]
    want, found, off, on = both_ways(blocked(spark, chains, edges, False), P.hashmin())
    assert found == want and {d for _, d in found} == {0, 100, 200}
    assert on.iterations == off.iterations == [20] and on.supersteps == off.supersteps
    assert (on.jobs, off.jobs) == (3, 21)


OPEN = {
    "crossing edge": ([(1, "a"), (2, "a"), (3, "b"), (4, "b")], [(1, 2, "a"), (2, 3, "a"), (3, 4, "b")]),
    "edge to nowhere": ([(1, "a"), (2, "a")], [(1, 2, "a"), (2, 99, "a")]),
    "edges of no vertex's block": ([(1, "a"), (2, "a")], [(1, 2, "z")]),
    "an id twice": ([(1, "a"), (2, "a"), (2, "b"), (3, "b")], [(1, 2, "a"), (2, 3, "b")]),
    "no id": ([(1, "a"), (None, "a"), (2, "a")], [(1, 2, "a")]),
}


@pytest.mark.parametrize("name", OPEN)
@pytest.mark.parametrize("program", ["hashmin", "components"])
def test_what_does_not_fit_blocks_runs_as_before(spark, monkeypatch, name, program):
    monkeypatch.setattr(blocks, "BLOCK", 1)
    want, found, off, on = both_ways(blocked(spark, *OPEN[name], False), PROGRAMS[program])
    assert found == want and on.iterations == off.iterations and on.supersteps == off.supersteps


def test_large_blocks_and_other_loops_run_as_before(spark, monkeypatch):
    g = blocked(spark, *random_blocks(5), False)
    for p, field in ((P.sssp(), "D"), (P.scc(), "Scc")):
        off, on = (run(p, g, blocks=x) for x in (False, True))
        assert sorted(map(tuple, on.state.select("id", field).collect()), key=repr) == sorted(map(tuple, off.state.select("id", field).collect()), key=repr)
        assert on.ledger.iterations == off.ledger.iterations
    monkeypatch.setattr(blocks, "MOST", 3)
    want, found, off, on = both_ways(g, P.hashmin())
    assert found == want and on.iterations == off.iterations and on.jobs > off.jobs


def test_no_vertices(spark):
    g = blocked(spark, [], [], False)
    want, found, off, on = both_ways(g, P.hashmin())
    assert found == want == [] and on.iterations == off.iterations and on.supersteps == off.supersteps


def test_iterations_by_diameter(spark):
    from farfield.queries import QUERIES

    d = "/root/testdata/sf0.001"
    rows = {(r["program"], r["graph"]): r for r in QUERIES["iterations_by_diameter"](spark, d).collect()}
    spark.read.parquet(f"{d}/events.parquet").createOrReplaceTempView("few_events")
    passes = spark.sql("""WITH p AS (SELECT user_id, event_id, row_number() OVER (PARTITION BY user_id ORDER BY ts, event_id) AS pos FROM few_events),
        f AS (SELECT user_id, min_by(pos, event_id) AS first_pos FROM p GROUP BY user_id) SELECT max(abs(pos - first_pos)) + 1 FROM p JOIN f USING (user_id)""").first()[0]
    flood = rows["hashmin", "user chains"]
    assert flood["passes"] == passes > 50 and flood["supersteps"] == passes + 2
    assert flood["jobs"] < 10  # one a pass before
    assert rows["components", "user chains"]["passes"] < 15 and rows["components", "event chain"]["jobs"] > rows["components", "event chain"]["passes"]
