import random

import pytest
from hypothesis import HealthCheck, given, settings
from hypothesis import strategies as st
from pyspark.sql import functions as F

from farfield.algorithms import programs as P
from farfield.algorithms import run as R
from farfield.baselines import exact, handwritten
from farfield.lang import dsl as L
from farfield.lang.dsl import F as V
from farfield.lang.check import ProgramError
from farfield.lang.interp import INF, Interpreter, LocalGraph
from farfield.lang.text import parse, pretty
from farfield.operators import relational as O
from farfield.plans import machine
from farfield.plans.runtime import run
from farfield.sources.graph import Graph


def graph(spark, ids, edges, directed=True):
    v = spark.createDataFrame([(i,) for i in ids], "id long")
    e = spark.createDataFrame([(a, b, w) for a, b, w in edges], "src long, dst long, val long")
    return Graph.of(v, e, directed)


def got(df, *cols):
    return {r[0]: r[1] if len(cols) == 1 else tuple(r[1:]) for r in df.select("id", *cols).collect()}


def random_edges(seed, n, m):
    r = random.Random(seed)
    return list({(a, b): (a, b, r.randint(1, 9)) for a, b in ((r.randrange(n), r.randrange(n)) for _ in range(m)) if a != b}.values())


SMALL = {"path": (range(5), [(i, i + 1, 1) for i in range(4)]), "star": (range(6), [(5, i, 1) for i in range(5)]), "isolated": (range(3), [(0, 1, 1)]), "random": (range(20), random_edges(3, 20, 22))}


@pytest.mark.parametrize("name", SMALL)
def test_components(spark, name):
    ids, edges = SMALL[name]
    want = exact.components(ids, [(a, b) for a, b, _ in edges])
    g = graph(spark, ids, edges, False)
    assert got(R.components(g).state, "D") == want == got(R.hashmin(g).state, "D") == got(handwritten.components(g), "comp")


def test_flags_agree_and_ledger_counts(spark):
    ids, edges = SMALL["random"]
    g = graph(spark, ids, edges, False)
    runs = [R.components(g, merge=m, fuse=f, combine=c) for m, f, c in ((True, True, True), (False, True, True), (True, False, False), (False, False, True))]
    assert len({tuple(sorted(got(r.state, "D").items())) for r in runs}) == 1
    assert len({r.ledger.iterations[0] for r in runs}) == 1
    k = runs[0].ledger.iterations[0]
    assert runs[0].ledger.supersteps == 2 + 3 * k < runs[3].ledger.supersteps == 3 + 5 * k
    assert runs[0].ledger.jobs < runs[3].ledger.jobs


def test_sssp(spark):
    ids, edges = range(15), random_edges(5, 15, 40)
    want = exact.distances(ids, edges, 0)
    g = graph(spark, ids, edges)
    assert got(R.sssp(g).state, "D") == want == got(R.sssp(g, active=False).state, "D") == got(handwritten.sssp(g), "dist")
    assert got(R.sssp(g, unit=True).state, "D") == exact.distances(ids, [(a, b, 1) for a, b, _ in edges], 0)


def test_list_rank_and_invariant(spark):
    pred = {0: 0, 1: 0, 2: 1, 3: 2, 4: 3, 10: 10, 11: 10}
    val = {i: 0 if pred[i] == i else i * i for i in pred}
    g = Graph(spark.createDataFrame([(i, val[i], pred[i]) for i in pred], "id long, Val long, Pred long"))
    want = exact.ranks(pred, val)
    assert got(R.list_rank(g).state, "Sum") == want == got(handwritten.list_rank(g), "rank")
    assert got(R.list_rank(g, val=1).state, "Sum")[4] == 4


def test_scc(spark):
    for seed in (1, 2):
        ids, edges = range(14), random_edges(seed, 14, 22)
        want = exact.strong_components(ids, [(a, b) for a, b, _ in edges])
        g = graph(spark, ids, edges)
        assert got(R.scc(g).state, "Scc") == want == got(handwritten.scc(g), "scc")


def test_msf(spark):
    for edges in (random_edges(7, 16, 40), [(0, 1, 1), (1, 2, 1), (2, 3, 1), (0, 3, 1)]):
        once = list({(min(a, b), max(a, b)): (min(a, b), max(a, b), w) for a, b, w in edges}.values())
        g = graph(spark, range(16), once, False)
        want = exact.forest(range(16), once)
        for df in (R.msf(g), R.msf(g, peephole=False), handwritten.msf(g)):
            assert {tuple(r) for r in df.collect()} == want


def test_matchings(spark):
    edges = [(a, 100 + b, 1) for a, b in {(random.Random(9 * i).randrange(8), random.Random(7 * i + 1).randrange(8)) for i in range(30)}]
    g = graph(spark, [*range(8), *range(100, 108)], edges, False)
    g = Graph(g.vertices.withColumn("Side", (F.col("id") >= 100).cast("int")), g.edges, False)
    m = [tuple(r) for r in R.bipartite_matching(g).collect()]
    left, right = {a for a, _ in m}, {b for _, b in m}
    assert len(left) == len(right) == len(m) and set(m) <= {(a, b) for a, b, _ in edges}
    assert all(a in left or b in right for a, b, _ in edges)
    once = list({(min(a, b), max(a, b)): (min(a, b), max(a, b), w) for a, b, w in random_edges(11, 12, 30)}.values())
    m = [tuple(r) for r in R.weight_matching(graph(spark, range(12), once, False)).collect()]
    ends = [x for a, b, _ in m for x in (a, b)]
    assert len(ends) == len(set(ends)) and all(a in ends or b in ends for a, b, _ in once)
    greedy, used = 0, set()
    for a, b, w in sorted(once, key=lambda e: (-e[2], e[0], e[1])):
        if a not in used and b not in used:
            greedy, used = greedy + w, used | {a, b}
    assert sum(w for _, _, w in m) == greedy


def test_pagerank(spark):
    g = graph(spark, range(4), [(0, 1, 1), (1, 2, 1), (2, 0, 1), (3, 0, 1)])
    a, b = got(R.pagerank(g, 15).state, "Rank"), got(handwritten.pagerank(g, 15), "rank")
    assert all(abs(a[i] - b[i]) < 1e-12 for i in a) and abs(sum(a.values()) - 1) < 1e-9
    d = got(R.pagerank(graph(spark, range(3), [(0, 1, 1), (1, 2, 1)]), 10, dangling="redistribute").state, "Rank")
    assert abs(sum(d.values()) - 1) < 1e-9
    assert R.pagerank(g, 50, eps=0.05).ledger.iterations[0] < 50


def test_preorder_and_roots(spark):
    parent = {0: 0, 1: 0, 2: 0, 3: 1, 4: 1, 7: 7, 8: 7}
    g = Graph(spark.createDataFrame(list(parent.items()), "id long, Parent long"))
    assert got(R.preorder(g), "pre") == {0: 0, 1: 1, 3: 2, 4: 3, 2: 4, 7: 5, 8: 6}
    assert got(R.roots(g).state, "Root", "Depth") == {0: (0, 0), 1: (0, 1), 2: (0, 1), 3: (0, 2), 4: (0, 2), 7: (7, 0), 8: (7, 1)}


def test_stopped_is_frozen_but_read(spark):
    g = Graph(spark.createDataFrame([(0, 0, 5), (1, 0, 7)], "id long, P long, X long"))
    p = L.stop(lambda u: V.id[u].eq(0)) >> L.step(lambda u: [L.local(V.X[u], V.X[V.P[u]] + 1), L.remote(V.X[V.P[u]], "max", 99)])
    assert got(run(p, g).state, "X") == {0: 5, 1: 6}


def test_reads_see_the_snapshot(spark):
    g = Graph(spark.createDataFrame([(0, 1, 5), (1, 0, 7)], "id long, P long, X long"))
    p = L.step(lambda u: [L.local(V.X[u], 100), L.local(V.Y[u], V.X[u]), L.local(V.Z[u], V.X[V.P[u]])])
    assert got(run(p, g).state, "X", "Y", "Z") == {0: (100, 5, 7), 1: (100, 7, 5)}


def test_do_until_runs_once(spark):
    g = Graph(spark.createDataFrame([(0, 1)], "id long, D long"))
    assert run(L.repeat(L.step(lambda u: [L.local(V.D[u], V.D[u])]), L.stable("D")), g).ledger.iterations == [1]


@settings(max_examples=6, deadline=None, suppress_health_check=[HealthCheck.function_scoped_fixture])
@given(st.lists(st.integers(0, 7), min_size=8, max_size=8), st.integers(2, 5), st.sampled_from(["min", "max", "+"]))
def test_engine_is_the_interpreter(spark, pointers, depth, op):
    """Chains of any depth over random functional graphs, with branches, neighbours and remote writes."""
    at = lambda u: V.D[at_(u, depth - 1)]
    p = L.step(lambda u: [
        L.local(V.Value[u], at(u)),
        L.let("near", L.In[u].where(lambda e: V.D[e.ref] > V.id[u]).minimum(lambda e: V.D[V.D[e.ref]] + e.val)),
        L.when(L.var("near") < V.D[u], [L.remote(V.X[V.D[u]], op, V.id[u] + 1)], [L.local(V.X[u], V.X[u] + V.X[V.D[u]])]),
    ])
    edges = [(i, d, i + 1) for i, d in enumerate(pointers) if i != d]
    v = spark.createDataFrame([(i, d, 10 * i) for i, d in enumerate(pointers)], "id long, D long, X long")
    mine = got(run(p, Graph.of(v, spark.createDataFrame(edges or [(0, 0, 1)], "src long, dst long, val long").limit(len(edges)))).state, "Value", "X")
    local = Interpreter(LocalGraph({i: {"D": d, "X": 10 * i} for i, d in enumerate(pointers)}, edges)).run(p)
    assert mine == {i: tuple(None if f[k] == INF else f[k] for k in ("Value", "X")) for i, f in local.v.items()}


def at_(u, k):
    for _ in range(k):
        u = V.D[u]
    return u


@pytest.mark.parametrize("p", [P.components(), P.hashmin(), P.sssp()])
def test_interpreter_runs_the_programs(p):
    ids, edges = SMALL["random"]
    i = Interpreter(LocalGraph({k: {} for k in ids}, edges, directed=False))
    out = {k: f["D"] for k, f in i.run(p).v.items()}
    want = exact.components(ids, [(a, b) for a, b, _ in edges]) if p != P.sssp() else {k: INF if d is None else d for k, d in exact.distances(ids, [*edges, *((b, a, w) for a, b, w in edges)], 0).items()}
    assert out == want


def test_operators(spark):
    g = graph(spark, range(5), [(0, 1, 1), (1, 2, 1), (0, 2, 1), (2, 3, 1)], False)
    assert got(O.triangles(g), "triangles") == {0: 1, 1: 1, 2: 1}
    assert g.validate().first().asDict() == {"repeated_ids": 0, "dangling_ends": 0, "self_loops": 0, "repeated_edges": 0, "unmirrored_edges": 0}
    a = spark.createDataFrame([(0, 5), (1, 12)], "a long, ta long")
    b = spark.createDataFrame([(0, 5), (1, 15), (2, 16)], "b long, tb long")
    assert {tuple(r) for r in O.range_join(a, b, "ta", "tb", 10).select("a", "b").collect()} == {(0, 0), (0, 1), (1, 1), (1, 2)}
    l = spark.createDataFrame([(1, 10), (1, 4), (2, 9)], "k long, t long")
    r = spark.createDataFrame([(1, 5, "x"), (1, 10, "y"), (2, 11, "z")], "k long, t long, v string")
    assert {tuple(x) for x in O.as_of_join(l, r, "k", "t", "v").select("k", "t", "as_of").collect()} == {(1, 10, "y"), (1, 4, None), (2, 9, None)}


def test_read_and_write(spark, tmp_path):
    (tmp_path / "e.txt").write_text("# edges\n1 2\n2 3 7\n")
    g = Graph.read(spark, str(tmp_path / "e.txt"), "text")
    assert {tuple(r) for r in g.edges.collect()} == {(1, 2, 1), (2, 3, 7)}
    for kind in ("parquet", "csv", "json", "orc"):
        g.write(str(tmp_path / kind), kind)
        assert Graph.read(spark, f"{tmp_path}/{kind}/edges", kind).edges.count() == 2
    g.create_views("t")
    assert spark.sql("SELECT count(*) FROM t_edges").first()[0] == 2


def test_msf_is_a_program(spark):
    for edges in (random_edges(7, 16, 40), random_edges(8, 16, 12), [(0, 1, 1), (1, 2, 1), (2, 3, 1), (0, 3, 1)]):
        once = list({(min(a, b), max(a, b)): (min(a, b), max(a, b), w) for a, b, w in edges}.values())
        g = graph(spark, range(16), once, False)
        for flags in ({}, {"peephole": False}, {"merge": False, "fuse": False}):
            assert {tuple(r) for r in R.msf_program(g, **flags).collect()} == exact.forest(range(16), once)


def test_scc_leaves_early(spark):
    ids, edges = range(14), random_edges(2, 14, 22)
    want = exact.strong_components(ids, [(a, b) for a, b, _ in edges])
    early, late = (R.scc(graph(spark, ids, edges), early=x) for x in (True, False))
    assert got(early.state, "Scc") == want == got(late.state, "Scc")
    assert early.ledger.supersteps < late.ledger.supersteps and len(early.ledger.iterations) == len(late.ledger.iterations) - 2


@pytest.mark.parametrize("reads", ["planned", "request_reply", "doubling"])
def test_ways_to_read_chains(spark, reads):
    """Chains of each length and of mixed fields, some of which end at no vertex, as the interpreter reads them."""
    r = random.Random(4)
    rows = [(i, r.randrange(12) if i % 5 else None, r.randrange(14), 10 * i) for i in range(12)]
    at = lambda u, path: u if not path else getattr(V, path[-1])[at(u, path[:-1])]
    paths = [("D",) * k for k in range(2, 9)] + [("D", "E", "X"), ("E", "D", "E", "X"), ("E", "E", "D", "X")]
    p = L.step(lambda u: [L.local(getattr(V, f"Out{k}")[u], at(u, path)) for k, path in enumerate(paths)])
    mine = run(p, Graph(spark.createDataFrame(rows, "id long, D long, E long, X long")), reads=reads).state
    local = Interpreter(LocalGraph({i: {"D": INF if d is None else d, "E": e, "X": x} for i, d, e, x in rows}, [])).run(p)
    names = [f"Out{k}" for k in range(len(paths))]
    assert got(mine, *names) == {i: tuple(None if f[n] == INF else f[n] for n in names) for i, f in local.v.items()}


@pytest.mark.parametrize("reads", ["planned", "doubling"])
def test_hot_vertices_are_read_by_many_tasks(spark, reads):
    """All but two vertices point to one, some nowhere; splitting its readers changes no value."""
    rows = [(i, 3 if i % 4 else None, (i + 1) % 30, 10 * i) for i in range(40)]
    g = Graph(spark.createDataFrame(rows, "id long, D long, E long, X long"))
    p = L.step(lambda u: [L.local(V.A[u], V.D[V.D[u]]), L.local(V.B[u], V.X[V.E[V.D[u]]]), L.local(V.C[u], V.X[V.D[u] + 1])])
    plain, split = (run(p, g, reads=reads, hot=n).state for n in (None, 5))
    assert got(plain, "A", "B", "C") == got(split, "A", "B", "C") == {i: (None if d is None else 3, None if d is None else 40, None if d is None else 40) for i, d, _, _ in rows}
    plans = [x._jdf.queryExecution().optimizedPlan().toString() for x in (plain, split)]
    assert "_salt" not in plans[0] and "_salt" in plans[1]


def test_hot_roots_of_components(spark, monkeypatch):
    from farfield.plans import runtime

    edges = [(5, i, 1) for i in range(30) if i != 5] + [(40, 41, 1)]
    g = graph(spark, range(43), edges, False)
    want = exact.components(range(43), [(a, b) for a, b, _ in edges])
    monkeypatch.setattr(runtime, "HOT_FROM", 10)  # from the second pass on, without being asked to
    monkeypatch.setattr(runtime, "HOT_PART", 10)
    rt = runtime.Runtime(g)
    assert got(rt.run(P.components()).state, "D") == want and rt.options["hot"] == 4


def test_none_match_exit_and_limit(spark):
    g = Graph(spark.createDataFrame([(i, i) for i in range(5)], "id long, X long"))
    count = L.step(lambda u: [L.local(V.X[u], V.X[u] + 1)])
    assert run(L.repeat(count, L.none_match(lambda u: V.X[u] < 7)), g).ledger.iterations == [7]
    assert run(L.repeat(count >> L.exit_when("any", lambda u: V.X[u] > 9) >> count, L.rounds(50)), g).ledger.iterations == [4]
    capped = run(L.repeat(count, L.none_match(lambda u: V.X[u] < 7), 3), g)
    assert capped.ledger.iterations == [3] and not capped.ledger.converged
    text = pretty(L.repeat(count >> L.exit_when("any", lambda u: V.X[u] > 9), L.none_match(lambda u: V.X[u] < 7)))
    assert pretty(parse(text)) == text
    for p in (L.repeat(count, L.none_match(lambda u: V.X[u] < 7)), L.repeat(count >> L.exit_when("any", lambda u: V.X[u] > 9) >> count, L.rounds(50))):
        i = Interpreter(LocalGraph({k: {"X": k} for k in range(5)}, []))
        assert {k: f["X"] for k, f in i.run(p).v.items()} == got(run(p, g).state, "X")


def test_writes_to_what_is_not_there(spark):
    g = Graph(spark.createDataFrame([(0, 1, 5), (1, 9, 7)], "id long, P long, X long"))
    p = L.step(lambda u: [L.remote(V.X[V.P[u]], "max", 99)])
    assert got(run(p, g).state, "X") == {0: 5, 1: 99}
    with pytest.raises(Exception, match="not there or has stopped"):
        run(p, g, on_missing="error").state.collect()
    stopped = L.stop(lambda u: V.id[u].eq(1)) >> p
    assert got(run(stopped, g).state, "X") == {0: 5, 1: 7}
    with pytest.raises(Exception, match="not there or has stopped"):
        run(stopped, g, on_missing="error").state.collect()


def test_two_hops(spark):
    edges = [(0, 1, 1), (1, 2, 5), (1, 3, 7), (0, 2, 1), (2, 3, 2)]
    p = L.step(lambda u: [L.local(V.X[u], L.Out[u].total(lambda e: L.Out[e.ref].maximum(lambda f: f.val, "f"), "e"))])
    with pytest.raises(ProgramError):
        run(p, graph(spark, range(4), edges))
    assert got(run(p, graph(spark, range(4), edges), allow_two_hop=True).state, "X") == {0: 9, 1: 2, 2: 0, 3: 0}


def test_edges_are_derived_once(spark):
    """However many passes a loop has, what the edges come from is read once, and buckets take exchanges away."""
    seen = spark.sparkContext.accumulator(0)

    def mark(batches):
        for b in batches:
            seen.add(b.num_rows)
            yield b

    edges = spark.range(40).selectExpr("id AS src", "id + 1 AS dst", "1L AS val").mapInArrow(mark, "src long, dst long, val long")
    g = Graph(spark.range(41).select("id"), edges)
    r = run(P.pagerank(6), Graph(g.vertices.selectExpr("id", "1.0D AS Rank", "1L AS Deg", "0.1D AS Base"), edges))
    assert r.ledger.iterations == [6] and seen.value == 40
    before = spark.conf.get("spark.sql.autoBroadcastJoinThreshold")
    spark.conf.set("spark.sql.autoBroadcastJoinThreshold", "-1")
    try:
        ids, pairs = SMALL["random"]
        plain, dealt = (R.components(graph(spark, ids, pairs, False), measure=True, buckets=b) for b in (None, 4))
        assert got(plain.state, "D") == got(dealt.state, "D")
        assert dealt.ledger.exchanges < plain.ledger.exchanges
    finally:
        spark.conf.set("spark.sql.autoBroadcastJoinThreshold", before)


def test_ledger_measures(spark):
    ids, edges = SMALL["random"]
    p = P.components()
    r = R.components(graph(spark, ids, edges, False), measure=True)
    assert r.ledger.supersteps == machine.supersteps(machine.build(p), r.ledger.iterations)
    sent = [(kind, n) for kind, n, _ in r.ledger.messages]
    assert ("from Nbr", 2 * len(edges)) in sent and all(receivers <= n for _, n, receivers in r.ledger.messages)
    assert r.ledger.redundant == len(list(ids))  # each asks its pointer once more
    quiet = R.sssp(graph(spark, ids, edges), measure=True)
    assert quiet.ledger.redundant == 0 and not any(n for k, n, _ in quiet.ledger.messages[-1:])


def test_adjacency_in_parts(spark):
    g = graph(spark, range(9), [(0, k, k) for k in range(1, 8)] + [(1, 0, 3)])
    rows = g.with_adjacency(3).collect()
    assert sorted(len(r["adjacent"]) for r in rows if r["id"] == 0) == [1, 3, 3]
    assert sorted(x["ref"] for r in rows if r["id"] == 0 for x in r["adjacent"]) == list(range(1, 8))
    assert [r["adjacent"] for r in rows if r["id"] == 8] == [None]
