"""The algorithms as functions of graphs."""

from __future__ import annotations

from dataclasses import replace

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from farfield.algorithms import programs as P
from farfield.functions.foreign import FUNCTIONS
from farfield.lang import dsl as L
from farfield.plans.runtime import Result, run
from farfield.plans.store import materialise
from farfield.sources.builders import predecessors
from farfield.sources.graph import Graph

def sssp(g: Graph, source: int = 0, unit: bool = False, active: bool = True, **flags) -> Result:
    return run(P.sssp(source, unit, active), g, **flags)


def components(g: Graph, **flags) -> Result:
    return run(P.components(), g, **flags)


def hashmin(g: Graph, **flags) -> Result:
    return run(P.hashmin(), g, **flags)


def list_rank(g: Graph, val: int | None = None, **flags) -> Result:
    """val=1 ranks by place."""
    if val is not None:
        g = Graph(g.vertices.withColumn("Val", F.when(F.col("Pred") == F.col("id"), 0).otherwise(val).cast("long")))
    return run(P.list_rank(), g, **flags)


def roots(g: Graph, **flags) -> Result:
    return run(P.roots(), g, **flags)


def with_rank(g: Graph, damping: float = 0.85) -> Graph:
    """The graph with what the program for PageRank needs: Rank, Deg and Base."""
    deg = g.edges.groupBy("src").agg(F.count(F.lit(1)).alias("Deg"))
    n = max(g.vertices.count(), 1)
    v = g.vertices.select("id").join(deg, F.col("id") == F.col("src"), "left").select("id", "Deg")
    return replace(g, vertices=materialise(v.withColumn("Rank", F.lit(1.0 / n)).withColumn("Base", F.lit((1 - damping) / n)))[0])


def pagerank(g: Graph, rounds: int = 30, damping: float = 0.85, dangling: str = "drop", eps: float | None = None, **flags) -> Result:
    """dangling: 'drop' loses the rank of vertices without edges out; 'redistribute' spreads it over all, by edges to a virtual
    vertex that has an edge to every one. eps ends the loop when no rank changes by more."""
    g = with_rank(g.stored(flags.get("buckets")), damping)
    if dangling == "redistribute":
        return _redistributed(g, g.vertices.count(), rounds, damping)
    p = P.pagerank(rounds, damping)
    if eps is not None:
        p = L.repeat(p.body, L.change_below("Rank", eps), rounds)
    return run(p, g, **flags)


def _redistributed(g: Graph, n: int, rounds: int, damping: float) -> Result:
    """One scalar more per round: the rank of dangling vertices, summed by the job that writes the round."""
    from pyspark.sql import Observation

    from farfield.plans.runtime import Ledger

    s, lost = g.vertices, None
    for _ in range(rounds):
        if lost is None:
            lost = s.filter("Deg IS NULL").agg(F.sum("Rank")).first()[0] or 0.0
        near = g.edges.join(s.select(F.col("id").alias("src"), (F.col("Rank") / F.col("Deg")).alias("x")), "src").groupBy("dst").agg(F.sum("x").alias("x"))
        new = s.join(near, F.col("id") == F.col("dst"), "left").select("id", "Deg", (F.col("Base") + damping * (F.coalesce("x", F.lit(0.0)) + lost / n)).alias("Rank"), "Base")
        seen = Observation()
        s, _ = materialise(new.observe(seen, F.sum(F.when(F.col("Deg").isNull(), F.col("Rank"))).alias("lost")))
        lost = seen.get["lost"] or 0.0
    return Result(s, Ledger(iterations=[rounds], jobs=rounds))


def scc(g: Graph, early: bool = True, **flags) -> Result:
    return run(P.scc(early), g, **flags)


#: The least edge of a tree: its value, its ends in order, and the tree at the far end.
LEAST_EDGE = "struct<_1:bigint,_2:struct<lo:bigint,hi:bigint,far:bigint>>"


def msf_run(g: Graph, **flags) -> Result:
    """The spanning forest as a program of the language. Ties go by (val, src, dst)."""
    v = g.vertices.select("id", F.lit(None).cast(LEAST_EDGE).alias("Best"), F.lit(None).cast(LEAST_EDGE).alias("Edge"))
    return run(P.msf(), replace(g, vertices=v, edges=g.edges.withColumn("val", F.col("val").cast("long"))), functions=FUNCTIONS, **flags)


def msf_program(g: Graph, **flags) -> DataFrame:
    """(src, dst, val)"""
    return msf_run(g, **flags).state.filter("Edge IS NOT NULL").select("Edge._2.lo", "Edge._2.hi", "Edge._1").distinct().toDF("src", "dst", "val")


def with_mirrors(g: Graph) -> Graph:
    """The graph with val 1 on edges whose mirror is an edge too, else 0."""
    back = g.edges.select(F.col("dst").alias("a"), F.col("src").alias("b"), F.lit(1).cast("long").alias("back")).distinct()
    both = g.edges.join(back, (F.col("src") == F.col("a")) & (F.col("dst") == F.col("b")), "left").select("src", "dst", F.coalesce("back", F.lit(0).cast("long")).alias("val"))
    return Graph(g.vertices, both, g.directed)


def bipartite_matching(g: Graph, seed: int = 1, **flags) -> DataFrame:
    out = run(P.bipartite_matching(seed), g, functions=FUNCTIONS, **flags).state
    return out.filter("Side = 0 AND Mate IS NOT NULL").select(F.col("id").alias("left"), F.col("Mate").alias("right"))


def weight_matching(g: Graph, **flags) -> DataFrame:
    out = run(P.weight_matching(), g, functions=FUNCTIONS, **flags).state
    m = out.filter("id < Mate").select(F.col("id").alias("a"), F.col("Mate").alias("b"))
    return m.join(g.edges, (F.col("a") == F.col("src")) & (F.col("b") == F.col("dst"))).select("a", "b", "val")


def mutual_pointers(v: DataFrame, peephole: bool = True) -> DataFrame:
    """ids whose pointer's pointer comes back, for (id, D). With the peephole pointers are sent to where they point, in one exchange;
    else it is a chain read of two rounds."""
    if not peephole:
        far = v.select(F.col("id").alias("k"), F.col("D").alias("back"))
        return v.join(far, F.col("D") == F.col("k")).filter("back = id AND D <> id").select("id")
    mail = v.filter("D IS NOT NULL AND D <> id").select(F.col("D").alias("to"), F.col("id").alias("whose"))
    # only the letter of the own target matters, so letters and pointers meet by both ends, however many point to a vertex
    return v.join(mail, (F.col("id") == F.col("to")) & (F.col("D") == F.col("whose")), "left_semi").select("id")


def msf(g: Graph, peephole: bool = True) -> DataFrame:
    """Minimum spanning forest (src, dst, val): each tree picks its least edge, mutual picks make a root, pointers jump to it, and edges are
    relabelled until none is left. Ties go by (val, src, dst)."""
    e = g.once().select("src", "dst", "val", F.col("src").alias("x"), F.col("dst").alias("y"))
    e, _ = materialise(e, "edges")
    picked = e.limit(0).select("src", "dst", "val")
    while not e.isEmpty():
        key = F.struct("val", "src", "dst")
        ends = e.select(F.col("x").alias("id"), key.alias("k"), F.col("y").alias("o")).union(e.select("y", key, "x"))
        best, _ = materialise(ends.groupBy("id").agg(F.min("k").alias("k"), F.min_by("o", "k").alias("D")), "best")
        both = mutual_pointers(best.select("id", "D"), peephole).withColumn("mutual", F.lit(True))
        point = best.join(both, "id", "left").select("id", "k", F.when(F.col("mutual") & (F.col("id") < F.col("D")), F.col("id")).otherwise(F.col("D")).alias("Parent"))
        picked = picked.union(best.select("k.src", "k.dst", "k.val")).distinct()
        picked, _ = materialise(picked, "forest")
        tops = run(P.roots(), Graph(point.select("id", "Parent"))).state.select("id", "Root")
        a, b = tops.select(F.col("id").alias("x"), F.col("Root").alias("rx")), tops.select(F.col("id").alias("y"), F.col("Root").alias("ry"))
        moved = e.join(a, "x").join(b, "y").filter("rx <> ry").select("src", "dst", "val", F.least("rx", "ry").alias("x"), F.greatest("rx", "ry").alias("y"))
        # of parallel edges only the least can matter
        e, _ = materialise(moved.groupBy("x", "y").agg(F.min(F.struct("val", "src", "dst")).alias("k")).select("k.src", "k.dst", "k.val", "x", "y"), "edges")
    return picked


def preorder(g: Graph) -> DataFrame:
    """(id, pre): pre-order numbers of a forest, roots and children by id. The Euler tour enters and leaves each vertex; ranking the list with 1 for each entry
    numbers them."""
    v = g.vertices.select("id", F.when(F.col("Parent") != F.col("id"), F.col("Parent")).alias("p"))
    kids = predecessors(v.filter("p IS NOT NULL"), "id", ["id"], "p").withColumnRenamed("Pred", "before")
    # roots have no parent to be dealt by, so they are ordered by ranges
    kids = kids.union(predecessors(v.filter("p IS NULL"), "id", ["id"]).withColumnRenamed("Pred", "before"))
    last = v.filter("p IS NOT NULL").groupBy(F.col("p").alias("lp")).agg(F.max("id").alias("last"))
    enter, leave = F.col("id") * 2, F.col("id") * 2 + 1
    # what comes before entering: the sibling's leaving, or the parent's entering; before leaving: the last child's leaving, or the own entering
    into = kids.select(enter.alias("id"), F.lit(1).cast("long").alias("Val"), F.coalesce(F.col("before") * 2 + 1, F.col("p") * 2, F.lit(-1).cast("long")).alias("Pred"))
    out = v.join(last, F.col("id") == F.col("lp"), "left").select(leave.alias("id"), F.lit(0).cast("long").alias("Val"), F.coalesce(F.col("last") * 2 + 1, F.col("id") * 2).alias("Pred"))
    head = g.vertices.sparkSession.createDataFrame([(-1, 0, -1)], "id long, Val long, Pred long")
    ranked = list_rank(Graph(materialise(into.union(out).union(head))[0])).state
    return ranked.filter("id >= 0 AND id % 2 = 0").select((F.col("id") / 2).cast("long").alias("id"), (F.col("Sum") - 1).alias("pre"))


def pattern(g: Graph, expr, name: str = "Hit", **flags) -> DataFrame:
    """ids of the vertices where an expression of chains and comprehensions holds."""
    return run(L.step(lambda u: [L.local(getattr(L.F, name)[u], expr(u))]), g, **flags).state.filter(name).select("id")
