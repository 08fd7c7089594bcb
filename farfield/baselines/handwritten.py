"""The algorithms written directly as DataFrame loops, without the language. frontier=True lets only changed vertices send."""

from __future__ import annotations

from pyspark.sql import DataFrame, Observation
from pyspark.sql import functions as F

from farfield.plans.store import materialise
from farfield.sources.graph import Graph


def _until_same(s: DataFrame, one, changed) -> DataFrame:
    while True:
        seen = Observation()
        s, _ = materialise(one(s).observe(seen, F.max(changed.cast("int")).alias("c")))
        if not seen.get["c"]:
            return s


def sssp(g: Graph, source: int = 0, frontier: bool = True) -> DataFrame:
    e, _ = materialise(g.edges)
    s = g.vertices.select("id", F.when(F.col("id") == source, 0).cast("long").alias("d"), (F.col("id") == source).alias("a"))

    def one(s):
        senders = s.filter("a" if frontier else "d IS NOT NULL").select(F.col("id").alias("src"), "d")
        got = e.join(senders, "src").groupBy("dst").agg(F.min(F.col("d") + F.col("val")).alias("n"))
        return s.join(got, F.col("id") == F.col("dst"), "left").select("id", F.least("d", "n").alias("d"), F.coalesce(F.col("n") < F.col("d"), F.col("n").isNotNull() & F.col("d").isNull(), F.lit(False)).alias("a"))

    return _until_same(s, one, F.col("a")).select("id", F.col("d").alias("dist"))


def components(g: Graph) -> DataFrame:
    e, _ = materialise(g.edges)
    s = g.vertices.select("id", F.col("id").alias("d"), F.lit(None).cast("long").alias("was"))

    def one(s):
        base = s.select("id", "d")
        up = base.select(F.col("id").alias("k"), F.col("d").alias("g"))
        near = e.join(base.select(F.col("id").alias("src"), F.col("d").alias("x")), "src").groupBy("dst").agg(F.min("x").alias("n"))
        r = base.join(up, F.col("d") == F.col("k")).join(near, F.col("id") == F.col("dst"), "left").select("id", "d", "g", "n")
        hooks = r.filter("g = d AND n < d").groupBy("d").agg(F.min("n").alias("h")).withColumnRenamed("d", "t")
        return r.join(hooks, F.col("id") == F.col("t"), "left").select("id", F.least(F.when(F.col("g") == F.col("d"), F.col("d")).otherwise(F.col("g")), "h").alias("d"), F.col("d").alias("was"))

    return _until_same(s, one, F.col("d") != F.col("was")).select("id", F.col("d").alias("comp"))


def list_rank(g: Graph, frontier: bool = True) -> DataFrame:
    s = g.vertices.select("id", F.col("Val").alias("r"), F.col("Pred").alias("p"), F.lit(True).alias("a"))

    def one(s):
        far = s.select(F.col("id").alias("k"), F.col("r").alias("r2"), F.col("p").alias("p2"))
        # those that have reached their head sleep and are not joined again
        awake, asleep = (s.filter("a"), s.filter("NOT a")) if frontier else (s, None)
        j = awake.join(far, F.col("p") == F.col("k"))
        go = F.col("p2") != F.col("p")
        moved = j.select("id", F.when(go, F.col("r") + F.col("r2")).otherwise(F.col("r")).alias("r"), F.when(go, F.col("p2")).otherwise(F.col("p")).alias("p"), go.alias("a"))
        return moved.union(asleep) if frontier else moved

    return _until_same(s, one, F.col("a")).select("id", F.col("r").alias("rank"))


def pagerank(g: Graph, rounds: int = 30, damping: float = 0.85) -> DataFrame:
    n = g.vertices.count()
    deg = g.edges.groupBy("src").agg(F.count(F.lit(1)).alias("deg"))
    e, _ = materialise(g.edges.select("src", "dst").join(deg, "src"))
    s = g.vertices.select("id", F.lit(1.0 / n).alias("rank"))
    for _ in range(rounds):
        got = e.join(s.withColumnRenamed("id", "src"), "src").groupBy("dst").agg(F.sum(F.col("rank") / F.col("deg")).alias("x"))
        s, _ = materialise(s.select("id").join(got, F.col("id") == F.col("dst"), "left").select("id", (F.lit((1 - damping) / n) + damping * F.coalesce("x", F.lit(0.0))).alias("rank")))
    return s


def _flood(nodes: DataFrame, edges: DataFrame) -> DataFrame:
    s = nodes.select("id", F.col("id").alias("l"), F.lit(True).alias("a"))

    def one(s):
        got = edges.join(s.filter("a").select(F.col("id").alias("src"), F.col("l").alias("x")), "src").groupBy("dst").agg(F.min("x").alias("x"))
        return s.join(got, F.col("id") == F.col("dst"), "left").select("id", F.least("l", "x").alias("l"), F.coalesce(F.col("x") < F.col("l"), F.lit(False)).alias("a"))

    return _until_same(s, one, F.col("a")).select("id", "l")


def scc(g: Graph) -> DataFrame:
    live, e = g.vertices.select("id"), g.edges.select("src", "dst").filter("src <> dst")
    done = live.limit(0).select("id", F.col("id").alias("scc"))
    live, e = materialise(live)[0], materialise(e)[0]
    while not live.isEmpty():
        inner = live.join(e.select(F.col("src").alias("id")), "id", "left_semi").join(e.select(F.col("dst").alias("id")), "id", "left_semi")
        done = done.union(live.join(inner, "id", "left_anti").select("id", F.col("id").alias("scc")))
        inner, _ = materialise(inner)
        e = e.join(inner.withColumnRenamed("id", "src"), "src", "left_semi").join(inner.withColumnRenamed("id", "dst"), "dst", "left_semi")
        e, _ = materialise(e.select("src", "dst"))
        fw = _flood(inner, e)
        bw = _flood(inner, e.select(F.col("dst").alias("src"), F.col("src").alias("dst")))
        both, _ = materialise(fw.join(bw.withColumnRenamed("l", "b"), "id"))
        done, _ = materialise(done.union(both.filter("l = b").select("id", "l")))
        live, _ = materialise(both.filter("l <> b").select("id"))
        part = both.filter("l <> b").select("id", F.struct("l", "b").alias("p"))
        a, b = part.select(F.col("id").alias("src"), F.col("p").alias("ps")), part.select(F.col("id").alias("dst"), F.col("p").alias("pd"))
        e, _ = materialise(e.join(a, "src").join(b, "dst").filter("ps = pd").select("src", "dst"))
    return done


def msf(g: Graph) -> DataFrame:
    """By component labels: each component's least edge out, then new labels, until no edge crosses."""
    e, _ = materialise(g.once())
    label, _ = materialise(g.vertices.select("id", F.col("id").alias("l")))
    forest = e.limit(0)
    while True:
        a, b = label.select(F.col("id").alias("src"), F.col("l").alias("ls")), label.select(F.col("id").alias("dst"), F.col("l").alias("ld"))
        cross = e.join(a, "src").join(b, "dst").filter("ls <> ld").withColumn("k", F.struct("val", "src", "dst"))
        pick = cross.select(F.col("ls").alias("l"), "k").union(cross.select("ld", "k")).groupBy("l").agg(F.min("k").alias("k")).select("k.src", "k.dst", "k.val").distinct()
        pick, _ = materialise(pick)
        if pick.isEmpty():
            return forest
        forest, _ = materialise(forest.union(pick))
        label, _ = materialise(components(Graph.of(g.vertices.select("id"), forest.select("src", "dst", "val"), False)).withColumnRenamed("comp", "l"))


def recursive_sssp(spark, vertices: str, edges: str, source: int = 0, hops: int = 64) -> DataFrame:
    """WITH RECURSIVE over views. Spark's recursion keeps all rows, so the hops need a bound, and cycles cost rows."""
    return spark.sql(f"""
        WITH RECURSIVE reach(id, dist, hop) AS (
          SELECT CAST({source} AS BIGINT), CAST(0 AS BIGINT), 0
          UNION ALL
          SELECT e.dst, r.dist + 1, r.hop + 1 FROM reach r JOIN {edges} e ON e.src = r.id WHERE r.hop < {hops}
        )
        SELECT v.id, min(r.dist) AS dist FROM {vertices} v LEFT JOIN reach r ON v.id = r.id GROUP BY v.id""")
