"""Operators around graphs that Spark has no single call for."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from farfield.sources.graph import Graph


def range_join(left: DataFrame, right: DataFrame, at: str, other: str, width: int, keys: list[str] | None = None) -> DataFrame:
    """Pairs with other - width <= at - ... : 0 <= right.other - left.at <= width, on numbers. Each left row goes to its bucket of that width, each right
    row to its own and the one before, so the join is on equal buckets."""
    keys = keys or []
    a = left.withColumn("_b", F.floor(F.col(at) / width))
    b = right.withColumn("_b", F.explode(F.array(F.floor(F.col(other) / width), F.floor(F.col(other) / width) - 1)))
    return a.join(b, [*keys, "_b"]).filter((F.col(other) >= F.col(at)) & (F.col(other) - F.col(at) <= width)).drop("_b")


def as_of_join(left: DataFrame, right: DataFrame, key: str, at: str, value: str, name: str = "as_of") -> DataFrame:
    """left with the latest value of right at or before its time, by key. Both are one stream in order of time, and the last value is carried along."""
    a = left.withColumn("_side", F.lit(1)).withColumn("_v", F.lit(None))
    b = right.select(key, at, F.lit(0).alias("_side"), F.struct(value).alias("_v"))
    w = Window.partitionBy(key).orderBy(at, "_side").rowsBetween(Window.unboundedPreceding, 0)
    both = a.drop("_v").unionByName(b.select(key, at, "_side", "_v"), allowMissingColumns=True)
    return both.withColumn(name, F.last("_v", ignorenulls=True).over(w)[value]).filter("_side = 1").drop("_side", "_v")


def salted_sum(df: DataFrame, key: str, value: Column, salts: int = 32) -> DataFrame:
    """Sums by key in two shuffles, for functions that don't reduce before the first."""
    part = df.select(key, value.alias("v"), F.pmod(F.xxhash64(F.monotonically_increasing_id()), F.lit(salts)).alias("s")).groupBy(key, "s").agg(F.sum("v").alias("v"))
    return part.groupBy(key).agg(F.sum("v").alias("total"))


def pointer_join(state: DataFrame, pointer: str, fields: list[str], hot: DataFrame | None = None) -> DataFrame:
    """Brings fields from where pointer points. hot: a bounded table of ids that many point to; their values are broadcast, and only the rest is shuffled."""
    far = state.select(F.col("id").alias("_k"), *(F.col(f).alias(f"far_{f}") for f in fields))
    if hot is None:
        return state.join(far, F.col(pointer) == F.col("_k"), "left").drop("_k")
    ids = F.broadcast(hot.select(F.col("id").alias("_h")))
    few = F.broadcast(far.join(ids, F.col("_k") == F.col("_h"), "left_semi"))
    to_hot = state.join(ids, F.col(pointer) == F.col("_h"), "left_semi").join(few, F.col(pointer) == F.col("_k"), "left")
    rest = state.join(ids, F.col(pointer) == F.col("_h"), "left_anti").join(far, F.col(pointer) == F.col("_k"), "left")
    return to_hot.unionByName(rest).drop("_k")


def hot_targets(state: DataFrame, pointer: str, share: float = 0.001, most: int = 1000) -> DataFrame:
    """At most `most` ids to which more than a share of all rows point."""
    n = state.count()
    return state.groupBy(F.col(pointer).alias("id")).agg(F.count(F.lit(1)).alias("n")).filter(F.col("n") > share * n).orderBy(F.desc("n"), "id").limit(most).select("id")


def degrees(g: Graph) -> DataFrame:
    """id, ins, outs."""
    e = g.edges.select(F.col("dst").alias("id"), F.lit(1).alias("i"), F.lit(0).alias("o")).union(g.edges.select("src", F.lit(0), F.lit(1)))
    d = e.groupBy("id").agg(F.sum("i").alias("ins"), F.sum("o").alias("outs"))
    return g.vertices.select("id").join(d, "id", "left").select("id", F.coalesce("ins", F.lit(0)).cast("long").alias("ins"), F.coalesce("outs", F.lit(0)).cast("long").alias("outs"))


def component_sizes(labels: DataFrame, label: str) -> DataFrame:
    """size, n: how many components have it."""
    return labels.groupBy(label).agg(F.count(F.lit(1)).alias("size")).groupBy("size").agg(F.count(F.lit(1)).alias("n"))


def modularity(g: Graph, labels: DataFrame, label: str) -> DataFrame:
    """One row: modularity of a labelling of an undirected graph."""
    l1 = labels.select(F.col("id").alias("src"), F.col(label).alias("a"))
    l2 = labels.select(F.col("id").alias("dst"), F.col(label).alias("b"))
    e = g.edges.join(l1, "src").join(l2, "dst")
    by = e.groupBy("a").agg(F.sum((F.col("a") == F.col("b")).cast("int")).alias("inside"), F.count(F.lit(1)).alias("deg"))
    return by.agg(F.sum("inside").alias("i"), F.sum("deg").alias("m"), F.sum(F.col("deg").cast("double") ** 2).alias("q")).select((F.col("i") / F.col("m") - F.col("q") / F.col("m") ** 2).alias("modularity"))


def triangles(g: Graph) -> DataFrame:
    """id, triangles of an undirected graph; each edge points from the lower to the higher degree, so hubs have short lists."""
    d = g.edges.groupBy("src").agg(F.count(F.lit(1)).alias("d"))
    rank = lambda x, n: d.select(F.col("src").alias(x), F.struct("d", "src").alias(n))
    e = g.edges.select("src", "dst").distinct().join(rank("src", "p"), "src").join(rank("dst", "q"), "dst").filter("p < q").select("src", "dst")
    two = e.select(F.col("src").alias("a"), F.col("dst").alias("b")).join(e.select(F.col("src").alias("a"), F.col("dst").alias("c")), "a").filter("b <> c")
    closed = two.join(e, (F.col("b") == F.col("src")) & (F.col("c") == F.col("dst"))).select("a", "b", "c")
    return closed.select(F.explode(F.array("a", "b", "c")).alias("id")).groupBy("id").agg(F.count(F.lit(1)).alias("triangles"))


def top_edges(g: Graph, k: int) -> DataFrame:
    """The k edges of least (val, dst) of each vertex."""
    w = Window.partitionBy("src").orderBy("val", "dst")
    return g.edges.withColumn("r", F.row_number().over(w)).filter(F.col("r") <= k).select("src", "dst", "val", "r")
