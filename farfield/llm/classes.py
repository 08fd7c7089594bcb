"""Classes of a link table: rounds of hooking and pointer jumping over DataFrames."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from farfield.llm.common import Generations, looked_up, written

#: Nodes with more than this share of all links are hubs: fewer than 1 / HUB.
HUB = 1 / 256


def classes_of_links(links: DataFrame) -> DataFrame:
    """(node, root) for each node of links (a, b); root is the least node of its class.

    A round gives each node the least root among its neighbours, hooks the root of its own tree to it, and jumps. The rounds
    grow with the logarithm of the longest path. Each writes its table to the shared folder, which ends the lineage.
    All aggregation is by minimum, so what a hub or a root gets is reduced before it is shuffled. No join brings the links of a hub or the nodes of a
    root to one task: hubs are few, and their rows are broadcast; roots are looked up by salted keys.
    """
    both = links.filter("a <> b").select("a", "b").union(links.filter("a <> b").select(F.col("b").alias("a"), F.col("a").alias("b")))
    edges = written(both.distinct(), "edges")
    n = edges.count()
    hubs = [r["b"] for r in edges.groupBy("b").agg(F.count(F.lit(1)).alias("n")).filter(F.col("n") > F.lit(n * HUB)).collect()]  # fewer than 1 / HUB
    is_hub = F.col("b").isin(hubs)
    tables = Generations("classes")
    state = tables.written(edges.groupBy("a").agg(F.min("b").alias("m")).select(F.col("a").alias("node"), F.least("a", "m").alias("root")))
    while True:
        far = state.select(F.col("node").alias("b"), F.col("root").alias("r"))
        heard = edges.filter(~is_hub).join(far.filter(~is_hub), "b").select("a", "r").union(edges.filter(is_hub).join(F.broadcast(far.filter(is_hub)), "b").select("a", "r"))
        near = heard.groupBy("a").agg(F.min("r").alias("r"))
        seen = state.join(near, state["node"] == near["a"], "left").select("node", "root", F.least("root", F.coalesce("r", "root")).alias("low"))
        hooks = seen.filter("low < root").groupBy(F.col("root").alias("old")).agg(F.min("low").alias("hook"))
        hooked = looked_up(seen, "root", hooks, "old", "node").select("node", "root", F.least("low", F.coalesce("hook", "low")).alias("new"))
        up = hooked.select(F.col("node").alias("p"), F.col("new").alias("above"))
        # what stands above the roots that are pointed to, each of them once
        tops = hooked.select(F.col("new").alias("top")).distinct()
        higher = tops.join(up, F.col("top") == F.col("p")).filter("above < top").select("top", "above")
        jumped = looked_up(hooked, "new", higher, "top", "node").select("node", F.col("root").alias("was"), F.least("new", F.coalesce("above", "new")).alias("root"))
        after = tables.written(jumped)
        state = after.select("node", "root")
        if after.filter("was <> root").isEmpty():
            return state
