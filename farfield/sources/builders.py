"""Graphs derived from the given tables."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from farfield.operators.nearest import nearest
from farfield.plans.store import materialise
from farfield.sources.graph import Graph
from farfield.sources.tables import load

LINE_ORDER = ("l_linenumber", "l_partkey", "l_suppkey", "l_quantity", "l_extendedprice")


def cents(c: str) -> Column:
    return F.round(F.col(c) * 100).cast("long")


def predecessors(df: DataFrame, id_: str, order: list[str], by: str | None = None, partitions: int | None = None) -> DataFrame:
    """Adds Pred: the id before, in order; NULL at the start. Without `by` the order is global: rows are range-partitioned, and each
    partition's first row takes the last of the one before, from a table of one row per partition."""
    if by:
        return df.withColumn("Pred", F.lag(id_).over(Window.partitionBy(by).orderBy(*order)))
    n = partitions or int(df.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    ranged, _ = materialise(df.repartitionByRange(n, *order).withColumn("_part", F.spark_partition_id()), "ranged")
    within = ranged.withColumn("Pred", F.lag(id_).over(Window.partitionBy("_part").orderBy(*order)))
    last = ranged.groupBy("_part").agg(F.max_by(id_, F.struct(*order)).alias("_last"))
    last = last.select((F.lead("_part").over(Window.orderBy("_part"))).alias("_p"), "_last").filter("_p IS NOT NULL")
    return within.join(F.broadcast(last), F.col("_part") == F.col("_p"), "left").withColumn("Pred", F.coalesce("Pred", "_last")).drop("_part", "_p", "_last")


def global_rank(df: DataFrame, order: list[Column], name: str, partitions: int | None = None) -> DataFrame:
    """Adds the rank from 1 of each row in a global order, without bringing all rows together: ranges are ranked on their own, and shifted by a prefix sum over
    one row per range."""
    n = partitions or int(df.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    ranged, _ = materialise(df.repartitionByRange(n, *order).withColumn("_part", F.spark_partition_id()), "ranged")
    sizes = ranged.groupBy(F.col("_part").alias("_p")).agg(F.count(F.lit(1)).alias("_n"))
    before = sizes.select("_p", (F.sum("_n").over(Window.orderBy("_p").rowsBetween(Window.unboundedPreceding, 0)) - F.col("_n")).alias("_before"))
    own = F.row_number().over(Window.partitionBy("_part").orderBy(*order))
    return ranged.withColumn(name, own).join(F.broadcast(before), F.col("_part") == F.col("_p")).withColumn(name, (F.col(name) + F.col("_before")).cast("long")).drop("_part", "_p", "_before")


def add_heads(items: DataFrame, head: Column) -> DataFrame:
    """Lists need a head of value 0 that points to itself; head gives its id for each element."""
    rows = items.withColumn("_head", head)
    heads = rows.select(F.col("_head").alias("id"), F.lit(0).cast("long").alias("Val"), F.col("_head").alias("Pred")).distinct()
    return rows.select("id", "Val", F.coalesce("Pred", "_head").alias("Pred")).union(heads)


def event_chain(spark: SparkSession, d: str) -> Graph:
    e = load(spark, d, "events").select(F.col("event_id").alias("id"), cents("value").alias("Val"), "ts")
    return Graph(add_heads(predecessors(e, "id", ["ts", "id"]), F.lit(-1).cast("long")))


def user_chains(spark: SparkSession, d: str) -> Graph:
    e = load(spark, d, "events").select(F.col("event_id").alias("id"), cents("value").alias("Val"), "ts", "user_id")
    return Graph(add_heads(predecessors(e, "id", ["ts", "id"], "user_id"), -(F.col("user_id") + 1)))


def turn_chain(spark: SparkSession, d: str) -> Graph:
    t = load(spark, d, "conversations").select((F.col("conv_id") * 1000 + F.col("turn")).alias("id"), F.coalesce(F.length("text"), F.lit(0)).cast("long").alias("Val"), "conv_id", "turn")
    return Graph(add_heads(predecessors(t, "id", ["turn"], "conv_id"), -(F.col("conv_id") + 1)))


def order_chain(spark: SparkSession, d: str) -> Graph:
    o = load(spark, d, "orders").select(F.col("o_orderkey").alias("id"), cents("o_totalprice").alias("Val"), "o_custkey", "o_orderdate")
    return Graph(add_heads(predecessors(o, "id", ["o_orderdate", "id"], "o_custkey"), -(F.col("o_custkey") + 1)))


def user_chain_graph(spark: SparkSession, d: str) -> Graph:
    e = load(spark, d, "events").select(F.col("event_id").alias("id"), "ts", "user_id")
    chains = predecessors(e, "id", ["ts", "id"], "user_id").filter("Pred IS NOT NULL").select(F.col("Pred").alias("src"), F.col("id").alias("dst"), "user_id")
    return Graph.of(e.select("id", "user_id"), chains, False, block="user_id")


def event_chain_graph(spark: SparkSession, d: str) -> Graph:
    e = load(spark, d, "events").select(F.col("event_id").alias("id"), "ts")
    return Graph.of(e.select("id"), predecessors(e, "id", ["ts", "id"]).filter("Pred IS NOT NULL").select(F.col("Pred").alias("src"), F.col("id").alias("dst")), False)


def line_successors(lines: DataFrame, key: str) -> DataFrame:
    """(src, dst, val) of successive lines of each order by a key, without loops, one row a pair."""
    w = Window.partitionBy("l_orderkey").orderBy(*LINE_ORDER)
    pairs = lines.select(F.col(key).alias("src"), F.lead(key).over(w).alias("dst"), F.col("l_quantity").cast("long").alias("q"))
    return pairs.filter("dst IS NOT NULL AND src <> dst").groupBy("src", "dst").agg(F.min("q").alias("val"))


LINE_FILTERS = {"a": "true", "b": "l_returnflag = 'R'", "c": "l_returnflag = 'R' AND l_discount >= 0.065"}


def part_flow(spark: SparkSession, d: str, which: str = "a") -> Graph:
    parts = load(spark, d, "part").select(F.col("p_partkey").alias("id"), F.col("p_name").alias("Name"), F.col("p_brand").alias("Brand"))
    return Graph.of(parts, line_successors(load(spark, d, "lineitem").filter(LINE_FILTERS[which]), "l_partkey"))


def undirected(g: Graph) -> Graph:
    """Each pair of linked vertices once, in both orientations, with the least value."""
    e = g.edges.select(F.least("src", "dst").alias("src"), F.greatest("src", "dst").alias("dst"), "val").groupBy("src", "dst").agg(F.min("val").alias("val"))
    return Graph.of(g.vertices, e, False)


def supplier_mesh(spark: SparkSession, d: str) -> Graph:
    """Weights are unique: ranks of pairs by how often they follow each other."""
    w = Window.partitionBy("l_orderkey").orderBy(*LINE_ORDER)
    lines = load(spark, d, "lineitem").filter(LINE_FILTERS["c"])
    p = lines.select(F.col("l_suppkey").alias("x"), F.lead("l_suppkey").over(w).alias("y")).filter("y IS NOT NULL AND x <> y")
    n = p.groupBy(F.least("x", "y").alias("src"), F.greatest("x", "y").alias("dst")).agg(F.count(F.lit(1)).alias("n"))
    e = global_rank(n, [F.desc("n"), F.col("src"), F.col("dst")], "val")
    return Graph.of(load(spark, d, "supplier").select(F.col("s_suppkey").alias("id")), e.select("src", "dst", "val"), False)


def shared_key(df: DataFrame, id_: str, key: str) -> DataFrame:
    """A star for each key that several rows share: edges to its least id."""
    least = df.groupBy(key).agg(F.min(id_).alias("dst"))
    return df.join(least, key).filter(F.col(id_) > F.col("dst")).select(F.col(id_).alias("src"), "dst").distinct()


def _documents(spark: SparkSession, d: str) -> DataFrame:
    labels = load(spark, d, "labels").select("doc_id", "toxic")
    return load(spark, d, "documents").select("doc_id", "lang", "source").join(labels, "doc_id", "left").select(F.col("doc_id").alias("id"), F.col("lang").alias("Lang"), F.col("source").alias("Source"), F.coalesce(F.col("toxic"), F.lit(0)).cast("long").alias("Toxic"))


def doc_overlap(spark: SparkSession, d: str, least: int = 40) -> Graph:
    lines = load(spark, d, "documents").select("doc_id", F.explode(F.split("text", "\n")).alias("l")).select("doc_id", F.trim("l").alias("l"))
    lines = lines.filter(F.length("l") >= least).select("doc_id", F.md5("l").alias("k")).distinct()
    return Graph.of(_documents(spark, d), shared_key(lines, "doc_id", "k"), False)


def doc_exact(spark: SparkSession, d: str) -> Graph:
    return Graph.of(_documents(spark, d), shared_key(load(spark, d, "documents").select("doc_id", F.md5("text").alias("k")), "doc_id", "k"), False)


def vec_knn(spark: SparkSession, d: str, k: int = 5) -> Graph:
    """k nearest by squared distance of components in thousandths, by an exact search of all pairs."""
    v = load(spark, d, "embeddings").select(F.col("vec_id").alias("id"), F.transform("embedding", lambda x: F.round(x.cast("double") * 1000).cast("long")).alias("x"), F.col("label").alias("Label"))
    e = nearest(v, k).select(F.least("a", "b").alias("src"), F.greatest("a", "b").alias("dst"), "val").distinct()
    return Graph.of(v.select("id", "Label"), materialise(e, "knn")[0], False)


SPANS = {"region": 0, "nation": 1_000, "supplier": 10_000_000_000, "customer": 20_000_000_000, "orders": 30_000_000_000}


def geo_forest(spark: SparkSession, d: str) -> Graph:
    """Region, nation, supplier, customer and order in one tree; Parent points upwards, named pointers too."""
    at = {k: F.lit(v).cast("long") for k, v in SPANS.items()}
    none, text = F.lit(None).cast("long"), F.lit(None).cast("string")
    cols = lambda kind, id_, name, parent, amount=none, cust=none, nation=none, region=none: [id_.alias("id"), F.lit(kind).alias("Kind"), name.alias("Name"), parent.alias("Parent"), amount.alias("Amount"), cust.alias("Cust"), nation.alias("Nation"), region.alias("Region")]
    r = load(spark, d, "region").select(*cols("region", F.col("r_regionkey").cast("long"), F.col("r_name"), F.col("r_regionkey").cast("long")))
    n = load(spark, d, "nation").select(*cols("nation", at["nation"] + F.col("n_nationkey"), F.col("n_name"), F.col("n_regionkey").cast("long"), region=F.col("n_regionkey").cast("long")))
    s = load(spark, d, "supplier").select(*cols("supplier", at["supplier"] + F.col("s_suppkey"), F.col("s_name"), at["nation"] + F.col("s_nationkey"), nation=at["nation"] + F.col("s_nationkey")))
    c = load(spark, d, "customer").select(*cols("customer", at["customer"] + F.col("c_custkey"), F.col("c_name"), at["nation"] + F.col("c_nationkey"), nation=at["nation"] + F.col("c_nationkey")))
    o = load(spark, d, "orders").select(*cols("orders", at["orders"] + F.col("o_orderkey"), text, at["customer"] + F.col("o_custkey"), cents("o_totalprice"), at["customer"] + F.col("o_custkey")))
    return Graph(r.unionByName(n).unionByName(s).unionByName(c).unionByName(o))


def cust_part(spark: SparkSession, d: str) -> Graph:
    c = load(spark, d, "customer").select(F.col("c_custkey").alias("id"), F.lit(0).alias("Side"))
    p = load(spark, d, "part").select((-(F.col("p_partkey") + 1)).alias("id"), F.lit(1).alias("Side"))
    lines = load(spark, d, "lineitem").filter("l_returnflag = 'R' AND l_discount >= 0.095")
    e = lines.join(load(spark, d, "orders"), F.col("l_orderkey") == F.col("o_orderkey")).select(F.col("o_custkey").alias("src"), (-(F.col("l_partkey") + 1)).alias("dst")).distinct()
    return Graph.of(c.union(p), e, False)


def page_links(spark: SparkSession, d: str) -> Graph:
    pages = load(spark, d, "pages")
    links = pages.select("page_id", F.explode(F.array_distinct(F.regexp_extract_all("html", F.lit('href="([^"]*)"'), F.lit(1)))).alias("h"))
    owner = links.groupBy("h").agg(F.min("page_id").alias("dst"))
    e = links.join(owner, "h").filter("page_id <> dst").select(F.col("page_id").alias("src"), "dst").distinct()
    return Graph.of(pages.select(F.col("page_id").alias("id"), F.col("url").alias("Url")), e)


BUILDERS = {
    "event_chain": event_chain, "event_chain_graph": event_chain_graph, "user_chains": user_chains, "user_chain_graph": user_chain_graph,
    "part_flow_a": lambda s, d: part_flow(s, d, "a"), "part_flow_b": lambda s, d: part_flow(s, d, "b"), "part_flow_c": lambda s, d: part_flow(s, d, "c"),
    "doc_overlap": doc_overlap, "doc_exact": doc_exact, "vec_knn": vec_knn, "geo_forest": geo_forest, "cust_part": cust_part,
    "supplier_mesh": supplier_mesh, "page_links": page_links, "turn_chain": turn_chain, "order_chain": order_chain,
}
