"""Graphs as a vertex table (id and fields) and an edge table (src, dst, val)."""

from __future__ import annotations

from dataclasses import dataclass, replace

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.window import Window


@dataclass(frozen=True)
class Graph:
    """An undirected graph stores each edge in both orientations, so edges are seen alike from both ends."""

    vertices: DataFrame
    edges: DataFrame | None = None
    directed: bool = True
    #: Edges bucketed by dst, where `stored` made them besides those by src.
    by_dst: DataFrame | None = None
    is_stored: bool = False
    #: A column of vertices and edges: both ends of an edge have the edge's value.
    block: str | None = None

    @staticmethod
    def of(vertices: DataFrame, edges: DataFrame | None = None, directed: bool = True, block: str | None = None) -> "Graph":
        if edges is not None:
            if "val" not in edges.columns:
                edges = edges.withColumn("val", F.lit(1).cast("long"))
            more = [block] if block else []
            edges = edges.select("src", "dst", "val", *more)
            if not directed:
                edges = edges.union(edges.select("dst", "src", "val", *more))
        return Graph(vertices, edges, directed, block=block)

    @staticmethod
    def from_edges(edges: DataFrame, directed: bool = True) -> "Graph":
        ids = edges.select(F.col("src").alias("id")).union(edges.select("dst")).distinct()
        return Graph.of(ids, edges, directed)

    @staticmethod
    def read(spark: SparkSession, path: str, format: str = "csv", directed: bool = True, **options) -> "Graph":
        """An edge list: csv, tsv, json, orc, parquet or text with white space between the ends."""
        if format == "text":
            part = F.split(F.trim("value"), r"\s+")
            e = spark.read.text(path).filter(~F.col("value").startswith("#")).select(part[0].cast("long").alias("src"), part[1].cast("long").alias("dst"), F.coalesce(F.get(part, F.lit(2)).cast("long"), F.lit(1).cast("long")).alias("val"))
        else:
            if format == "tsv":
                format, options = "csv", {"sep": "\t", **options}
            if format in ("csv", "json"):
                options.setdefault("schema", "src long, dst long, val long")
            schema = options.pop("schema", None)
            reader = spark.read.format(format).options(**options)
            e = (reader.schema(schema) if schema else reader).load(path)
        return Graph.from_edges(e, directed)

    def write(self, path: str, format: str = "parquet", partition_by: str | None = None) -> None:
        for name, df in (("vertices", self.vertices), ("edges", self.edges)):
            if df is not None:
                w = df.write.mode("overwrite").format(format)
                (w.partitionBy(partition_by) if partition_by and partition_by in df.columns else w).save(f"{path}/{name}")

    def create_views(self, prefix: str) -> None:
        self.vertices.createOrReplaceTempView(f"{prefix}_vertices")
        if self.edges is not None:
            self.edges.createOrReplaceTempView(f"{prefix}_edges")

    def stored(self, buckets: int | None = None) -> "Graph":
        """The graph with its edges written, so that a loop does not derive them again in each pass. With buckets they are written twice, by src and by dst."""
        from farfield.plans.store import materialise

        if self.edges is None or self.is_stored:
            return self
        edges, _ = materialise(self.edges, "edges", buckets, "src")
        by_dst = materialise(edges, "edges", buckets, "dst")[0] if buckets else None
        return replace(self, edges=edges, by_dst=by_dst, is_stored=True)

    def once(self) -> DataFrame:
        """Each edge of an undirected graph once, src below dst."""
        return self.edges.filter("src < dst")

    def induced(self, keep: DataFrame) -> "Graph":
        """The part on the vertices whose ids are in keep.id."""
        k = keep.select(F.col("id").alias("k"))
        edges = self.edges.join(k, F.col("src") == F.col("k"), "left_semi").join(k, F.col("dst") == F.col("k"), "left_semi")
        return Graph(self.vertices.join(k, F.col("id") == F.col("k"), "left_semi"), edges, self.directed)

    def with_adjacency(self, most: int = 1000) -> DataFrame:
        """id, part and an array of (ref, val): the edges out of a vertex in order, in parts of at most `most` from 0 on, so that no list grows with a
        hub. A vertex without edges has one part, null."""
        spread = self.edges.withColumn("h", F.pmod(F.xxhash64("dst"), F.lit(256)))
        # places by prefix sums over (src, h), so a hub is no single task; edges of a bucket of it are
        sizes = spread.groupBy("src", "h").agg(F.count(F.lit(1)).alias("n"))
        before = F.sum("n").over(Window.partitionBy("src").orderBy("h").rowsBetween(Window.unboundedPreceding, 0)) - F.col("n")
        sizes = sizes.select(F.col("src").alias("s"), F.col("h").alias("h2"), before.alias("first"))
        own = F.row_number().over(Window.partitionBy("src", "h").orderBy("dst", "val")) - 1
        placed = spread.withColumn("nth", own).join(sizes, (F.col("src") == F.col("s")) & (F.col("h") == F.col("h2")))
        parts = placed.groupBy("src", F.floor((F.col("first") + F.col("nth")) / most).alias("part")).agg(F.sort_array(F.collect_list(F.struct(F.col("dst").alias("ref"), "val"))).alias("adjacent"))
        return self.vertices.select("id").join(parts, F.col("id") == F.col("src"), "left").select("id", "part", "adjacent")

    def validate(self) -> DataFrame:
        """One row: repeated ids, edges with an unknown end, self loops, repeated edges, and edges without their mirror if undirected."""
        v, e = self.vertices, self.edges
        ends = e.select(F.col("src").alias("x")).union(e.select("dst"))
        mirror = e.select(F.col("dst").alias("a"), F.col("src").alias("b"), F.col("val").alias("w"))
        lone = e.join(mirror, (F.col("src") == F.col("a")) & (F.col("dst") == F.col("b")) & F.col("val").eqNullSafe(F.col("w")), "left_anti")
        one = lambda df, name: df.agg(F.count(F.lit(1)).alias(name))
        out = one(v.groupBy("id").count().filter("count > 1"), "repeated_ids")
        for df in (
            one(ends.join(v.select("id"), F.col("x") == F.col("id"), "left_anti"), "dangling_ends"),
            one(e.filter("src = dst"), "self_loops"),
            one(e.groupBy("src", "dst").count().filter("count > 1"), "repeated_edges"),
            one(lone if not self.directed else lone.limit(0), "unmirrored_edges"),
        ):
            out = out.crossJoin(df)  # one row each
        return out


def intern_ids(df: DataFrame, key: str, name: str = "id", check: bool = True) -> DataFrame:
    """Adds a bigint id for a string key: a 64-bit hash. If two keys share an id, that is an error, unless check is off."""
    out = df.withColumn(name, F.xxhash64(key))
    if check and not collisions(out, key, name).isEmpty():
        raise ValueError(f"two values of {key} share an id")
    return out


def collisions(df: DataFrame, key: str, name: str = "id") -> DataFrame:
    return df.select(key, name).distinct().groupBy(name).agg(F.count(F.lit(1)).alias("n")).filter("n > 1")
