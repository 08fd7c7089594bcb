"""Streams of events as changing graphs."""

from __future__ import annotations

import uuid
from collections.abc import Callable, Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from farfield.plans.store import materialise, shared_folder


def source(spark: SparkSession, path: str, like: DataFrame | None = None, files_per_trigger: int = 1) -> DataFrame:
    """A directory of Parquet files as a stream, with the schema of like or of what is there."""
    return spark.readStream.schema((like or spark.read.parquet(path)).schema).option("maxFilesPerTrigger", files_per_trigger).parquet(path)


def start(df: DataFrame, mode: str, checkpoint: str, path: str | None = None, batch: Callable | None = None):
    """A query over what is there now; started again with the same checkpoint it goes on where it ended."""
    w = df.writeStream.outputMode(mode).trigger(availableNow=True).option("checkpointLocation", checkpoint)
    return (w.foreachBatch(batch) if batch else w.format("parquet").option("path", path)).start()


def windowed_pairs(events: DataFrame, length: str = "1 hour", slide: str | None = None, late: str = "1 hour") -> DataFrame:
    """Window, user and number of events; later than the watermark is dropped."""
    return events.withWatermark("ts", late).groupBy(F.window("ts", length, slide), "user_id").agg(F.count(F.lit(1)).alias("n"))


def sessions(events: DataFrame, gap: str = "30 minutes", late: str = "1 hour") -> DataFrame:
    return events.withWatermark("ts", late).groupBy(F.session_window("ts", gap), "user_id").agg(F.count(F.lit(1)).alias("n"))


def interval_edges(left: DataFrame, right: DataFrame, bound: str = "1 hour", late: str = "2 hours") -> DataFrame:
    """src, dst: events of one user, the second at most `bound` after the first."""
    a = left.select(F.col("event_id").alias("src"), F.col("user_id").alias("ua"), F.col("ts").alias("ta")).withWatermark("ta", late)
    b = right.select(F.col("event_id").alias("dst"), F.col("user_id").alias("ub"), F.col("ts").alias("tb")).withWatermark("tb", late)
    return a.join(b, F.expr(f"ua = ub AND tb > ta AND tb <= ta + INTERVAL {bound}")).select("src", "dst")


def dedup_edges(edges: DataFrame, late: str = "1 hour") -> DataFrame:
    """Each (src, dst) once within the watermark; ts is the event time."""
    return edges.withWatermark("ts", late).dropDuplicatesWithinWatermark(["src", "dst"])


def running_rank(events: DataFrame) -> DataFrame:
    """event_id, rank: the running sum in cents per user, kept as state. Events of a user must come in order over the batches."""

    def run(key, batches: Iterator[pd.DataFrame], state):
        total = state.get[0] if state.exists else 0
        rows = pd.concat(list(batches)).sort_values(["ts", "event_id"])
        rank = total + rows["cents"].cumsum()
        state.update((int(rank.iloc[-1]),))
        yield pd.DataFrame({"event_id": rows["event_id"], "rank": rank})

    cents = F.round(F.col("value") * 100).cast("long").alias("cents")
    return events.select("event_id", "user_id", "ts", cents).groupBy("user_id").applyInPandasWithState(run, "event_id long, rank long", "total long", "append", "NoTimeout")


class Components:
    """Labels kept up to date under edge insertions: labels so far are a valid forest, so each batch joins only the labels that its edges touch."""

    def __init__(self, spark: SparkSession):
        self.labels = spark.createDataFrame([], "id long, comp long")

    def __call__(self, edges: DataFrame, batch_id: int) -> None:
        from farfield.algorithms.run import components
        from farfield.sources.graph import Graph

        ends = edges.select(F.col("src").alias("id")).union(edges.select("dst")).distinct()
        all_ = ends.join(self.labels, "id", "full_outer").select("id", F.coalesce("comp", "id").alias("comp"))
        all_, _ = materialise(all_, "labels")
        a, b = all_.select(F.col("id").alias("src"), F.col("comp").alias("x")), all_.select(F.col("id").alias("dst"), F.col("comp").alias("y"))
        links, _ = materialise(edges.select("src", "dst").join(a, "src").join(b, "dst").filter("x <> y").select(F.least("x", "y").alias("src"), F.greatest("x", "y").alias("dst")).distinct(), "links")
        if not links.isEmpty():
            ids = links.select(F.col("src").alias("id")).union(links.select("dst")).distinct()
            new = components(Graph.of(ids, links, False)).state.select(F.col("id").alias("c"), "D")
            all_, _ = materialise(all_.join(new, F.col("comp") == F.col("c"), "left").select("id", F.coalesce("D", "comp").alias("comp")), "labels")
        self.labels = all_


def replay(spark: SparkSession, df: DataFrame, parts: int, order: str) -> str:
    """A table as a directory of files in order, for streams over stored tables; a part is a range of the order and one file. Event times are made instants."""
    path = f"{shared_folder(spark)}/replay-{uuid.uuid4().hex}"
    df = df.select(*(F.col(c).cast("timestamp").alias(c) if t == "timestamp_ntz" else F.col(c) for c, t in df.dtypes))
    cut, _ = materialise(df.repartitionByRange(parts, order).withColumn("_n", F.spark_partition_id() + 1), "cut")
    for k in range(1, parts + 1):
        cut.filter(F.col("_n") == k).drop("_n").coalesce(1).write.mode("overwrite" if k == 1 else "append").parquet(path)
    return path
