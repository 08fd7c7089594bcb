"""Shared plumbing of the training-data operators."""

from __future__ import annotations

import ctypes
import os
import re
import sys
import tempfile
import uuid
from collections.abc import Callable, Iterator

import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.window import Window

#: The columns of `documents`; every pipeline stage but the last returns them.
DOCUMENT_COLUMNS = ("doc_id", "text", "lang", "source", "n_chars")

#: Words are runs of anything but ASCII white space.
WORD = r"[^\x20\x09-\x0D]+"
#: What a worker keeps between the tasks of an operator, by its name: functions that drop it.
KEPT: dict[str, Callable[[], None]] = {}
_TRIM = getattr(ctypes.CDLL(None), "malloc_trim", None)
#: The rows of a hot key are dealt to so many tasks.
SALTS = 16


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def let_workers_import(spark: SparkSession) -> None:
    """Puts this checkout on the Python workers' path, wherever the driver was started."""
    root = os.path.dirname(os.path.dirname(os.path.dirname(os.path.abspath(__file__))))
    sc = spark.sparkContext
    path = sc.environment.get("PYTHONPATH", "")
    if root not in path.split(os.pathsep):
        sc.environment["PYTHONPATH"] = os.pathsep.join(x for x in (root, path) if x)
    if root not in sys.path:
        sys.path.append(root)


def scratch(spark: SparkSession) -> str:
    """The shared folder of the cluster. A folder of our own only where none is set and all runs on this machine, as in tests."""
    sc = spark.sparkContext
    named = sc.getConf().get("spark.checkpoint.dir")
    if named:
        return named.rstrip("/")
    if not sc._jsc.sc().getCheckpointDir().isDefined():
        if not re.fullmatch(r"local(\[[^\]]*\])?", sc.master):
            raise RuntimeError("spark.checkpoint.dir must name a folder that driver and executors share")
        sc.setCheckpointDir(tempfile.mkdtemp(prefix="farfield-"))
    return sc._jsc.sc().getCheckpointDir().get().rstrip("/")


def _file(spark: SparkSession, path: str):
    where = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(path)
    return where.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()), where


def _written(df: DataFrame, name: str) -> tuple[DataFrame, str]:
    spark = df.sparkSession
    path = f"{scratch(spark)}/{name}-{uuid.uuid4().hex}"
    df.write.parquet(path)
    fs, where = _file(spark, path)
    fs.deleteOnExit(where)
    return spark.read.schema(df.schema).parquet(path), path


def written(df: DataFrame, name: str) -> DataFrame:
    """df as a Parquet table in the shared folder: lineage ends there, and lost executors cost no recomputation."""
    return _written(df, name)[0]


class Generations:
    """Tables of an iteration: a new one replaces the one before, whose files go. Only the newest may be read."""

    def __init__(self, name: str):
        self.name, self.path = name, None

    def written(self, df: DataFrame) -> DataFrame:
        old = self.path
        out, self.path = _written(df, self.name)
        if old:
            fs, where = _file(df.sparkSession, old)
            fs.delete(where, True)
        return out


def looked_up(rows: DataFrame, key: str, found: DataFrame, found_key: str, spread: str) -> DataFrame:
    """rows with what found, one row a key, says of their key; null if nothing. The rows of a key, of which one may have most, are
    dealt to SALTS tasks by the column `spread`, and found is sent to each."""
    salt = F.pmod(F.xxhash64(spread), F.lit(SALTS)).cast("int")
    each = found.withColumn("__to", F.explode(F.sequence(F.lit(0), F.lit(SALTS - 1))))
    dealt = rows.withColumn("__salt", salt)
    return dealt.join(each, (dealt[key] == each[found_key]) & (F.col("__salt") == F.col("__to")), "left").drop("__salt", "__to")


def slices(batches: Iterator[pa.RecordBatch], rows: int = 256, keeps: str | None = None) -> Iterator[pa.RecordBatch]:
    """Batches in short slices, so that what a worker makes of one is small. A worker lives on from task to task, so it first drops what tasks of other operators
    kept, and in the end gives back what Arrow and the C library hold."""
    for name, forget in KEPT.items():
        if name != keeps:
            forget()
    for b in batches:
        for at in range(0, b.num_rows, rows):
            yield b.slice(at, rows)
    pa.default_memory_pool().release_unused()
    if _TRIM is not None:
        _TRIM(0)


def n_words(text: Column) -> Column:
    """Number of words, 0 for null."""
    return F.coalesce(F.regexp_count(text, F.lit(WORD)), F.lit(0)).cast("long")


def bucketed_rank(df: DataFrame, key: str, order: list[Column], bucket: Column, name: str) -> DataFrame:
    """Adds `name`: the rank from 0 of each row within key, by (bucket, order).

    A plain window would bring all rows of a hot key together. Here rows are ranked within (key, bucket) and
    shifted by the bucket's place, a prefix sum over one row per (key, bucket). Ties beyond `order` are broken
    arbitrarily; give an order that leaves none between different rows.
    """
    b, n, before = f"__b_{name}", f"__n_{name}", f"__p_{name}"
    with_bucket = df.withColumn(b, bucket)
    sizes = with_bucket.groupBy(key, b).agg(F.count(F.lit(1)).alias(n))
    places = sizes.withColumn(
        before, F.sum(n).over(Window.partitionBy(key).orderBy(b).rowsBetween(Window.unboundedPreceding, 0)) - F.col(n)
    ).drop(n)
    own = Window.partitionBy(key, b).orderBy(*order)
    ranked = with_bucket.withColumn(name, F.row_number().over(own) - 1)
    places = places.withColumnsRenamed({key: f"__k_{name}", b: f"__b2_{name}"})
    return (
        ranked.join(places, ranked[key].eqNullSafe(places[f"__k_{name}"]) & (ranked[b] == places[f"__b2_{name}"]))
        .withColumn(name, (F.col(name) + F.col(before)).cast("long"))
        .drop(b, before, f"__k_{name}", f"__b2_{name}")
    )


def bitmaps(rows: DataFrame, keys: list[str], place: str) -> DataFrame:
    """One row per keys: bits array<long>, where bit p % 64 of bits[p / 64] is set for each place p (from 0) of the rows.

    Places come together as bits before and after the shuffle, so their number and repeats cost little.
    """
    bit = F.call_function("shiftleft", F.lit(1).cast("long"), F.pmod(place, F.lit(64)).cast("int"))
    by_word = rows.groupBy(*keys, F.floor(F.col(place) / 64).cast("int").alias("__w")).agg(F.bit_or(bit).alias("__bits"))
    whole = by_word.groupBy(*keys).agg(F.map_from_entries(F.collect_list(F.struct("__w", "__bits"))).alias("__m"), F.max("__w").alias("__top"))
    return whole.select(
        *keys,
        F.transform(F.sequence(F.lit(0), "__top"), lambda w: F.coalesce(F.element_at("__m", w), F.lit(0).cast("long"))).alias("bits"),
    )


def has_bit(bits: Column, place: Column) -> Column:
    """Whether a place is set; false if bits is null or ends before it."""
    word = F.coalesce(F.get(bits, F.floor(place / 64).cast("int")), F.lit(0).cast("long"))
    return F.getbit(word, F.pmod(place, F.lit(64)).cast("int")) == 1
