"""Tables that end a lineage, in the folder that the cluster shares."""

from __future__ import annotations

import os
import re
import sys
import tempfile
import uuid

from pyspark.sql import DataFrame, SparkSession


def shared_folder(spark: SparkSession) -> str:
    """spark.checkpoint.dir if it is set; a folder of our own only where it is not and all runs on this machine, as in tests."""
    sc = spark.sparkContext
    named = sc.getConf().get("spark.checkpoint.dir")
    if named:
        return named.rstrip("/")
    if not sc._jsc.sc().getCheckpointDir().isDefined():
        if not re.fullmatch(r"local(\[[^\]]*\])?", sc.master):
            raise RuntimeError("spark.checkpoint.dir must name a folder that driver and executors share")
        sc.setCheckpointDir(tempfile.mkdtemp(prefix="farfield-"))
    return sc._jsc.sc().getCheckpointDir().get().rstrip("/")


def let_workers_import(spark: SparkSession) -> None:
    """Puts this checkout on the Python workers' path, wherever the driver was started."""
    root = os.path.dirname(os.path.dirname(os.path.dirname(os.path.abspath(__file__))))
    sc = spark.sparkContext
    path = sc.environment.get("PYTHONPATH", "")
    if root not in path.split(os.pathsep):
        sc.environment["PYTHONPATH"] = os.pathsep.join(x for x in (root, path) if x)
    if root not in sys.path:
        sys.path.append(root)


def _fs(spark: SparkSession, path: str):
    where = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(path)
    return where.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()), where


#: Tables of the catalogue that stand for bucketed files, by path.
_TABLES: dict[str, str] = {}


def materialise(df: DataFrame, name: str = "state", buckets: int | None = None, key: str = "id") -> tuple[DataFrame, str]:
    """df written as Parquet and read again, and where. The files go when the JVM ends, or by drop(). With buckets, rows are dealt by key to so many
    sorted files, and joins and sums by key need no exchange on this side."""
    spark = df.sparkSession
    path = f"{shared_folder(spark)}/{name}-{uuid.uuid4().hex}"
    fs, where = _fs(spark, path)
    if buckets:
        _TABLES[path] = f"farfield_{uuid.uuid4().hex}"
        df.repartition(buckets, key).write.bucketBy(buckets, key).sortBy(key).option("path", path).format("parquet").saveAsTable(_TABLES[path])
        fs.deleteOnExit(where)
        return spark.table(_TABLES[path]), path
    df.write.parquet(path)
    fs.deleteOnExit(where)
    return spark.read.schema(df.schema).parquet(path), path


def drop(spark: SparkSession, path: str) -> None:
    if path in _TABLES:
        spark.sql(f"DROP TABLE IF EXISTS {_TABLES.pop(path)}")
    fs, where = _fs(spark, path)
    fs.delete(where, True)
