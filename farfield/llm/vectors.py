"""What the two vector searches share: valid vectors, and a join of row blocks with query blocks.

Rows are dealt by (block, chunk); a chunk is part of a block, by hash of the id, of about `CHUNK` rows. Queries go, in strips of
about `STRIP`, to the chunks of those blocks that they have to see. A task holds one chunk and one strip at a time,
whatever the size of a block or the number of queries, and returns k rows per query at most.
"""

from __future__ import annotations

from collections.abc import Callable

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

CHUNK, STRIP = 2048, 2048


def valid(vectors: DataFrame, zero: bool) -> DataFrame:
    """(vec_id, v array<double>) of the vectors that take part: not null, all components finite, and not all zero if zero is False.

    Rows without an id take no part, and of rows with several lengths only those of the commonest length (ties: the longer).
    """
    x = F.col("embedding").cast("array<double>")
    ok = F.forall(x, lambda c: c.isNotNull() & ~F.isnan(c) & (F.abs(c) < F.lit(float("inf"))))
    rows = vectors.filter(F.col("vec_id").isNotNull() & F.col("embedding").isNotNull() & (F.size("embedding") > 0)).filter(ok)
    if not zero:
        rows = rows.filter(F.exists(x, lambda c: c != 0))
    rows = rows.select(F.col("vec_id").cast("long").alias("vec_id"), x.alias("v"))
    common = rows.groupBy(F.size("v").alias("d")).count().orderBy(F.desc("count"), F.desc("d")).limit(1).collect()
    return rows.filter(F.size("v") == (common[0]["d"] if common else 0))


def matrix(column: pa.Array | pa.ChunkedArray, n: int) -> np.ndarray:
    """Of a column of n lists of equal length."""
    if not n:
        return np.zeros((0, 0))
    parts = column.chunks if isinstance(column, pa.ChunkedArray) else [column]
    return np.concatenate([p.flatten().to_numpy(zero_copy_only=False).reshape(len(p), -1) for p in parts if len(p)])


def chunk_of(n_chunks: Column) -> Column:
    return F.pmod(F.xxhash64("vec_id"), n_chunks).cast("int")


def strips(queries: DataFrame) -> int:
    return max(1, -(-queries.count() // STRIP))


def blocked_search(rows: DataFrame, queries: DataFrame, n_strips: int, best: Callable[[pa.Table, pa.Table], tuple], k: int, ascending: bool, score: str) -> DataFrame:
    """rows: (block, chunk, ...); queries: (query_id, block, chunk, ...). best takes a chunk's rows and a strip's queries and gives arrays
    (query_id, vec_id, score) with k a query at most; the k best overall come back, ties to the smaller vec_id."""
    kind = pa.int64() if score == "long" else pa.float64()

    def search(left: pa.Table, right: pa.Table) -> pa.Table:
        q, v, s = best(left, right) if left.num_rows and right.num_rows else ((), (), ())
        return pa.table({"query_id": pa.array(q, pa.int64()), "vec_id": pa.array(v, pa.int64()), "score": pa.array(s, kind)})

    dealt = rows.withColumn("strip", F.explode(F.sequence(F.lit(0), F.lit(n_strips - 1)))) if n_strips > 1 else rows.withColumn("strip", F.lit(0))
    asked = queries.withColumn("strip", F.pmod(F.xxhash64("query_id"), F.lit(n_strips)).cast("int"))
    key = ["block", "chunk", "strip"]
    found = dealt.groupBy(*key).cogroup(asked.groupBy(*key)).applyInArrow(search, f"query_id long, vec_id long, score {score}")
    order = [F.col("score") if ascending else F.col("score").desc(), F.col("vec_id")]
    ranked = found.withColumn("rank", F.row_number().over(Window.partitionBy("query_id").orderBy(*order)))
    return ranked.filter(F.col("rank") <= k).select("query_id", "rank", "vec_id", "score")


def first_k(query: np.ndarray, value: np.ndarray, ids: np.ndarray, k: int) -> np.ndarray:
    """Places of the k least (value, id) of each query."""
    order = np.lexsort((ids, value, query))
    q = query[order]
    start = np.flatnonzero(np.concatenate([[True], q[1:] != q[:-1]])) if len(q) else np.zeros(0, int)
    nth = np.arange(len(q)) - np.repeat(start, np.diff(np.append(start, len(q))))
    return order[nth < k]
