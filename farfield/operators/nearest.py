"""Exact nearest neighbours of integer vectors, blocks of rows against blocks of rows."""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from farfield.plans.store import let_workers_import, materialise

#: Rows of a block at least (fewer if the table has not so many) and at most, and the rows of one that are compared with another at a time.
LEAST_BLOCK, MOST_BLOCK, AT_ONCE = 1024, 16_384, 256
#: Squared lengths below this are summed without rounding in double precision, and those below the other in single precision.
EXACT, EXACT_SINGLE = 1 << 50, 1 << 22


def _least(dist: np.ndarray, k: int) -> tuple[np.ndarray, np.ndarray]:
    """(row, column) of all distances that are not above the k-th least of their row."""
    rows, n = dist.shape
    if n > 64 * k:
        # k groups have a least value that is not above the k-th least of these, so the k-th least of all is not above it
        whole = n // 64 * 64
        tops = dist[:, :whole].reshape(rows, -1, 64).min(axis=2)
        bound = np.partition(tops, k - 1, axis=1)[:, k - 1]
    else:
        bound = np.partition(dist, k - 1, axis=1)[:, k - 1] if n > k else np.full(rows, np.inf)
    return np.nonzero(dist <= bound[:, None])


def block_nearest(ids: np.ndarray, x: np.ndarray, other_ids: np.ndarray, y: np.ndarray, k: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(id, other id, squared distance): the k nearest rows of y with another id for each row of x, ties to the smaller id."""
    got: list[list[np.ndarray]] = [[], [], []]
    nx, ny = (x * x).sum(axis=1), (y * y).sum(axis=1)
    for at in range(0, len(x), AT_ONCE):
        mine = ids[at : at + AT_ONCE]
        dist = x[at : at + AT_ONCE] @ y.T
        dist *= -2
        dist += nx[at : at + AT_ONCE, None]
        dist += ny[None]
        same = np.isin(mine, other_ids)
        for r in np.flatnonzero(same):
            dist[r, other_ids == mine[r]] = np.inf
        row, col = _least(dist, k)
        val = dist[row, col]
        order = np.lexsort((other_ids[col], val, row))
        row, col, val = row[order], col[order], val[order]
        nth = np.arange(len(row)) - np.searchsorted(row, row)
        keep = (nth < k) & np.isfinite(val)
        for out, new in zip(got, (mine[row[keep]], other_ids[col[keep]], val[keep].astype(np.int64))):
            out.append(new)
    return tuple(np.concatenate([np.zeros(0, np.int64), *g]) for g in got)


def nearest(vectors: DataFrame, k: int) -> DataFrame:
    """(a, b, val): for each row of (id, x array<long>) the k rows with another id that are nearest by squared distance, ties to the smaller id. All pairs
    are looked at, by products of matrices without rounding. A task holds two blocks of rows and gives back k rows for each of the one. Vectors that are
    null, hold nulls, differ in length from the most or are too long for exact products are compared pair by pair."""
    let_workers_import(vectors.sparkSession)
    rows, _ = materialise(vectors.select("id", "x"), "vectors")
    common = rows.filter("x IS NOT NULL").groupBy(F.size("x").alias("d")).count().orderBy(F.desc("count"), F.desc("d")).limit(1).collect()
    d = common[0]["d"] if common else 0
    # doubles can't overflow; what they round is far above the limit
    square = F.aggregate("x", F.lit(0.0), lambda s, c: s + c.cast("double") * c.cast("double"))
    fit = F.coalesce((F.size("x") == d) & F.col("id").isNotNull() & F.lit(d > 0) & (square < F.lit(float(EXACT))), F.lit(False))
    split = rows.withColumn("square", square).withColumn("fit", fit)
    seen = split.agg(F.sum(F.col("fit").cast("long")).alias("n"), F.sum((~F.col("fit")).cast("long")).alias("odd"), F.max(F.when(F.col("fit"), F.col("square"))).alias("most")).first()
    n, kind = seen["n"] or 0, np.float32 if (seen["most"] or 0) < EXACT_SINGLE else np.float64
    blocks = max(1, min(-(-n // LEAST_BLOCK), max(6, -(-n // MOST_BLOCK))))

    def pack(block: pa.Table) -> pa.Table:
        x = np.concatenate([c.flatten().to_numpy(zero_copy_only=False) for c in block["x"].chunks]).astype(kind)
        ids = block["id"].to_numpy().astype(np.int64)
        return pa.table({"block": block["block"][:1], "ids": pa.array([ids.tobytes()], pa.binary()), "x": pa.array([x.tobytes()], pa.binary())})

    dealt = split.filter("fit").select("id", "x", F.pmod(F.xxhash64("id", "x"), F.lit(blocks)).cast("int").alias("block"))
    packed, _ = materialise(dealt.groupBy("block").applyInArrow(pack, "block int, ids binary, x binary"), "blocks")

    def search(left: pa.Table, right: pa.Table) -> pa.Table:
        found: tuple = ((), (), ())
        if left.num_rows and right.num_rows:
            a, b = (np.frombuffer(t["ids"][0].as_py(), np.int64) for t in (left, right))
            x, y = (np.frombuffer(t["x"][0].as_py(), kind).reshape(-1, d) for t in (left, right))
            found = block_nearest(a, x, b, y, k)
        return pa.table({c: pa.array(v, pa.int64()) for c, v in zip(("a", "b", "val"), found)})

    every = F.explode(F.sequence(F.lit(0), F.lit(blocks - 1)))
    mine, theirs = packed.withColumn("other", every), packed.withColumnRenamed("block", "other").withColumn("block", every)
    found = mine.groupBy("block", "other").cogroup(theirs.groupBy("block", "other")).applyInArrow(search, "a long, b long, val long")
    if seen["odd"]:
        found = found.union(_pair_by_pair(split))
    return found.withColumn("r", F.row_number().over(Window.partitionBy("a").orderBy("val", "b"))).filter(F.col("r") <= k).select("a", "b", "val")


def _pair_by_pair(split: DataFrame) -> DataFrame:
    """(a, b, val) of the pairs with a row that does not fit."""
    side = lambda a: split.select(F.col("id").alias(a), F.col("x").alias(f"x{a}"), F.col("fit").alias(f"fit{a}"))
    dist = F.aggregate(F.zip_with("xa", "xb", lambda p, q: (p - q) * (p - q)), F.lit(0).cast("long"), lambda s, y: s + y)
    return side("a").join(side("b"), (F.col("a") != F.col("b")) & ~(F.col("fita") & F.col("fitb"))).select("a", "b", dist.alias("val"))
