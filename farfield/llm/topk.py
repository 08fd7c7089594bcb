"""Exact top-k inner products by norm-bucketed retrieval.

Vectors are grouped by length into buckets. Each query gets a threshold from the `SEEDS` longest vectors: its k-th best
product with them, which the answer cannot fall below. A bucket whose longest vector times the query's length stays below the threshold
is never sent to the query. For the others the local cosine threshold, threshold / (length of query * longest in chunk),
chooses how to prune: if it is high, by coordinates (a unit vector within that angle of the query has its largest query coordinates
within narrow bounds), else by length (a prefix of the chunk, which is sorted). What is left is verified by exact integer
products. All bounds are rounded outwards, so results are exact.

Defined results: components become floor(256 x) as long; vectors that are null, without id, or hold null or non-finite components take no
part, zero vectors do; nor do those of another length than the commonest; rows that share the query's id are its own; equal scores go
to the smaller vec_id; no query or no candidate gives no rows; extra columns are not read.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from farfield.llm import vectors as V
from farfield.llm.common import let_workers_import, written

SCALE, K, QUERIES = 256, 5, 50
SEEDS, BUCKETS = 1024, 64
#: From this cosine on coordinates prune; so many of them are looked at.
COORDINATES_FROM, COORDINATES = 0.5, 3
_OUT = 1e-9


def products(rows: np.ndarray, query: np.ndarray) -> np.ndarray:
    """Exact integer inner products: by floating point where all sums are exact in it, else by integers."""
    if rows.size and float(np.abs(rows).max()) * float(np.abs(query).max()) * rows.shape[1] < 2**53:
        return (rows.astype(np.float64) @ query.astype(np.float64).T).astype(np.int64)
    return rows @ query.T


def best_products(rows: np.ndarray, ids: np.ndarray, norms: np.ndarray, query: np.ndarray, own: int, norm: float, floor: float, k: int) -> tuple[np.ndarray, np.ndarray]:
    """(ids, scores) of at most k rows that can be among the query's best; rows are sorted by norm, longest first."""
    most = norm * norms[0]
    local = floor / most if most > 0 else (-np.inf if floor <= 0 else np.inf)
    if local > 1 + _OUT:
        return ids[:0], np.zeros(0, np.int64)
    if local >= COORDINATES_FROM:
        unit, t = query / norm, min(local * (1 - _OUT), 1.0)
        keep = np.ones(len(rows), bool)
        for f in np.argsort(-np.abs(unit))[:COORDINATES]:
            slack = np.sqrt(max(0.0, (1 - t * t) * (1 - unit[f] ** 2)))
            low = -1.0 if -unit[f] >= t else unit[f] * t - slack
            high = 1.0 if unit[f] >= t else unit[f] * t + slack
            c = rows[:, f]
            keep &= (c >= (low - _OUT) * norms) & (c <= (high + _OUT) * norms)
        at = np.flatnonzero(keep)
    elif floor > 0:
        at = np.arange(np.searchsorted(-norms, -floor / norm * (1 - _OUT), side="right"))
    else:
        at = np.arange(len(rows))
    at = at[ids[at] != own]
    scores = products(rows[at], query[None])[:, 0] if len(at) else np.zeros(0, np.int64)
    if floor > -np.inf:
        enough = scores >= floor
        at, scores = at[enough], scores[enough]
    top = np.lexsort((ids[at], -scores))[:k]
    return ids[at[top]], scores[top]


def search(vectors: DataFrame, every: int = QUERIES, k: int = K, scale: int = SCALE) -> DataFrame:
    """query_id, rank, vec_id, score: the k highest products of each row whose vec_id is divisible by every."""
    spark = vectors.sparkSession
    let_workers_import(spark)
    ints = V.valid(vectors, zero=True).select("vec_id", F.transform("v", lambda x: F.floor(x * scale)).alias("v"))
    square = F.aggregate("v", F.lit(0.0), lambda a, x: a + x.cast("double") * x.cast("double"))
    rows = written(ints.withColumn("norm", F.sqrt(square)), "norms")
    seeds = [(r["vec_id"], r["v"]) for r in rows.orderBy(F.desc("norm"), "vec_id").limit(SEEDS).collect()]
    if not seeds:
        return spark.createDataFrame([], "query_id long, rank int, vec_id long, score long")
    seed_ids, seed_rows = np.array([i for i, _ in seeds]), np.array([v for _, v in seeds], np.int64)
    edges = sorted(set(rows.approxQuantile("norm", [b / BUCKETS for b in range(1, BUCKETS)], 1 / (4 * BUCKETS))))
    bucket = F.size(F.filter(F.array(*map(F.lit, edges)), lambda e: e <= F.col("norm")))
    bucketed = rows.withColumn("block", bucket)
    # one row per bucket, BUCKETS at most
    known = {r["block"]: (r["n"], r["longest"]) for r in bucketed.groupBy("block").agg(F.count(F.lit(1)).alias("n"), F.max("norm").alias("longest")).collect()}
    chunks = [max(1, -(-known.get(b, (0, 0))[0] // V.CHUNK)) for b in range(len(edges) + 1)]
    longest = np.array([known[b][1] if b in known else -1.0 for b in range(len(edges) + 1)])

    def ask(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            if not b.num_rows:
                continue
            q, ids, norms = V.matrix(b.column(1), b.num_rows).astype(np.int64), b.column(0).to_numpy(), b.column(2).to_numpy()
            p = products(seed_rows, q).T.astype(np.float64)
            p[ids[:, None] == seed_ids[None]] = -np.inf
            floor = np.sort(p, axis=1)[:, -k] if p.shape[1] >= k else np.full(len(q), -np.inf)
            can = (longest >= 0)[None] & (norms[:, None] * np.maximum(longest, 0)[None] * (1 + _OUT) >= floor[:, None])
            at, block = np.nonzero(can)
            take = pa.array(at)
            yield pa.RecordBatch.from_arrays([*(c.take(take) for c in b.columns), pa.array(floor[at]), pa.array(block, pa.int32())], names=["query_id", "v", "norm", "floor", "block"])

    def best(left: pa.Table, right: pa.Table) -> tuple:
        norms = left["norm"].to_numpy()
        order = np.argsort(-norms, kind="stable")
        norms, rv, rid = norms[order], V.matrix(left["v"], left.num_rows).astype(np.int64)[order], left["vec_id"].to_numpy()[order]
        qv, qid = V.matrix(right["v"], right.num_rows).astype(np.int64), right["query_id"].to_numpy()
        qn, floor = right["norm"].to_numpy(), right["floor"].to_numpy()
        got = [best_products(rv, rid, norms, qv[i], qid[i], qn[i], floor[i], k) for i in range(len(qv))]
        return np.repeat(qid, [len(s) for _, s in got]), np.concatenate([v for v, _ in got]), np.concatenate([s for _, s in got])

    n_chunks = F.element_at(F.array(*map(F.lit, chunks)), F.col("block") + 1)
    dealt = bucketed.withColumn("chunk", V.chunk_of(n_chunks))
    queries = rows.filter(F.pmod("vec_id", F.lit(every)) == 0)
    n_strips = V.strips(queries)
    asked = queries.repartition("vec_id").mapInArrow(ask, "query_id long, v array<long>, norm double, floor double, block int")
    asked = asked.withColumn("chunk", F.explode(F.sequence(F.lit(0), n_chunks - 1)))
    return V.blocked_search(dealt, asked, n_strips, best, k, False, "long")


def op7_norm_buckets(vectors: DataFrame) -> DataFrame:
    return search(vectors)


ORACLE_SQL = """
WITH v AS (
  SELECT vec_id, list_transform(embedding, lambda x: floor(256 * CAST(x AS DOUBLE))) AS q
  FROM embeddings
  WHERE embedding IS NOT NULL AND len(list_filter(embedding, lambda x: x IS NULL OR NOT isfinite(x))) = 0
), s AS (
  SELECT a.vec_id AS query_id, b.vec_id, CAST(list_dot_product(a.q, b.q) AS BIGINT) AS score
  FROM v a JOIN v b ON a.vec_id % 50 = 0 AND a.vec_id <> b.vec_id
)
SELECT query_id, CAST(row_number() OVER (PARTITION BY query_id ORDER BY score DESC, vec_id) AS INTEGER) AS rank, vec_id, score
FROM s QUALIFY rank <= 5
"""
