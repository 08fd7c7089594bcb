"""Approximate nearest neighbours by an inverted multi-index.

Vectors are cut into two halves, and each half is quantised on its own. A pair of centroids is a cell; with c centroids a half
there are c^2. For each query a heap yields the cells by the sum of the two distances, without sorting all of them, until
these cells hold a share of all rows. The rows in the cells are then reranked by their exact distance.

The number of centroids grows with the square root of the rows, so that a cell holds `PER_CELL`, up to `MOST`. Centroids are fitted on one half of at
most `FIT_ON` rows (of least hash), and the share on the other: it is what held `RECALL` of the true neighbours of `TRIED` rows. It falls as
the table grows, and each row of the result names it. All rows are indexed. On vectors without any structure, like random directions, the
share is large; on clustered ones it is small.

Defined results: vectors that are null, zero, without id, or hold null or non-finite components take no part; nor do those of another
length than the commonest; rows that share the query's id are its own; equal distances go to the smaller vec_id; no query or no
candidate gives no rows; extra columns are not read.
"""

from __future__ import annotations

import heapq
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from farfield.llm import vectors as V
from farfield.llm.common import let_workers_import, written

FIT_ON, TRIED, RECALL = 8192, 256, 0.95
#: Rows a cell, and the least and most centroids of a half; the most bounds the table of cells, and the heap's work for a query.
PER_CELL, FEWEST, MOST = 10, 16, 512
K = 10
QUERIES = 100


def kmeans(x: np.ndarray, c: int, rounds: int = 12, seed: int = 1) -> np.ndarray:
    at = np.unique(x, axis=0)
    if len(at) <= c:
        return at
    means = at[np.random.default_rng(seed).choice(len(at), c, replace=False)]
    for _ in range(rounds):
        own = nearest(x, means)
        n = np.bincount(own, minlength=c)
        total = np.zeros_like(means)
        np.add.at(total, own, x)
        means = np.where(n[:, None] > 0, total / np.maximum(n, 1)[:, None], means)
    return means


def squared(x: np.ndarray, y: np.ndarray) -> np.ndarray:
    return np.maximum((x * x).sum(1)[:, None] + (y * y).sum(1)[None] - 2 * x @ y.T, 0)


def nearest(x: np.ndarray, means: np.ndarray) -> np.ndarray:
    return np.concatenate([squared(x[i : i + 4096], means).argmin(1) for i in range(0, len(x), 4096)]) if len(x) else np.zeros(0, int)


def by_distance(a: np.ndarray, b: np.ndarray) -> Iterator[tuple[int, int]]:
    """Pairs (i, j) by a[i] + b[j], least first, from a heap that holds one open pair per row at most."""
    ia, ib = np.argsort(a, kind="stable"), np.argsort(b, kind="stable")
    heap = [(a[ia[0]] + b[ib[0]], 0, 0)]
    while heap:
        _, i, j = heapq.heappop(heap)
        yield int(ia[i]), int(ib[j])
        if j + 1 < len(ib):
            heapq.heappush(heap, (a[ia[i]] + b[ib[j + 1]], i, j + 1))
        if j == 0 and i + 1 < len(ia):
            heapq.heappush(heap, (a[ia[i + 1]] + b[ib[0]], i + 1, 0))


def centroids_for(rows: int) -> int:
    """Centroids of a half, so that cells hold PER_CELL of the rows: their number grows with the square root of the rows."""
    return int(min(MOST, max(FEWEST, (rows / PER_CELL) ** 0.5)))


class MultiIndex:
    """sample: half of it is for the centroids, half for the share; rows: of the table that it is from."""

    def __init__(self, sample: np.ndarray, rows: int, centroids: int | None = None, k: int = K, recall: float = RECALL):
        self.half = sample.shape[1] // 2
        learn = sample[::2]
        c = centroids or centroids_for(rows)
        self.means = kmeans(learn[:, : self.half], c), kmeans(learn[:, self.half :], c)
        self.share = self._share(sample[1::2], rows, k, recall)

    def cells(self, x: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        return nearest(x[:, : self.half], self.means[0]), nearest(x[:, self.half :], self.means[1])

    def visited(self, x: np.ndarray, counts: np.ndarray, enough: float) -> Iterator[tuple[int, int]]:
        """Cells for one query until they hold enough rows; empty ones are passed over."""
        got = 0
        for i, j in by_distance(squared(x[None, : self.half], self.means[0])[0], squared(x[None, self.half :], self.means[1])[0]):
            if counts[i, j]:
                if got >= enough:
                    return
                got += counts[i, j]
                yield i, j

    def histogram(self, i: np.ndarray, j: np.ndarray) -> np.ndarray:
        counts = np.zeros((len(self.means[0]), len(self.means[1])), np.int64)
        np.add.at(counts, (i, j), 1)
        return counts

    def _share(self, sample: np.ndarray, rows: int, k: int, recall: float) -> float:
        """Share of the rows to look at, from the places of true neighbours in the order of cells, among rows that the centroids have not seen.
        k neighbours of the table are fewer in a sample of it, so the share falls as the table grows."""
        near = max(1, -(-k * len(sample) // max(rows, 1)))
        if len(sample) <= 10 * near:
            return 1.0
        i, j = self.cells(sample)
        counts, places = self.histogram(i, j), []
        for q in range(min(TRIED, len(sample))):
            d = squared(sample[q : q + 1], sample)[0]
            d[q] = np.inf
            true = np.argpartition(d, near)[:near]
            before, got = np.zeros_like(counts), 0
            for a, b in self.visited(sample[q], counts, len(sample)):
                before[a, b] = got  # a cell is read if fewer than enough were seen before it
                got += counts[a, b]
            places.append(before[i[true], j[true]])
        return min(1.0, float(np.quantile(np.concatenate(places), recall, method="higher") + 1) / len(sample))


def search(vectors: DataFrame, every: int = QUERIES, k: int = K, centroids: int | None = None, recall: float = RECALL) -> DataFrame:
    """query_id, rank, vec_id, score: the k nearest of each row whose vec_id is divisible by every; share: of the rows that a query looks at."""
    spark = vectors.sparkSession
    let_workers_import(spark)
    rows = V.valid(vectors, zero=False)
    sample = [r["v"] for r in rows.orderBy(F.xxhash64("vec_id"), "vec_id").limit(FIT_ON).collect()]
    if not sample:
        return spark.createDataFrame([], "query_id long, rank int, vec_id long, score double, share double")
    index = spark.sparkContext.broadcast(MultiIndex(np.array(sample), rows.count(), centroids, k, recall))

    def code(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            i, j = index.value.cells(V.matrix(b.column(1), b.num_rows)) if b.num_rows else ((), ())
            yield pa.RecordBatch.from_arrays([*b.columns, pa.array(i, pa.int32()), pa.array(j, pa.int32())], names=["vec_id", "v", "block", "j"])

    coded = written(rows.mapInArrow(code, "vec_id long, v array<double>, block int, j int"), "multi-index")
    m = index.value
    counts = np.zeros((len(m.means[0]), len(m.means[1])), np.int64)
    for r in coded.groupBy("block", "j").count().collect():  # one row a cell, c^2 at most
        counts[r["block"], r["j"]] = r["count"]
    chunks = np.maximum(1, -(-counts.sum(1) // V.CHUNK)).tolist()
    enough = int(np.ceil(m.share * counts.sum()))

    def ask(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            if not b.num_rows:
                continue
            x, take, block, js = V.matrix(b.column(1), b.num_rows), [], [], []
            for q in range(b.num_rows):
                seen: dict[int, list[int]] = {}
                for i, j in index.value.visited(x[q], counts, enough):
                    seen.setdefault(i, []).append(j)
                take += [q] * len(seen)
                block += seen.keys()
                js += seen.values()
            at = pa.array(take, pa.int64())
            yield pa.RecordBatch.from_arrays([b.column(0).take(at), b.column(1).take(at), pa.array(block, pa.int32()), pa.array(js, pa.list_(pa.int32()))], names=["query_id", "v", "block", "js"])

    def best(left: pa.Table, right: pa.Table) -> tuple:
        rv, qv = V.matrix(left["v"], left.num_rows), V.matrix(right["v"], right.num_rows)
        rid, qid = left["vec_id"].to_numpy(), right["query_id"].to_numpy()
        cell = np.zeros((len(qv), counts.shape[1]), bool)
        lists = right["js"].combine_chunks()
        cell[np.repeat(np.arange(len(qv)), np.diff(lists.offsets.to_numpy())), lists.flatten().to_numpy()] = True
        j, out = left["j"].to_numpy(), []
        for at in range(0, len(qv), 256):
            q = slice(at, at + 256)
            d = squared(qv[q], rv)
            d[~cell[q][:, j] | (qid[q][:, None] == rid[None])] = np.inf
            least = np.partition(d, min(k, d.shape[1]) - 1, axis=1)[:, min(k, d.shape[1]) - 1 : min(k, d.shape[1])]
            # what the faster formula cannot tell apart is told apart by the exact one
            unsure = 1e-9 * ((qv[q] ** 2).sum(1)[:, None] + (rv**2).sum(1).max())
            a, b = np.nonzero((d <= least + unsure) & (d < np.inf))
            exact = np.sqrt(((qv[q][a] - rv[b]) ** 2).sum(1))
            top = V.first_k(a, exact, rid[b], k)
            out.append((qid[q][a[top]], rid[b[top]], exact[top]))
        return tuple(np.concatenate(x) for x in zip(*out))

    n_chunks = F.element_at(F.array(*map(F.lit, chunks)), F.col("block") + 1)
    dealt = coded.withColumn("chunk", V.chunk_of(n_chunks)).select("vec_id", "v", "j", "block", "chunk")
    queries = coded.filter(F.pmod("vec_id", F.lit(every)) == 0).select("vec_id", "v")
    n_strips = V.strips(queries)
    # spread before the heaps, which are the dear part
    asked = queries.repartition("vec_id").mapInArrow(ask, "query_id long, v array<double>, block int, js array<int>")
    asked = asked.withColumn("chunk", F.explode(F.sequence(F.lit(0), n_chunks - 1)))
    return V.blocked_search(dealt, asked, n_strips, best, k, True, "double").withColumn("share", F.lit(float(m.share)))


def op4_multi_index(vectors: DataFrame) -> DataFrame:
    return search(vectors)
