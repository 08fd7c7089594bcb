"""Exact nearest neighbours by blocks against all pairs."""

import time

import numpy as np
import pytest

from farfield.operators import nearest as N
from farfield.sources import builders as B


def by_hand(rows, k):
    out = set()
    for i, x in rows:
        near = sorted((sum((p - q) ** 2 for p, q in zip(x, y)), j) for j, y in rows if j != i)[:k]
        out |= {(i, j, v) for v, j in near}
    return out


@pytest.mark.parametrize("most, blocks", [(3, 40), (900, 40), (900, 2000), (3_000_000, 40), (1 << 26, 40)])
def test_same_as_all_pairs(spark, monkeypatch, most, blocks):
    monkeypatch.setattr(N, "LEAST_BLOCK", blocks)
    rng = np.random.default_rng(most)
    rows = [(int(i), [int(c) for c in x]) for i, x in zip(rng.permutation(150) * 7 - 300, rng.integers(-most, most, (150, 5)))]
    rows += [(i + 5000, x) for i, x in rows[:40]]  # copies: ties by id
    rows += [(9001, [1 << 28] * 5), (9002, [-(1 << 28)] * 5)]  # too long for exact products
    got = [tuple(r) for r in N.nearest(spark.createDataFrame(rows, "id long, x array<long>"), 5).collect()]
    assert len(got) == len(set(got)) and set(got) == by_hand(rows, 5)


def test_few_and_no_rows(spark):
    kind = "id long, x array<long>"
    assert N.nearest(spark.createDataFrame([], kind), 5).count() == 0
    assert N.nearest(spark.createDataFrame([(1, [1, 2])], kind), 5).count() == 0
    assert sorted(map(tuple, N.nearest(spark.createDataFrame([(1, [1, 2]), (2, [1, 4])], kind), 5).collect())) == [(1, 2, 4), (2, 1, 4)]


def test_ten_thousand_vectors_in_a_minute(spark, tmp_path):
    x = np.random.default_rng(5).normal(size=(10_000, 64))
    rows = [(i, (v / np.linalg.norm(v)).tolist(), 0) for i, v in enumerate(x)]
    spark.createDataFrame(rows, "vec_id long, embedding array<float>, label int").write.parquet(f"{tmp_path}/embeddings.parquet")
    began = time.time()
    assert B.vec_knn(spark, str(tmp_path)).edges.count() >= 50_000
    assert time.time() - began < 60
