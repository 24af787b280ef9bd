"""Exact search against brute force: repeated ids and rows, ties, odd vectors, tiles of any size."""

import numpy as np
import pytest
from pyspark.sql import functions as F

from erblock.llm import topk_search


def _check(spark, ids, vectors, k=5, **sizes):
    rows = spark.createDataFrame([(int(i), [float(x) / 256 for x in v], "y") for i, v in zip(ids, vectors, strict=True)], "vec_id long, embedding array<double>, score string")
    got = topk_search.top_k(rows, F.col("vec_id") % 5 == 0, k, **sizes).collect()
    want = topk_search.brute_force(np.array(ids), np.array(vectors, dtype=np.int64), sorted({int(i) for i in ids if i % 5 == 0}), k)
    assert sorted((r["query_id"], r["rank"], r["vec_id"], r["score"]) for r in got) == sorted(want)


@pytest.mark.parametrize("spread", [3, 40, 100_000, 1 << 22])
def test_against_brute_force(spark, spread):
    rng = np.random.default_rng(spread)
    vectors = rng.integers(-spread, spread, (300, 9))
    _check(spark, np.arange(300), vectors, shard_rows=70, group_rows=20)


def test_repeated_ids_and_rows(spark):
    rng = np.random.default_rng(1)
    vectors = rng.integers(-4, 4, (120, 3))
    ids = rng.integers(0, 30, 120)  # an id has several vectors, some of them equal
    ids[:20], vectors[:20] = 5, vectors[0]  # one row twenty times
    ids[20:40] = 10  # twenty vectors of one id
    vectors[40:60] = vectors[0]  # equal to the hot row, other ids
    _check(spark, ids, vectors, shard_rows=50)


def test_fewer_candidates_and_no_rows(spark):
    _check(spark, [5, 6, 7], [[1, 2], [3, 4], [-1, 0]])
    none = spark.createDataFrame([], "vec_id long, embedding array<double>")
    assert topk_search.top_k(none, F.col("vec_id") % 5 == 0).count() == 0


def test_stops_early_only_on_proof():
    rng = np.random.default_rng(2)
    x = rng.integers(-5, 6, (4000, 8))
    x[:12] += 3000  # a few far ahead
    shard = topk_search.Shard(np.arange(4000), x, 5)
    q = np.abs(rng.integers(1, 9, (6, 8)))
    found = shard.search(np.full(6, -1), q)
    for i in range(6):
        assert [(s, m) for j, s, m in found if j == i] == [(-s, m) for s, m in sorted((-int(s), m) for m, s in enumerate(x @ q[i]))[:5]]
    assert all(len(at) < 80 for _, at in shard._possible(np.full(6, -1), q, 4000))
