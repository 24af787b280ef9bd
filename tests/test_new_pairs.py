"""Pairs with a new description are counted without counting the others, and what is moved at a time is bounded."""

from __future__ import annotations

import random
from itertools import combinations

import pytest
from pyspark.sql import functions as F

from erblock.operators import pairs


def _rows(seed: int, n: int) -> list[tuple]:
    r = random.Random(seed)
    return [(f"e{i}", sorted(r.sample(range(40), r.randint(0, 4))), r.random() < 0.2) for i in range(n)]


@pytest.mark.parametrize("limits", [(), (30, 60)])
def test_pairs_with_a_new_one(spark, limits):
    rows = _rows(3, 150)
    want = sum(bool(set(a[1]) & set(b[1])) for a, b in combinations(rows, 2) if a[2] or b[2])
    df = spark.createDataFrame(rows, "entity_id string, keys array<long>, new boolean")
    assert pairs.count_new(df, *limits) == want
    assert pairs.count_new(df.withColumn("new", F.lit(False)), *limits) == 0


@pytest.mark.parametrize("task", ["clean", "dirty"])
def test_tiles_are_moved_a_few_at_a_time(spark, monkeypatch, task):
    rows = [("R" if i % 3 else "L", f"e{i}", k) for i, (_, k, _) in enumerate(_rows(5, 200))]
    side = {"clean": lambda a, b: {a[0], b[0]} == {"L", "R"}, "dirty": lambda a, b: True}[task]
    want = sum(bool(set(a[2]) & set(b[2])) for a, b in combinations(rows, 2) if side(a, b))
    df = spark.createDataFrame(rows, "collection string, entity_id string, keys array<string>")
    sizes = []
    monkeypatch.setattr(pairs, "MOVED", 100)
    monkeypatch.setattr(pairs, "_apart", lambda s, n, f=pairs._apart: sizes.append(n) or f(s, n))
    assert pairs.count(df, task, 20, 50).first()[0] == want
    assert len(sizes) > 2
