"""What cells of a matrix have in common is made once; few edges need no rounds."""

from __future__ import annotations

import random

from erblock.functions import cut
from erblock.operators import attr_clustering, components
from erblock.plans import workloads


def test_tasks_share_bags(spark, monkeypatch):
    made = []
    monkeypatch.setattr(workloads, "_MATRIX", {})
    monkeypatch.setattr(workloads, "bags", lambda d, m, *a, f=workloads.bags: made.append(m) or f(d, m, *a))
    rows = workloads.matrix(spark, "/root/testdata/sf0.001", ("d2",), ("token",)).collect()
    assert sorted(r.task for r in rows) == ["clean", "dirty"] and made == ["token"]


def test_values_are_cut_into_grams_once(spark, monkeypatch):
    made = []
    monkeypatch.setattr(attr_clustering, "written", lambda df, *a: made.append(df.columns) or cut.written(df, *a), raising=False)
    desc = spark.createDataFrame([("L", "a", "name", "red house", "literal"), ("R", "b", "title", "red horse", "literal")], "collection string, entity_id string, attribute string, value string, kind string")
    found = {tuple(r) for r in attr_clustering.find_clusters(desc).collect()}
    assert {r[:2] for r in found} == {("L", "name"), ("R", "title")} and len({r[2] for r in found}) == 1
    assert made[0] == ["collection", "attribute", "gram"]


def test_components_of_few_and_of_many_edges(spark, monkeypatch):
    r = random.Random(1)
    edges = spark.createDataFrame([(f"n{r.randrange(60)}", f"n{r.randrange(60)}") for _ in range(45)], "src string, dst string")
    few = sorted(map(tuple, components.connected(edges).collect()))
    monkeypatch.setattr(components, "FEW", 0)
    assert few == sorted(map(tuple, components.connected(edges).collect()))
    assert components._of_few([("a", "b"), ("c", "c")])
