"""Connected components of an undirected graph by label propagation with pointer doubling.

Every node starts with its own id as label.  A round takes the least label among a node and its neighbours,
then replaces a label by its own label (doubling), so a path of length d takes O(log d) rounds.
Labels are a table of the shared folder, written anew each round and deleted when the next one is there; the driver sees one
count.  A node with very many neighbours is one key of the joins: its rows are on the side that adaptive execution splits, and
the least label is aggregated before the exchange.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from erblock.functions.cut import discard, written


#: Ends of edges up to which the driver finds the components: a round costs more there than all of them.
FEW = 20_000


def _of_few(rows: list[tuple]) -> list[tuple]:
    """(node, component) by union of sets under their least node."""
    to: dict = {}

    def top(x):  # noqa: ANN001, ANN202
        while to.setdefault(x, x) != x:
            to[x] = x = to[to[x]]
        return x

    for a, b in rows:
        lo, hi = sorted((top(a), top(b)))
        to[hi] = lo
    return [(x, top(x)) for x in list(to)]


def connected(edges: DataFrame, left: str = "src", right: str = "dst", max_rounds: int = 50) -> DataFrame:
    """node, component (its least node) for every node of ``edges``; self-loops make single nodes known.

    Null ends are left out.  Raises if ``max_rounds`` do not suffice, rather than return a wrong answer.
    """
    both = edges.select(F.col(left).alias("a"), F.col(right).alias("b")).where("a is not null and b is not null")
    graph = written(both.unionByName(both.select(F.col("b").alias("a"), F.col("a").alias("b"))).distinct())
    few = graph.limit(FEW + 1).collect()
    if len(few) <= FEW:
        discard(graph)
        kind = edges.schema[left].dataType
        return edges.sparkSession.createDataFrame(_of_few(few), T.StructType([T.StructField("node", kind), T.StructField("component", kind)]))
    labels = written(graph.groupBy("a").agg(F.min("b").alias("m")).select(F.col("a").alias("node"), F.least("a", "m").alias("component")))
    for _ in range(max_rounds):
        near = graph.join(labels, graph["b"] == labels["node"]).groupBy("a").agg(F.min("component").alias("m"))
        stepped = written(labels.join(near, labels["node"] == near["a"]).select("node", F.least("component", "m").alias("to"), F.col("component").alias("old")))
        jump = stepped.select(F.col("node").alias("n"), F.col("to").alias("t"))
        new = written(stepped.join(jump, stepped["to"] == jump["n"], "left").select("node", F.least("to", F.coalesce("t", "to")).alias("component"), "old"))
        discard(labels, stepped)
        changed = new.where("component <> old").limit(1).count()
        labels = new
        if not changed:
            discard(graph)
            return labels.select("node", "component")
    raise RuntimeError(f"components did not settle in {max_rounds} rounds")
