"""Exact top-k inner products with an impact-ordered score-at-a-time index.

*Index.*  Vectors are cut into shards by a hash of their id.  Inside a shard equal vectors are one
entry (with its ids).  Every dimension has two posting lists, one of the distance above the shard's least
value, one of the distance below its greatest; a list holds its entries by descending quantised impact (one
of 256 levels), cut into a *segment* per level.

*Search.*  For a query the score is rewritten with non-negative impacts: in a dimension with a positive
weight the first list counts, with a negative one the second.  Segments are processed by descending
impact, a band of levels of all lists at a time, for a block of queries together: the band's postings are laid
out as one matrix, whose product with the weights adds to the accumulators.  After a band, what an entry
may still gain is at most the next level in every dimension.  A query stops when the entries whose
upper bound reaches the k-th lower bound are few, or no segment is left; these possible members are then
scored exactly.  So the result is exact whatever the stopping point.

*Spread.*  The work is tiles, a shard against a group of queries: each task holds one tile of bounded size, and the
two sides travel (queries / ``GROUP_ROWS``) and (vectors / ``SHARD_ROWS``) times.  Per tile and query at most
k rows return, and a window keeps the best, cut to k per query before the exchange.  Nothing is collected or broadcast.

Edge cases: vectors that are null, empty, or hold a null or non-finite component take no part, nor do rows
without an id; vectors of different length share the shorter one's dimensions (a missing component is 0);
ties go to the smaller id; equal rows are separate candidates, so an id that is repeated may be listed as often.
Rows with the query's id are its own and no candidates; query rows with equal id and vector are one
query, with equal id and other vectors one query each (each gives ranks from 1); fewer than k
candidates are all returned; an empty table gives an empty result; extra columns are ignored.
"""

from __future__ import annotations

import numpy as np
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F
from pyspark.sql import types as T

#: Levels of impact.
LEVELS = 256
#: A band ends at these levels; after each the bounds are looked at.
BANDS = (LEVELS // 4, LEVELS // 32, 2, 1)
#: Vectors of a shard and queries of a group, about; queries that are processed together.
SHARD_ROWS, GROUP_ROWS, BLOCK_ROWS = 16_384, 16_384, 512
#: Possible members at which exact scoring takes over, as a share of the shard's entries.
FEW = 0.02


def quantised(col: Column, scale: int = 256) -> Column:
    """floor(scale * x) of each component, x as double; null if one is null or not finite."""
    bad = F.exists(col, lambda x: x.isNull() | F.isnan(x) | (F.abs(x) == float("inf")))
    ints = F.transform(col, lambda x: F.floor(x.cast("double") * F.lit(float(scale))).cast("long"))
    return F.when(col.isNotNull() & (F.size(col) > 0) & ~F.coalesce(bad, F.lit(True)), ints)


def _members(ids: np.ndarray, k: int) -> np.ndarray:
    """Ids (ascending) that can be among the k smallest after one id has been left out: at most k rows of an id, 2 k in all."""
    nth = np.arange(len(ids)) - np.searchsorted(ids, ids)
    return ids[nth < k][: 2 * k]


class Shard:
    """The impact-ordered index of some vectors."""

    def __init__(self, ids: np.ndarray, vectors: np.ndarray, k: int):
        order = np.argsort(ids, kind="stable")
        ids, vectors = ids[order], vectors[order]
        _, first, group = np.unique(vectors, axis=0, return_index=True, return_inverse=True)
        self.x = vectors[first]
        group = group.ravel()
        by = np.argsort(group, kind="stable")
        starts = np.searchsorted(group[by], np.arange(len(first) + 1))
        self.members = [_members(ids[by[a:b]], k) for a, b in zip(starts[:-1], starts[1:], strict=True)]
        self.k = k
        #: Entries that hold rows of one id only, by that id: they are left out for queries of that id.
        self.only: dict[int, list[int]] = {}
        for e, m in enumerate(self.members):
            if m[0] == m[-1]:
                self.only.setdefault(int(m[0]), []).append(e)
        self.low, self.high = self.x.min(axis=0), self.x.max(axis=0)
        self.span = self.high - self.low
        self.shift = max(0, int(self.span.max()).bit_length() - (LEVELS - 1).bit_length())
        # Lists of all dimensions, above the least value, then below the greatest.
        impact = np.concatenate([(self.x - self.low).T, (self.high - self.x).T]) >> self.shift
        self.order = np.argsort(LEVELS - 1 - impact.astype(np.uint8), axis=1, kind="stable").astype(np.int32)
        self.level = np.take_along_axis(impact, self.order, axis=1).astype(np.uint8)

    def _band(self, above: int, down_to: int, dtype: type) -> np.ndarray | None:
        """Impacts of the postings with down_to <= level < above, list by list."""
        out = None
        for s, levels in enumerate(self.level):
            falling = -levels.astype(np.int16)
            a, b = np.searchsorted(falling, [-above, -down_to], side="right")
            if b > a:
                out = np.zeros(self.level.shape, dtype=dtype) if out is None else out
                out[s, self.order[s, a:b]] = levels[a:b]
        return out

    def search(self, ids: np.ndarray, queries: np.ndarray) -> list[tuple[int, int, int]]:
        """(number of the query, score, id) of the k best of this shard for each query."""
        n, found = len(self.x), []
        for lo in range(0, len(ids), BLOCK_ROWS):
            found += [(lo + i, s, m) for i, at in self._possible(ids[lo : lo + BLOCK_ROWS], queries[lo : lo + BLOCK_ROWS], n) for s, m in self._best(int(ids[lo + i]), queries[lo + i], at)]
        return found

    def _possible(self, ids: np.ndarray, queries: np.ndarray, n: int) -> list[tuple[int, np.ndarray]]:
        """For each query the entries that may be among its k best, proven by bounds."""
        k, step = self.k, 1 << self.shift
        weight = np.abs(queries)
        most = int(weight.sum(axis=1).max()) * int(self.span.max() + 1) if len(queries) else 0
        dtype = np.float32 if most < 1 << 24 else np.float64 if most < 1 << 53 else np.int64
        signed = np.concatenate([np.maximum(queries, 0), np.maximum(-queries, 0)], axis=1).astype(dtype) * dtype(step)
        live, acc, above, done = np.arange(len(ids)), np.zeros((len(ids), n), dtype=dtype), LEVELS, []
        own = [self.only.get(int(i), []) for i in ids]
        for down_to in BANDS:
            band = self._band(above, down_to, dtype)
            above = down_to
            if band is not None:
                acc += signed[live] @ band
            gain = (weight[live] * np.minimum(down_to * step - 1, self.span)).sum(axis=1)
            usable = acc.copy() if any(own[q] for q in live) else acc
            for i, q in enumerate(live):
                usable[i, own[q]] = -1
            floor = np.partition(usable, n - k, axis=1)[:, n - k] if n > k else np.zeros(len(live))
            alive = usable >= np.maximum(floor - gain, 0)[:, None]
            stop = (alive.sum(axis=1) <= max(4 * k, FEW * n)) | (down_to == 1)
            done += [(int(live[i]), np.flatnonzero(alive[i])) for i in np.flatnonzero(stop)]
            live, acc = live[~stop], acc[~stop]
            if not len(live):
                break
        return done

    def _best(self, query_id: int, q: np.ndarray, at: np.ndarray) -> list[tuple[int, int]]:
        """(score, id) of the k best among the entries, scored exactly; rows of the query's id left out."""
        scores = self.x[at] @ q
        if len(at) > self.k:
            keep = np.flatnonzero(scores >= np.partition(scores, len(at) - self.k)[len(at) - self.k])
            at, scores = at[keep], scores[keep]
        found = sorted((-int(s), int(m)) for s, e in zip(scores, at, strict=True) for m in self.members[e] if m != query_id)
        return [(-s, m) for s, m in found[: self.k]]


def top_k(vectors: DataFrame, is_query: Column, k: int = 5, scale: int = 256, id_col: str = "vec_id", vec_col: str = "embedding", shard_rows: int = SHARD_ROWS, group_rows: int = GROUP_ROWS) -> DataFrame:
    """query_id, rank, vec_id, score: each query's k best other rows."""
    rows = vectors.select(F.col(id_col).cast("long").alias("vec_id"), quantised(F.col(vec_col), scale).alias("v"), F.coalesce(is_query, F.lit(False)).alias("q"))
    rows = rows.where(F.col("v").isNotNull() & F.col("vec_id").isNotNull())
    n, n_q = rows.agg(F.count(F.lit(1)), F.count_if("q")).first()
    shards, groups = -(-max(n, 1) // shard_rows), -(-max(n_q, 1) // group_rows)
    # All rows of an id lie in one shard, so that a query's own rows are known there.
    index = rows.select(F.pmod(F.xxhash64("vec_id"), F.lit(shards)).cast("int").alias("shard"), "vec_id", "v")
    index = index.select("shard", F.explode(F.sequence(F.lit(0), F.lit(groups - 1))).alias("group"), "vec_id", "v")
    asked = rows.where("q").select("vec_id", "v").distinct().withColumn("key", F.xxhash64("v"))
    asked = asked.select(F.pmod(F.xxhash64("vec_id", F.lit(1)), F.lit(groups)).cast("int").alias("group"), "vec_id", "key", "v")
    asked = asked.select(F.explode(F.sequence(F.lit(0), F.lit(shards - 1))).alias("shard"), "group", "vec_id", "key", "v")
    schema = T.StructType([T.StructField(c, T.LongType()) for c in ("query_id", "key", "score", "vec_id")])

    def tile(left: object, right: object) -> object:
        if not left.num_rows or not right.num_rows:
            return schema_table([])
        shard = Shard(*_arrays(left), k)
        ids, queries = _arrays(right)
        keys = right.column("key").to_pylist()
        return schema_table([(int(ids[i]), keys[i], s, m) for i, s, m in shard.search(ids, _fit(queries, shard.x.shape[1]))])

    def schema_table(found: list) -> object:
        import pyarrow as pa

        return pa.table([pa.array([f[c] for f in found], type=pa.int64()) for c in range(4)], names=schema.names)

    # As many partitions as tiles (twice, for even loads): a tile is work enough for a task.
    parts = min(2 * shards * groups, 20_000)
    spread = lambda df: df.repartition(parts, "shard", "group").groupBy("shard", "group")
    near = spread(index).cogroup(spread(asked)).applyInArrow(tile, schema)
    w = Window.partitionBy("query_id", "key").orderBy(F.desc("score"), "vec_id")
    best = near.withColumn("rank", F.row_number().over(w)).where(F.col("rank") <= k)
    return best.select("query_id", "rank", "vec_id", "score")


def _arrays(table: object) -> tuple[np.ndarray, np.ndarray]:
    """Ids and matrix of the columns vec_id and v; shorter vectors are filled with 0."""
    table = table.combine_chunks()
    ids = table.column("vec_id").to_numpy()
    lists = table.column("v").combine_chunks() if table.column("v").num_chunks != 1 else table.column("v").chunk(0)
    offsets = lists.offsets.to_numpy()
    sizes, values = np.diff(offsets), lists.values.to_numpy(zero_copy_only=False)[offsets[0] : offsets[-1]]
    if sizes.min() == sizes.max():
        return ids, values.reshape(len(ids), -1)
    out = np.zeros((len(ids), sizes.max()), dtype=np.int64)
    out[np.arange(sizes.max()) < sizes[:, None]] = values
    return ids, out


def _fit(x: np.ndarray, dims: int) -> np.ndarray:
    """Queries with just as many dimensions as the shard."""
    return x[:, :dims] if x.shape[1] >= dims else np.pad(x, ((0, 0), (0, dims - x.shape[1])))


def brute_force(ids: np.ndarray, vectors: np.ndarray, query_ids: list[int], k: int) -> list[tuple[int, int, int, int]]:
    """(query_id, rank, vec_id, score) by scoring every pair; for tests."""
    out = []
    for a in query_ids:
        for q in np.unique(vectors[ids == a], axis=0):
            best = sorted((-int(s), int(m)) for s, m in zip(vectors @ q, ids, strict=True) if m != a)[:k]
            out += [(int(a), r, m, -s) for r, (s, m) in enumerate(best, 1)]
    return out
