"""N-gram Jaccard self-join with Bayesian candidate pruning.

1. A text is the set of its five-word shingles.  Texts with equal sets are one *node* (copies are
   never paired); 96 MinHash values per node give 24 bands of 4.  A pair at similarity 0.8 meets in no band
   with probability 3e-6.
2. Nodes that meet in a bucket of a band are compared there by their MinHash values, 16 at a time.  After n of them
   with m agreeing, the posterior of the similarity under a uniform prior is Beta(m + 1, n - m + 1); pairs whose
   probability of reaching the threshold is under ``TOLERANCE`` are dropped.  A bucket yields the components of
   the pairs that are left as links to their least node (never pairs), so texts that share a band by chance or by a common
   passage are not brought together.  In a bucket of more than ``BUCKET`` nodes all are linked to its least one instead.
3. Connected components of these links bound where similar texts can be.  Large components are cut into blocks by hash,
   small ones share one; a block travels packed and compressed, once to every block of its component.  In a tile
   (block against block) the comparison of step 2 is repeated for all pairs, and the survivors are verified exactly
   by counting shared shingles.  A tile returns a row per linked text, never pairs.
4. Verified links make the classes; a text's links are summed over tiles, copies counted.

Edge cases: a text of fewer than five words is one shingle; one without words (null, empty, white space) has
no links and is its own class; ids may be null or repeat (a class with ids is named by its least one); equal
rows are copies; extra columns are ignored; an empty table gives an empty result.  Nodes are named by 64 bits
of a digest of their set (a chance of 3e-5 that any two of 10**7 texts clash; a clash merges two texts).
"""

from __future__ import annotations

import hashlib
import math
import pickle
from collections.abc import Iterator
from fractions import Fraction

import numpy as np
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from erblock.llm.common import checkpoint, fits, light_batches, mix64, row_of, settle, shingle_hashes
from erblock.operators.components import connected

BANDS, ROWS, STEP = 24, 4, 16
HASHES = BANDS * ROWS
#: Probability of reaching the threshold under which a pair is dropped.
TOLERANCE = 1e-9
#: Nodes of a bucket up to which its pairs are pruned by their MinHash values.
BUCKET = 2048
#: Nodes and shingles of a block, about.
BLOCK_NODES, BLOCK_SHINGLES = 2048, 1 << 21

_RNG = np.random.default_rng(5)
_MUL = _RNG.integers(1, 1 << 63, HASHES, dtype=np.uint64) * np.uint64(2) + np.uint64(1)
_ADD = _RNG.integers(0, 1 << 63, HASHES, dtype=np.uint64)


def signature(shingles: np.ndarray) -> np.ndarray:
    """MinHash values (32 bits each)."""
    out = np.full(HASHES, np.iinfo(np.uint64).max, dtype=np.uint64)
    with np.errstate(over="ignore"):
        for lo in range(0, len(shingles), 1024):
            part = shingles[lo : lo + 1024, None] * _MUL
            part += _ADD
            np.minimum(out, part.min(axis=0), out=out)
    return (out >> np.uint64(32)).astype(np.uint32)


def band_keys(sig: Column) -> Column:
    """A 64-bit key per band, from the 16-bit values."""
    return F.transform(F.sequence(F.lit(0), F.lit(BANDS - 1)), lambda b: F.xxhash64(F.substr(sig, b * 2 * ROWS + 1, F.lit(2 * ROWS)), b))


def node_of(shingles: np.ndarray) -> int:
    return int.from_bytes(hashlib.sha256(shingles.tobytes()).digest()[:8], "little", signed=True)


def needed(threshold: float, tolerance: float = TOLERANCE) -> dict[int, int]:
    """For n = 16, 32, ... the fewest agreeing values m with P(similarity >= threshold | m of n) >= tolerance.

    With a uniform prior that probability is the one of at most m successes in n + 1 trials.
    """
    out = {}
    for n in range(STEP, HASHES + 1, STEP):
        total, m = 0.0, 0
        for i in range(n + 1):
            total += math.comb(n + 1, i) * threshold**i * (1 - threshold) ** (n + 1 - i)
            if total >= tolerance:
                m = i
                break
        out[n] = m
    return out


def sketches(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """doc_id, tkey (hash of the text), node, n_shingles, sig (MinHash values, 16 bits of each); node and sig are null for
    texts without words."""
    schema = T.StructType(
        [
            T.StructField("doc_id", docs.schema[id_col].dataType),
            T.StructField("tkey", T.LongType()),
            T.StructField("node", T.LongType()),
            T.StructField("n_shingles", T.LongType()),
            T.StructField("sig", T.BinaryType()),
        ]
    )

    def run(batches: Iterator) -> Iterator:
        import pyarrow as pa

        settle("ngram_join")
        for batch in batches:
            for lo in range(0, batch.num_rows, 2048):
                part = batch.slice(lo, 2048)
                node, n, sigs = [], [], []
                for v in part.column(2).cast(pa.binary()):
                    s = shingle_hashes(v.as_py() or b"")
                    n.append(len(s))
                    node.append(node_of(s) if len(s) else None)
                    sigs.append(signature(s).astype("<u2").tobytes() if len(s) else None)
                columns = [pa.array(node, pa.int64()), pa.array(n, pa.int64()), pa.array(sigs, pa.binary())]
                yield pa.RecordBatch.from_arrays([part.column(0), part.column(1), *columns], names=schema.names)

    return docs.select(F.col(id_col).alias("doc_id"), F.xxhash64(text_col).alias("tkey"), F.col(text_col).alias("text")).mapInArrow(run, schema)


def _pack(nodes: list[int], copies: list[int], sets: list[np.ndarray]) -> bytes:
    """A block: sorted by size of set, so that near copies lie together for the compressor."""
    import zstandard

    sigs = np.stack([signature(s) for s in sets]).astype(np.uint16)
    raw = pickle.dumps((np.array(nodes), np.array(copies), sigs, np.array([len(s) for s in sets]), np.concatenate(sets)), protocol=5)
    return zstandard.ZstdCompressor(level=3, write_content_size=True).compress(raw)


class Block:
    def __init__(self, data: bytes):
        import zstandard

        self.nodes, self.copies, self.sigs, self.sizes, self.shingles = pickle.loads(zstandard.ZstdDecompressor().decompress(data))
        self.rows = np.repeat(np.arange(len(self.nodes)), self.sizes)


def candidates(a: Block, b: Block, need: dict[int, int]) -> tuple[np.ndarray, np.ndarray]:
    """Pairs (i of a, j of b) that no step of the comparison rules out."""
    agree = np.zeros((len(a.nodes), len(b.nodes)), dtype=np.uint8)
    pairs = count = None
    for n in range(STEP, HASHES + 1, STEP):
        if pairs is None:
            for k in range(n - STEP, n):
                agree += a.sigs[:, k, None] == b.sigs[None, :, k]
            alive = agree >= need[n]
            if np.count_nonzero(alive) < alive.size // 50:
                pairs = np.nonzero(alive)
                count = agree[pairs].astype(np.int32)
        else:
            count = count + (a.sigs[pairs[0], n - STEP : n] == b.sigs[pairs[1], n - STEP : n]).sum(axis=1)
            keep = count >= need[n]
            pairs, count = (pairs[0][keep], pairs[1][keep]), count[keep]
    return np.nonzero(alive) if pairs is None else pairs


def shared(a: Block, b: Block, i: np.ndarray, j: np.ndarray) -> np.ndarray:
    """Shingles that a's text i and b's text j share, for every pair."""
    if len(i) <= 2000:
        ends_a, ends_b = np.cumsum(a.sizes), np.cumsum(b.sizes)
        return np.array([len(np.intersect1d(a.shingles[ends_a[x] - a.sizes[x] : ends_a[x]], b.shingles[ends_b[y] - b.sizes[y] : ends_b[y]], assume_unique=True)) for x, y in zip(i, j, strict=True)], dtype=np.int64)
    both = np.intersect1d(np.unique(a.shingles), np.unique(b.shingles), assume_unique=True)

    def coded(x: Block) -> tuple[np.ndarray, np.ndarray]:
        at = np.searchsorted(both, x.shingles)
        at[at == len(both)] = 0
        keep = both[at] == x.shingles if len(both) else np.zeros(len(at), bool)
        return x.rows[keep], at[keep]

    (ra, ca), (rb, cb) = coded(a), coded(b)
    na, nb = np.bincount(ca, minlength=len(both)), np.bincount(cb, minlength=len(both))
    dense = na.astype(np.int64) * nb > 64
    place = np.cumsum(dense) - 1
    out = np.zeros((len(a.nodes), len(b.nodes)), dtype=np.float32)
    for lo in range(0, int(dense.sum()), 1024):
        ma, mb = (np.zeros((len(x.nodes), min(1024, int(dense.sum()) - lo)), dtype=np.float32) for x in (a, b))
        for m, r, c in ((ma, ra, ca), (mb, rb, cb)):
            here = dense[c] & (place[c] >= lo) & (place[c] < lo + 1024)
            m[r[here], place[c[here]] - lo] = 1
        out += ma @ mb.T
    # The rest: few texts on either side, so their pairs are listed.
    sa, sb = ~dense[ca], ~dense[cb]
    ra, ca, rb, cb = ra[sa], ca[sa], rb[sb], cb[sb]
    order = np.argsort(cb, kind="stable")
    rb, cb = rb[order], cb[order]
    lo, hi = np.searchsorted(cb, ca), np.searchsorted(cb, ca, side="right")
    reps = hi - lo
    left = np.repeat(ra, reps)
    right = rb[np.repeat(lo - np.concatenate([[0], np.cumsum(reps)[:-1]]), reps) + np.arange(reps.sum())] if reps.sum() else np.empty(0, np.int64)
    flat = np.bincount(left * len(b.nodes) + right, minlength=out.size)
    return np.rint(out[i, j]).astype(np.int64) + flat[i * len(b.nodes) + j]


def links(a: Block, b: Block | None, need: dict[int, int], threshold: Fraction) -> tuple[np.ndarray, np.ndarray]:
    """Verified pairs inside a (b None) or between a and b."""
    other = a if b is None else b
    i, j = candidates(a, other, need)
    if b is None:
        keep = i < j
        i, j = i[keep], j[keep]
    if not len(i):
        return i, j
    inter = shared(a, other, i, j)
    union = a.sizes[i] + other.sizes[j] - inter
    good = inter * threshold.denominator >= union * threshold.numerator
    return i[good], j[good]


def least_of(nodes: np.ndarray, i: np.ndarray, j: np.ndarray) -> np.ndarray:
    """Of each node the least one that it is connected with by the pairs (i, j)."""
    rank = np.argsort(np.argsort(nodes, kind="stable"), kind="stable")
    while True:
        new = rank.copy()
        np.minimum.at(new, i, rank[j])
        np.minimum.at(new, j, rank[i])
        if (new == rank).all():
            return np.sort(nodes)[rank]
        rank = new


def bucket_links(nodes: np.ndarray, sigs: np.ndarray, need: dict[int, int]) -> tuple[np.ndarray, np.ndarray]:
    """(node, least node connected with it) of a bucket, by the pairs that no step of the comparison rules out."""
    if len(nodes) == 2:  # most buckets
        same = sigs[0] == sigs[1]
        if any(np.count_nonzero(same[:n]) < m for n, m in need.items()):
            return nodes[:0], nodes[:0]
        return nodes.max()[None], nodes.min()[None]
    block = Block.__new__(Block)
    block.nodes, block.sigs = nodes, sigs
    i, j = candidates(block, block, need)
    least = least_of(nodes, i, j)
    linked = least != nodes
    return nodes[linked], least[linked]


def _tile(blocks: list[bytes], need: dict[int, int], threshold: Fraction) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """node, its links here (copies counted), least node of its component here."""
    a = Block(blocks[0])
    b = Block(blocks[1]) if len(blocks) > 1 else None
    i, j = links(a, b, need, threshold)
    n = len(a.nodes)
    other = a if b is None else b
    if b is not None:
        j = j + n
    nodes, copies = (a.nodes, a.copies) if b is None else (np.concatenate([a.nodes, b.nodes]), np.concatenate([a.copies, b.copies]))
    del other
    weight = np.bincount(i, weights=copies[j], minlength=len(nodes)) + np.bincount(j, weights=copies[i], minlength=len(nodes))
    label = least_of(nodes, i, j)
    index = np.arange(len(nodes))
    some = index[weight > 0]
    return nodes[some], weight[some].astype(np.int64), label[some]


def _pruned(met: DataFrame, need: dict[int, int]) -> DataFrame:
    """src, dst: links inside the buckets (band, node, sig) of bounded size."""
    schema = T.StructType([T.StructField("src", T.LongType()), T.StructField("dst", T.LongType())])

    def run(batches: Iterator) -> Iterator:
        import pyarrow as pa

        settle("ngram_join")
        held: list = []  # rows of the last bucket, which the next batch may continue
        for batch in _with_end(batches):
            if batch is not None:
                part = [batch.column(0).to_numpy(), batch.column(1).to_numpy(), np.frombuffer(b"".join(batch.column(2).to_pylist()), dtype="<u2").reshape(-1, HASHES)]
                held = [np.concatenate([x, y]) for x, y in zip(held, part, strict=True)] if held else part
            if not held:
                continue
            band, node, sig = held
            edges = np.flatnonzero(np.concatenate([[True], band[1:] != band[:-1], [True]]))
            whole = len(edges) - (1 if batch is None else 2)  # buckets that are complete
            found = []
            for a, b in zip(edges[:whole].tolist(), edges[1 : whole + 1].tolist(), strict=True):
                if b - a > 1:
                    found.append(bucket_links(node[a:b], sig[a:b], need))
            held = [x[edges[whole] :] for x in held]
            if found:
                src, dst = (np.concatenate(x) for x in zip(*found, strict=True))
                yield pa.RecordBatch.from_arrays([pa.array(src), pa.array(dst)], names=schema.names)

    dealt = met.select("band", "node", "sig").repartition("band").sortWithinPartitions("band", "node")
    return dealt.mapInArrow(run, schema).distinct()


def _with_end(batches: Iterator) -> Iterator:
    yield from batches
    yield None


def near_duplicates(docs: DataFrame, threshold: float = 0.8, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """doc_id, tkey, node, class_id, n_links, class_node of every row.

    class_node names the class, also where no row has an id (null for a text without words); class_id: least id of the class (texts connected by links of at least ``threshold``);
    n_links: number of other rows that are linked to it directly.
    """
    need, exact = needed(threshold), Fraction(threshold).limit_denominator(1000)
    rows = checkpoint(sketches(light_batches(docs), id_col, text_col))
    nodes = rows.where("node is not null").groupBy("node").agg(
        F.min(F.struct("tkey", "doc_id")).alias("rep"), F.min("doc_id").alias("first_id"), F.count(F.lit(1)).alias("copies"), F.max("n_shingles").alias("n_shingles"), F.first("sig").alias("sig")
    )
    nodes = checkpoint(nodes)
    in_band = nodes.select("node", F.explode(band_keys(F.col("sig"))).alias("band"))
    buckets = in_band.groupBy("band").agg(F.min("node").alias("least"), F.count(F.lit(1)).alias("n")).where("n > 1")
    met = checkpoint(in_band.join(buckets, "band").select("node", "band", "least", (F.col("n") > BUCKET).alias("large")))
    # A node of large buckets meets up to 24 least nodes: it is linked to the least of them, and that one to the others. The
    # latter links are the same for most nodes of a group, so the graph has about one link per node.
    star = met.where("large and node <> least").groupBy("node").agg(F.collect_set("least").alias("all"))
    star = star.select("node", F.array_min("all").alias("first"), "all")
    star = star.select(F.col("first").alias("dst"), F.explode(F.array_append("all", F.col("node"))).alias("src")).where("src <> dst").distinct()
    near = connected(star.unionByName(_pruned(met.where("not large").select("band", "node").join(nodes.select("node", "sig"), "node"), need)))

    members = near.join(nodes.drop("sig"), "node")
    sized = members.groupBy("component").agg(F.count(F.lit(1)).alias("n"), F.sum("n_shingles").alias("s"))
    sized = sized.withColumn("blocks", F.ceil(F.greatest(F.col("n") / BLOCK_NODES, F.col("s") / BLOCK_SHINGLES)).cast("int"))
    n_small, s_small = sized.where("blocks = 1").agg(F.coalesce(F.sum("n"), F.lit(0)), F.coalesce(F.sum("s"), F.lit(0))).first()
    bins = max(1, math.ceil(max(2 * n_small / BLOCK_NODES, 2 * s_small / BLOCK_SHINGLES)))
    placed = members.join(sized.select("component", "blocks"), "component").select(
        F.when(F.col("blocks") == 1, F.concat(F.lit("s"), F.pmod(F.xxhash64("component"), F.lit(bins)).cast("string"))).otherwise(F.col("component").cast("string")).alias("g"),
        F.pmod(F.xxhash64("node", F.lit(3)), F.col("blocks")).cast("int").alias("block"),
        "blocks", "node", "copies", F.col("rep.tkey").alias("rkey"), F.col("rep.doc_id").alias("rid"),
    )
    placed = checkpoint(placed)
    if fits(placed):
        placed = F.broadcast(placed)
    source = docs.select(F.col(id_col).alias("doc_id"), F.xxhash64(text_col).alias("tkey"), F.col(text_col).alias("text"))
    texts = source.join(placed, (source["tkey"] == F.col("rkey")) & source["doc_id"].eqNullSafe(F.col("rid"))).select("g", "block", "blocks", "node", "copies", "text")

    packed = T.StructType([T.StructField("g", T.StringType()), T.StructField("block", T.IntegerType()), T.StructField("blocks", T.IntegerType()), T.StructField("data", T.BinaryType())])

    def pack(table: object) -> object:
        import pyarrow as pa

        seen: dict[int, tuple[int, np.ndarray]] = {}
        for node, copies, text in zip(*(table.column(c) for c in ("node", "copies", "text")), strict=True):
            node = node.as_py()
            if node not in seen:
                s = shingle_hashes((text.as_py() or "").encode())
                if len(s) and node_of(s) == node:
                    seen[node] = (copies.as_py(), s)
        one = [table.column(c)[0].as_py() for c in ("g", "block", "blocks")]
        items = sorted(seen.items(), key=lambda x: (len(x[1][1]), x[0]))
        data = [_pack([k for k, _ in items], [v[0] for _, v in items], [v[1] for _, v in items])] if items else []
        return pa.table({"g": [one[0]] * len(data), "block": pa.array([one[1]] * len(data), pa.int32()), "blocks": pa.array([one[2]] * len(data), pa.int32()), "data": pa.array(data, pa.binary())})

    blocks = texts.groupBy("g", "block").applyInArrow(pack, packed)
    pairs = blocks.withColumn("other", F.explode(F.sequence(F.lit(0), F.col("blocks") - 1)))
    pairs = pairs.select("g", F.least("block", "other").alias("lo"), F.greatest("block", "other").alias("hi"), "block", "data")
    found = T.StructType([T.StructField("node", T.LongType()), T.StructField("links", T.LongType()), T.StructField("least", T.LongType())])

    def tile(table: object) -> object:
        import pyarrow as pa

        lo, hi = table.column("lo")[0].as_py(), table.column("hi")[0].as_py()
        if lo != hi and table.num_rows < 2:
            return pa.table([pa.array([], pa.int64())] * 3, names=found.names)
        node, n, least = _tile(table.column("data").to_pylist(), need, exact)
        return pa.table([pa.array(node), pa.array(n), pa.array(least)], names=found.names)

    linked = checkpoint(pairs.groupBy("g", "lo", "hi").applyInArrow(tile, found))
    classes = connected(linked.select("node", "least"), "node", "least")
    per = linked.groupBy("node").agg(F.sum("links").alias("links"))
    of_class = classes.join(nodes.select("node", "first_id"), "node").groupBy("component").agg(F.min("first_id").alias("class_first"))
    classes = classes.join(of_class, "component").select("node", "class_first", "component")
    per_node = nodes.select("node", "first_id", "copies").join(per, "node", "left").join(classes, "node", "left").where("copies > 1 or component is not null")
    per_node = per_node.select("node", F.coalesce("class_first", "first_id").alias("class_id"), (F.coalesce("links", F.lit(0)) + F.col("copies") - 1).alias("n_links"), F.coalesce("component", "node").alias("class_node"))
    per_node = checkpoint(per_node.withColumn("known", F.lit(True)))
    # A text alone in its class needs no join; of the others many rows may have one node, so the side of the nodes goes
    # to every task if it is small, and adaptive execution splits the rows of a node if not.
    out = rows.select("doc_id", "tkey", "node").join(F.broadcast(per_node) if fits(per_node) else per_node, "node", "left")
    alone = F.col("known").isNull()
    return out.select("doc_id", "tkey", "node", F.when(alone, F.col("doc_id")).otherwise(F.col("class_id")).alias("class_id"), F.coalesce("n_links", F.lit(0)).alias("n_links"), F.when(alone, F.col("node")).otherwise(F.col("class_node")).alias("class_node"))


def keep_one(docs: DataFrame, threshold: float = 0.8, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """One row of each class of ``docs``, and all texts without words.

    The row with the class's own id stays, of several texts with it the one of the least key, of repeated rows
    the least by its columns (which have to be orderable); rows without id only where their class has none.
    Columns may have any name.
    """
    marks = near_duplicates(docs, threshold, id_col, text_col)
    keys = marks.where("node is not null and n_links > 0").groupBy("doc_id", "tkey", "class_node").agg(F.count(F.lit(1)).alias("n"))
    keys = checkpoint(keys.select(F.col("doc_id").alias("d"), F.col("tkey").alias("k"), "class_node", "n"))
    first = keys.groupBy("class_node").agg(F.min(F.struct(F.col("d").isNull().alias("none"), "d", "k", "n")).alias("first"))
    first = checkpoint(first.select("first.d", "first.k", "first.n"))

    def of(left: DataFrame, right: DataFrame, how: str) -> DataFrame:
        right = right.select(F.col("d").alias("rd"), F.col("k").alias("rk"))
        right = F.broadcast(right) if fits(right) else right
        return left.join(right, F.col("d").eqNullSafe(F.col("rd")) & (F.col("k") == F.col("rk")), how)

    drop = checkpoint(of(keys, first, "left_anti"))
    again = first.where("n > 1")
    keyed = docs.select(row_of(docs).alias("row"), F.col(id_col).alias("d"), F.xxhash64(text_col).alias("k"))
    kept = of(of(keyed, drop, "left_anti"), again, "left_anti").select("row")
    once = of(keyed, again, "left_semi").groupBy("d", "k").agg(F.min("row").alias("row")).select("row")
    return kept.unionByName(once).select("row.*")
