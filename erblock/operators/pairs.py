"""Candidate pairs, for when they are asked for: expansion costs the sum of squared block sizes."""

from __future__ import annotations

from collections.abc import Sequence

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from erblock.functions.cut import discard, fits, tidy, written
from erblock.operators.blocks import bags, summary, unbagged, useful


def _sides(postings: DataFrame, task: str, more: Sequence[str] = ()) -> tuple[DataFrame, DataFrame, Column]:
    left, right = (postings.where("collection = 'L'"), postings.where("collection = 'R'")) if task == "clean" else (postings, postings)
    a = left.select("block_key", F.col("entity_id").alias("left_id"), *more)
    b = right.select("block_key", F.col("entity_id").alias("right_id"), *more)
    return a, b, F.lit(True) if task == "clean" else F.col("left_id") < F.col("right_id")


def raw(postings: DataFrame, task: str) -> DataFrame:
    """left_id, right_id once per common block."""
    a, b, good = _sides(postings, task)
    return a.join(b, "block_key").where(good).select("left_id", "right_id")


def distinct(postings: DataFrame, task: str, method: str = "exact") -> DataFrame:
    """Distinct candidate pairs.

    'exact': distinct of all; 'min_key': a pair comes from its least common key only, so no
    shuffle of pairs is needed.
    """
    if method == "exact":
        return raw(postings, task).distinct()
    if method != "min_key":
        raise ValueError(method)
    return _by_least_key(postings, task)


def _by_least_key(postings: DataFrame, task: str) -> DataFrame:
    """Each pair in the block of its least common key; keys are numbered.

    A posting carries its description's keys.  Where one side fits in memory it is sent to the other, whose postings are
    cut from their descriptions on the spot; else both are shuffled, with the keys before their own only.
    """
    named = written(summary(postings, task).select("block_key"), "zstd").withColumn("id", F.monotonically_increasing_id())
    named = F.broadcast(named) if fits(named) else named
    side = F.col("collection") if task == "clean" else F.lit("L").alias("collection")
    owned = postings.join(named, "block_key").select(side, "entity_id", "id").groupBy("collection", "entity_id")
    owned = written(owned.agg(F.array_sort(F.collect_set("id")).alias("keys")), "zstd")

    def each(who: str) -> DataFrame:
        cut = owned.where(F.col("collection") == (who.upper() if task == "clean" else "L"))
        cut = cut.select(F.col("entity_id").alias(f"{who}_id"), "keys", F.posexplode("keys").alias("place", "id"))
        return cut.select("id", F.col(f"{who}_id"), F.expr("slice(keys, 1, place)").alias(f"{who}_keys"))

    a, b = each("l"), each("r")
    if fits(b):
        b = F.broadcast(b)
    elif task == "clean" and fits(a):
        a = F.broadcast(a)
    order = F.lit(True) if task == "clean" else F.col("l_id") < F.col("r_id")
    met = a.join(b, "id").where(order & ~F.arrays_overlap("l_keys", "r_keys"))
    return met.select(F.col("l_id").alias("left_id"), F.col("r_id").alias("right_id"))


#: Classes of descriptions in a tile, and keys in a tile or a chunk of rows.
COLUMNS, KEYS = 65_536, 4_000_000
#: Tasks that a count is cut into at least.
TASKS = 12
#: Tasks up to which each group of a count has one of its own.
ALONE = 1_000


def numbered(rows: DataFrame, task: str) -> tuple[DataFrame, DataFrame]:
    """(block_key, n_left, n_right, comparisons, id of every useful block; collection, entity_id, ids sorted of every
    description of ``blocks.bags`` that is in one), as tables: what is shuffled later are numbers."""
    named = written(summary(unbagged(rows), task), "zstd")
    named_ids = named.select("block_key", F.monotonically_increasing_id().alias("id"))
    named_ids = F.broadcast(named_ids) if fits(named_ids) else named_ids
    p = rows.select("collection", "entity_id", F.explode("keys").alias("block_key")).join(named_ids, "block_key")
    # Numbers of one description are gathered behind the exchange only: before it hardly any meet.
    dealt = p.select("collection", "entity_id", "id").repartition("collection", "entity_id")
    return named, written(dealt.groupBy("collection", "entity_id").agg(F.array_sort(F.collect_list("id")).alias("ids")), "zstd")


def count(postings: DataFrame, task: str, columns: int = COLUMNS, keys: int = KEYS) -> DataFrame:
    """distinct_pairs, exactly and without a row per pair (``postings`` or ``blocks.bags``).

    Descriptions with the same useful keys are a class.  The classes of one side are cut into tiles of at most about ``columns``
    classes and ``keys`` keys, those of the other into chunks; for each row of a chunk the union of the tile's block members is
    counted (``_met``).  So a pair costs about a bit per common large block, and no shuffle.
    """
    spark = postings.sparkSession
    # Entity numbers stand for ids where sides are apart; in one collection an id may come from both.
    own = written((postings if "keys" in postings.columns else bags(postings)).select("collection", "entity_id", "keys"), "zstd")
    number = F.monotonically_increasing_id().cast("string") if task == "clean" else F.col("entity_id")
    side = F.col("collection") if task == "clean" else F.lit("L")
    named = written(summary(unbagged(own) if task == "clean" else unbagged(own.withColumn("collection", F.lit("L"))), task).select("block_key"), "zstd").withColumn("id", F.monotonically_increasing_id())
    if fits(named):
        named = F.broadcast(named)
    p = own.select(side.alias("collection"), number.alias("entity"), "keys").select("collection", "entity", F.explode("keys").alias("block_key")).join(named, "block_key")
    each = p.groupBy("collection", "entity").agg(F.array_sort(F.collect_set("id")).alias("ids"))
    return _count(each, task, columns, keys)


def shares_ids(rows: DataFrame) -> bool:
    """Whether an id is in both collections."""
    of = rows.groupBy("entity_id").agg(F.count_distinct("collection").alias("k")).where("k > 1")
    return of.limit(1).count() > 0


def count_numbered(numbers: DataFrame, task: str, shared: bool, columns: int = COLUMNS, keys: int = KEYS) -> DataFrame:
    """``count`` of what ``numbered`` made."""
    each = numbers
    if task != "clean":
        # An id of both collections is one description.
        each = numbers.select(F.lit("L").alias("collection"), "entity_id", "ids")
        if shared:
            each = each.groupBy("collection", "entity_id").agg(F.array_sort(F.array_distinct(F.flatten(F.collect_list("ids")))).alias("ids"))
    return _count(each, task, columns, keys)


def _count(each: DataFrame, task: str, columns: int, keys: int) -> DataFrame:
    """``count`` of descriptions with the numbers of their blocks."""
    spark = each.sparkSession
    classes = written(each.groupBy("collection", "ids").agg(F.count(F.lit(1)).alias("n")), "zstd")
    sizes = {r[0]: r[1:] for r in classes.groupBy("collection").agg(F.count(F.lit(1)), F.sum(F.size("ids")), F.sum("n")).collect()}
    if "L" not in sizes or (task == "clean" and "R" not in sizes):
        return spark.range(1).select(F.lit(0).cast("long").alias("distinct_pairs"))
    if task == "clean":
        # The tiles are of the side with fewer keys, as they are sent to every chunk.
        low, high = sorted("LR", key=lambda c: sizes[c][1])
        of = lambda c: classes.where(F.col("collection") == c)
        total = _unions(of(high), sizes[high], of(low), sizes[low], columns, keys)
    else:
        # Each pair was met from both ends, and each description meets itself.
        total = (_unions(classes, sizes["L"], None, sizes["L"], columns, keys) - sizes["L"][2]) // 2
    discard(classes)
    return spark.range(1).select(F.lit(total).cast("long").alias("distinct_pairs"))


def count_new(rows: DataFrame, columns: int = COLUMNS, keys: int = KEYS) -> int:
    """Distinct pairs of a dirty collection (entity_id, keys as numbers, new) of which one at least is new."""
    each = rows.select("new", F.array_sort("keys").alias("ids")).where(F.size("ids") > 0)
    classes = written(each.groupBy("new", "ids").agg(F.count(F.lit(1)).alias("n")), "zstd")
    sizes = {r[0]: r[1:] for r in classes.groupBy("new").agg(F.count(F.lit(1)), F.sum(F.size("ids")), F.sum("n")).collect()}
    if True not in sizes:
        return 0
    # Two new ones meet from both ends, as does each itself; with an old one a new one meets once, which is doubled.
    cols = classes.withColumn("n", F.when(F.col("new"), F.col("n")).otherwise(2 * F.col("n")))
    both = tuple(map(sum, zip(*sizes.values(), strict=True)))
    return (_unions(classes.where("new"), sizes[True], cols, both, columns, keys) - sizes[True][2]) // 2


#: Keys that are shuffled at a time, about: what is repeated for tiles and chunks goes off the disk before the next.
MOVED = 50_000_000
#: Keys that are worth a task.
LITTLE = 50_000


def _unions(rows: DataFrame, of_rows: tuple, cols: DataFrame | None, of_cols: tuple, columns: int, keys: int) -> int:
    """Sum over rows of n times the n of all columns that share an id (``_met``); ``of_``: number of classes and of keys.

    Without ``cols`` rows meet each other: a tile and a chunk are met once, and count twice.
    """
    half = cols is None
    least = min(TASKS, -(-of_rows[1] // LITTLE))
    tiles = max(-(-of_cols[0] // columns), -(-of_cols[1] // keys))
    if half:
        while tiles * (tiles + 1) // 2 < least:
            tiles += 1
        chunks, cols = tiles, rows
    else:
        chunks = max(-(-of_rows[1] // keys), -(-least // tiles))
    deal = lambda n: F.pmod(F.xxhash64("ids"), F.lit(n)).cast("int")
    every = lambda a, b: F.explode(F.sequence(a, b))
    total, lo = 0, 0
    while lo < tiles:
        hi, moved, groups = lo, 0, []
        while hi < tiles and (not groups or moved <= MOVED and len(groups) < ALONE):
            met_by = hi + 1 if half else chunks
            moved += (of_rows[1] // chunks + of_cols[1] // tiles) * met_by
            groups += [(i, hi) for i in range(met_by)]
            hi += 1
        a = rows.select(deal(chunks).alias("i"), every(F.lit(lo), F.lit(hi - 1)).alias("j"), "n", "ids")
        b = cols.select(deal(tiles).alias("j"), "n", "ids").where(F.col("j").between(lo, hi - 1))
        b = b.select("j", every(F.lit(0), F.col("j") if half else F.lit(chunks - 1)).alias("i"), "n", "ids")
        if half:
            a = a.where("i <= j").withColumn("n", F.when(F.col("i") < F.col("j"), 2 * F.col("n")).otherwise(F.col("n")))
        # Groups are numbered tile by tile.
        number = F.col("i") + (F.expr(f"(j * (j + 1) - {lo * (lo + 1)}) div 2").cast("int") if half else (F.col("j") - lo) * chunks)
        labels = F.array(*map(F.lit, _apart(rows.sparkSession, len(groups))))
        a, b = (x.select(F.get(labels, number).alias("g"), "n", "ids").repartition(len(groups), "g") for x in (a, b))
        with tidy(rows.sparkSession):
            total += a.groupBy("g").cogroup(b.groupBy("g")).applyInArrow(_met, "met long").agg(F.sum("met")).first()[0] or 0
        lo = hi
    return total


_APART: dict[int, list[int]] = {}


def _apart(spark: SparkSession, n: int) -> list[int]:
    """n numbers that go to n partitions, each to another, as far as found."""
    if n not in _APART:
        to = spark.range(n * 32).select(F.col("id").cast("int").alias("label")).withColumn("p", F.pmod(F.hash("label"), F.lit(n)))
        first = [r[0] for r in to.groupBy("p").agg(F.min("label").alias("label")).select("label").collect()]
        taken = set(first)
        _APART[n] = first + [x for x in range(n * 32) if x not in taken][: n - len(first)]
    return _APART[n]


#: Steps of a union by lists up to which rows are taken together, rows whose unions are made together, and bytes of large blocks as bits.
STEPS, TOGETHER, BITS = 2_000_000, 1024, 96 << 20


def _met(rows, cols):  # noqa: ANN001, ANN202
    """Sum over rows of n times the n of all columns that share an id."""
    import numpy as np
    import pyarrow as pa

    def flat(t):  # noqa: ANN001, ANN202
        ids = t.column("ids").combine_chunks()
        ids = ids if isinstance(ids, pa.ListArray) else pa.concat_arrays(ids.chunks)
        off = ids.offsets.to_numpy()
        return ids.values.to_numpy()[off[0] : off[-1]], np.diff(off), t.column("n").to_numpy()

    def runs(begin, n):  # noqa: ANN001, ANN202
        """begin, begin + 1, ... of each, n long, one behind the other."""
        return np.repeat(begin - np.cumsum(n) + n, n) + np.arange(int(n.sum()))

    total = 0
    if rows.num_rows and cols.num_rows:
        c_ids, c_len, c_n = flat(cols)
        width = len(c_n)
        order = np.argsort(c_ids)
        c_ids = c_ids[order]
        members = np.repeat(np.arange(width, dtype=np.int32), c_len)[order]
        del order
        start = np.flatnonzero(np.concatenate([[True], c_ids[1:] != c_ids[:-1]]))
        known, size = c_ids[start], np.diff(np.append(start, len(c_ids)))
        del c_ids

        # Large blocks as bits over the columns, others as lists.
        words = -(-width // 64)
        large = np.flatnonzero(size >= max(16, int((250 * width / TOGETHER) ** 0.5)))
        if len(large) * words * 8 > BITS:
            large = large[np.argsort(-size[large], kind="stable")[: BITS // (words * 8)]]
        place = np.full(len(known), -1, np.int32)
        place[large] = np.arange(len(large))
        here = np.zeros(words * 64, bool)
        bits = np.empty((len(large), words), np.uint64)
        for x, k in enumerate(large):
            here[:] = False
            here[members[start[k] : start[k] + size[k]]] = True
            bits[x] = np.packbits(here, bitorder="little").view(np.uint64)
        digits = []  # of the columns' n, as bits over the columns
        for d in range(int(c_n.max()).bit_length()):
            here[:] = False
            here[:width] = c_n >> d & 1
            digits.append((1 << d, np.packbits(here, bitorder="little").view(np.uint64)))

        r_ids, r_len, r_n = flat(rows)
        key = np.searchsorted(known, r_ids)
        key[key == len(known)] = 0
        good = known[key] == r_ids
        row, key = np.repeat(np.arange(len(r_n)), r_len)[good], key[good]
        del r_ids, good
        edge = np.searchsorted(row, np.arange(len(r_n) + 1))
        here = place[key] >= 0
        steps = np.bincount(row, weights=np.where(here, 0, size[key]), minlength=len(r_n)).astype(np.int64)
        held = np.bincount(row[here], minlength=len(r_n))

        # Rows of small blocks only: many at once.
        light = np.flatnonzero((held == 0) & (steps > 0) & (steps <= STEPS))
        cuts = np.searchsorted(np.cumsum(steps[light]), np.arange(STEPS, int(steps[light].sum()) + 2 * STEPS, STEPS), side="right")
        begun = 0
        for end in sorted(set(cuts.tolist()) | set(range(0, len(light), 100_000)) | {len(light)}):
            some, begun = light[begun:end], max(begun, end)
            if not len(some):
                continue
            span = runs(edge[some], edge[some + 1] - edge[some])
            k, n = key[span], size[key[span]]
            pair = np.unique(np.repeat(row[span], n) * width + members[runs(start[k], n)])
            total += int((r_n[pair // width] * c_n[pair % width]).sum())

        # The others: unions of some rows as bits, each large block put into those that have it.
        heavy = np.ones(len(r_n), bool)
        heavy[light] = False
        heavy = np.flatnonzero(heavy & (edge[1:] > edge[:-1]))
        one = np.uint64(1) << np.arange(64, dtype=np.uint64)
        for at in range(0, len(heavy), TOGETHER):
            some = heavy[at : at + TOGETHER]
            n = edge[some + 1] - edge[some]
            k, r = key[runs(edge[some], n)], np.repeat(np.arange(len(some)), n)
            p = place[k]
            union = np.zeros((len(some), words), np.uint64)
            by = np.flatnonzero(p >= 0)
            by = by[np.argsort(p[by], kind="stable")]
            cut = np.flatnonzero(np.diff(p[by], prepend=-1, append=-1)) if len(by) else []
            for a, b in zip(cut[:-1], cut[1:], strict=True):
                union[r[by[a:b]]] |= bits[p[by[a]]]
            k, r = k[p < 0], r[p < 0]
            cut = np.searchsorted(np.cumsum(size[k]), np.arange(0, int(size[k].sum()) + STEPS, STEPS), side="left")
            for a, b in zip(cut, [*cut[1:], len(k)], strict=True):
                to = members[runs(start[k[a:b]], size[k[a:b]])]
                np.bitwise_or.at(union.reshape(-1), np.repeat(r[a:b], size[k[a:b]]) * words + (to >> 6), one[to & 63])
            got = sum(w * np.bitwise_count(union & d).sum(axis=1, dtype=np.int64) for w, d in digits)
            total += int((r_n[some] * got).sum())
    return pa.table({"met": pa.array([total], pa.int64())})


def tiled(postings: DataFrame, task: str, cap: int = 1000) -> DataFrame:
    """As ``raw``; blocks with more than ``cap`` on a side are cut into tiles, so a frequent token is many tasks.

    A posting is repeated for each tile of the other side, not of its own; those of no use are left out before.
    """
    sizes = summary(postings, task).select("block_key", *[F.ceil(F.col(n) / cap).cast("int").alias(t) for n, t in (("n_left", "lt"), ("n_right" if task == "clean" else "n_left", "rt"))])
    sizes = written(sizes, "zstd")
    p = postings.join(F.broadcast(sizes) if fits(sizes) else sizes, "block_key")
    own = lambda t: F.pmod(F.xxhash64("entity_id"), F.col(t)).cast("int")
    every = lambda t: F.explode(F.sequence(F.lit(0), F.col(t) - 1))
    left = p.where("collection = 'L'") if task == "clean" else p
    right = p.where("collection = 'R'") if task == "clean" else p
    a = left.select("block_key", own("lt").alias("i"), every("rt").alias("j"), F.col("entity_id").alias("left_id"))
    b = right.select("block_key", every("lt").alias("i"), own("rt").alias("j"), F.col("entity_id").alias("right_id"))
    order = F.lit(True) if task == "clean" else F.col("left_id") < F.col("right_id")
    return a.join(b, ["block_key", "i", "j"]).where(order).select("left_id", "right_id")


def sketch(postings: DataFrame, task: str) -> DataFrame:
    """distinct_pairs by a HyperLogLog sketch of the raw pairs (about 1 % error); expands them all."""
    return raw(postings, task).agg(F.hll_sketch_estimate(F.hll_sketch_agg(F.xxhash64("left_id", "right_id"), 14)).alias("distinct_pairs"))


def estimate(postings: DataFrame, task: str, rate: float = 0.25, seed: int = 42) -> DataFrame:
    """sampled_blocks, sampled_pairs, distinct_pairs: an unbiased estimate from a share of the blocks.

    Blocks are drawn by the md5 of their key, which any engine repeats.  A pair of a drawn block counts 1 / m if it
    meets in m blocks, divided by the rate; only the drawn blocks are expanded.
    """
    drawn = F.conv(F.substring(F.md5(F.concat_ws("|", "block_key", F.lit(str(seed)))), 1, 8), 16, 10).cast("long") < int(rate * 2**32)
    good = useful(postings, task)
    some = good.where(drawn)
    met = raw(some, task).groupBy("left_id", "right_id").agg(F.count(F.lit(1)).alias("here"))
    keys = good.select("block_key", "entity_id").distinct()
    common = met.join(keys.withColumnRenamed("entity_id", "left_id"), "left_id").join(keys.withColumnRenamed("entity_id", "right_id"), ["right_id", "block_key"])
    shares = common.groupBy("left_id", "right_id").agg(F.max("here").alias("here"), F.count(F.lit(1)).alias("m"))
    blocks_ = some.agg(F.count_distinct("block_key").alias("sampled_blocks"))
    pairs_ = shares.agg(F.coalesce(F.sum("here"), F.lit(0)).alias("sampled_pairs"), F.coalesce(F.round(F.sum(F.col("here") / F.col("m")) / rate, 4), F.lit(0.0)).alias("distinct_pairs"))
    return blocks_.crossJoin(pairs_)


def all_pairs(desc: DataFrame, task: str) -> DataFrame:
    """Every pair: the exhaustive baseline, for tests on small data."""
    ids = desc.select("collection", "entity_id").distinct()
    if task == "clean":
        return ids.where("collection = 'L'").select(F.col("entity_id").alias("left_id")).crossJoin(ids.where("collection = 'R'").select(F.col("entity_id").alias("right_id")))
    a = ids.select(F.col("entity_id").alias("left_id"))
    return a.crossJoin(ids.select(F.col("entity_id").alias("right_id"))).where("left_id < right_id")
