"""Iterative blocking on the blocks of another method.

``run_sequential`` follows the method to the letter: one block after the other, a match replaces both
descriptions by their union in all blocks, until a pass changes nothing.  It runs per connected component of the
block graph, as components cannot influence each other, and is the reference for small data.

``run_rounds`` is its form for a cluster: each round compares all pairs of current representatives that share
a block and have not been compared, merges along connected components of the matches and relabels the
postings.  A merged description is new: it is compared anew with what its members were compared with.  With a matcher that stays true under merging both reach the same partition.
"""

from __future__ import annotations

from collections.abc import Callable, Iterable
from dataclasses import dataclass
from functools import reduce

import numpy as np
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from erblock.functions.cut import checkpoint, fits, written
from erblock.operators import blocks, pairs
from erblock.operators.components import connected

#: (pairs a < b of representatives, entity_map) -> matching pairs.
Matcher = Callable[[DataFrame, DataFrame], DataFrame]


def oracle(truth: DataFrame) -> Matcher:
    """Matches when members of both are a true pair."""

    def known(entity_map: DataFrame) -> DataFrame:
        rep = lambda side: entity_map.select(F.col("entity_id").alias(f"{side}_id"), F.col("rep_id").alias(f"{side}_rep"))
        both = truth.select("left_id", "right_id").join(rep("left"), "left_id").join(rep("right"), "right_id")
        return both.select(F.least("left_rep", "right_rep").alias("a"), F.greatest("left_rep", "right_rep").alias("b")).where("a <> b").distinct()

    def match(candidates: DataFrame, entity_map: DataFrame) -> DataFrame:
        return candidates.join(known(entity_map), ["a", "b"], "left_semi")

    match.known = known  # all that can match, so that candidates needn't be expanded to find the matches among them
    return match


def jaccard(tokens: DataFrame, theta: float) -> Matcher:
    """Matches when the token sets (entity_id, token) of the merged descriptions have similarity >= theta."""

    def match(candidates: DataFrame, entity_map: DataFrame) -> DataFrame:
        merged = tokens.join(entity_map, "entity_id").select("rep_id", "token").distinct()
        size = merged.groupBy("rep_id").agg(F.count(F.lit(1)).alias("n"))
        left = candidates.join(merged.withColumnRenamed("rep_id", "a"), "a")
        inter = left.join(merged.withColumnRenamed("rep_id", "b"), ["b", "token"], "left_semi").groupBy("a", "b").agg(F.count(F.lit(1)).alias("i"))
        sized = inter.join(size.select(F.col("rep_id").alias("a"), F.col("n").alias("na")), "a").join(size.select(F.col("rep_id").alias("b"), F.col("n").alias("nb")), "b")
        return sized.where(F.col("i") >= theta * (F.col("na") + F.col("nb") - F.col("i"))).select("a", "b")

    return match


@dataclass
class Run:
    """Outcome: entity_map (entity_id, rep_id), compared (a, b, round; expanded only when it is read, if the matcher knows its
    matches), rounds, if it reached a fixpoint, performed (one row), the number of comparisons, and suggested (one row), that of
    the blocks with repeats, where it is known."""

    entity_map: DataFrame
    compared: DataFrame
    rounds: int
    converged: bool
    performed: Callable[[], DataFrame] | None = None
    suggested: DataFrame | None = None


def run_rounds(postings: DataFrame, matcher: Matcher, max_rounds: int = 20, partial: bool = False, sides: bool = False) -> Run:
    """Bulk-synchronous iterative blocking of a dirty collection; with ``sides`` only descriptions (or unions) that
    lie on different sides of two clean collections are compared.

    Raises if ``max_rounds`` do not reach a fixpoint, rather than return a wrong answer; with ``partial`` the state
    after them is what is asked for.  ``postings`` may be ``blocks.bags``.
    """
    if hasattr(matcher, "known"):
        return _known_rounds(postings, matcher, max_rounds, partial, sides)
    postings = blocks.unbagged(postings)
    side = checkpoint(postings.select("entity_id", F.when(F.col("collection") == "R", 2).otherwise(1).alias("side")).distinct()) if sides else None
    postings = checkpoint(postings.select("block_key", "entity_id").distinct())
    entity_map = postings.select("entity_id").distinct().withColumn("rep_id", F.col("entity_id"))
    entity_map = checkpoint(entity_map)
    compared = done = None  # every comparison; those between descriptions as they are now
    for number in range(1, max_rounds + 1):
        now = postings.join(entity_map, "entity_id").select("block_key", F.lit("L").alias("collection"), F.col("rep_id").alias("entity_id")).distinct()
        todo = pairs.distinct(now, "dirty").select(F.col("left_id").alias("a"), F.col("right_id").alias("b"))
        if side is not None:
            held = entity_map.join(side, "entity_id").groupBy("rep_id").agg(F.bit_or("side").alias("held"))
            held = [held.select(F.col("rep_id").alias(x), F.col("held").alias(f"{x}_held")) for x in "ab"]
            todo = todo.join(held[0], "a").join(held[1], "b").where("a_held | b_held = 3").select("a", "b")
        if done is not None:
            todo = todo.join(done, ["a", "b"], "left_anti")
        todo = checkpoint(todo.withColumn("round", F.lit(number)))
        compared = todo if compared is None else compared.unionByName(todo)
        done = todo.select("a", "b") if done is None else done.unionByName(todo.select("a", "b"))
        found = checkpoint(matcher(todo.select("a", "b"), entity_map))
        if found.limit(1).count() == 0:
            return Run(entity_map, compared, number, True)
        comp = connected(found, "a", "b")
        joined = entity_map.join(comp.withColumnRenamed("node", "rep_id"), "rep_id", "left")
        entity_map = checkpoint(joined.select("entity_id", F.coalesce("component", "rep_id").alias("rep_id")))
        merged = checkpoint(comp.select("node"))
        done = checkpoint(done.join(merged.withColumnRenamed("node", "a"), "a", "left_anti").join(merged.withColumnRenamed("node", "b"), "b", "left_anti").select("a", "b"))
    if not partial:
        raise RuntimeError(f"iterative blocking did not settle in {max_rounds} rounds")
    return Run(entity_map, compared, max_rounds, False)


def _known_rounds(postings: DataFrame, matcher: Matcher, max_rounds: int, partial: bool, sides: bool) -> Run:
    """``run_rounds`` for a matcher that names all pairs which can match: those that share a block are the matches.

    What is compared in a round are the pairs with a common block of which one was merged in the round before (all, in the
    first); that is left as a plan, and counted without expansion.  Keys go as numbers, useful ones only, and a round makes
    anew the descriptions that the one before merged; the others stay as they are.
    """
    rows = postings if "keys" in postings.columns else written(blocks.bags(postings), "zstd")
    every = rows.select("entity_id", F.when(F.col("collection") == "R", 2).otherwise(1).alias("side"))
    useful, numbers = pairs.numbered(rows, "dirty")
    # An id of both collections is one description.
    own = numbers.select("entity_id", "ids", F.when(F.col("collection") == "R", 2).otherwise(1).alias("side"))
    own = own.groupBy("entity_id").agg(F.array_distinct(F.flatten(F.collect_list("ids"))).alias("keys"), F.bit_or("side").alias("held")) if pairs.shares_ids(numbers) else own.withColumnsRenamed({"ids": "keys", "side": "held"})
    now = own.withColumn("new", F.lit(True)).select("entity_id", "keys", "held", "new")
    entity_map = checkpoint(every.select("entity_id").distinct().withColumn("rep_id", F.col("entity_id")))
    compared, counts, settled = None, [], False
    for number in range(1, max_rounds + 1):
        is_new = [now.select(F.col("entity_id").alias(x), F.col("held").alias(f"{x}_held"), F.col("new").alias(f"{x}_new")) for x in "ab"]
        across = lambda p, on=is_new: p.join(on[0], "a").join(on[1], "b").where("a_held | b_held = 3" if sides else "true")
        todo = pairs.distinct(blocks.unbagged(now.select(F.lit("L").alias("collection"), "entity_id", "keys")), "dirty").select(F.col("left_id").alias("a"), F.col("right_id").alias("b"))
        todo = across(todo).where("a_new or b_new").select("a", "b", F.lit(number).alias("round"))
        compared = todo if compared is None else compared.unionByName(todo)
        counts.append(now)
        can = written(matcher.known(entity_map), "zstd")
        # Only descriptions that can match are looked up.
        ids = can.select(F.col("a").alias("entity_id")).unionByName(can.select(F.col("b").alias("entity_id"))).distinct()
        asked = now.join(F.broadcast(ids) if fits(ids) else ids, "entity_id", "left_semi").select(F.lit("L").alias("collection"), "entity_id", "keys")
        found = blocks.same_block(asked, can.select(F.col("a").alias("left_id"), F.col("b").alias("right_id"))).select(F.col("left_id").alias("a"), F.col("right_id").alias("b"))
        found = written(across(found).select("a", "b"), "zstd")
        settled = found.limit(1).count() == 0
        if settled:
            break
        comp = written(connected(found, "a", "b"), "zstd")
        to = comp.select(F.col("node").alias("rep_id"), "component")
        to = F.broadcast(to) if fits(to) else to
        entity_map = checkpoint(entity_map.join(to, "rep_id", "left").select("entity_id", F.coalesce("component", "rep_id").alias("rep_id")))
        to = to.withColumnRenamed("rep_id", "entity_id")
        union = now.join(to, "entity_id").groupBy("component").agg(F.array_distinct(F.flatten(F.collect_list("keys"))).alias("keys"), F.bit_or("held").alias("held"))
        union = union.select(F.col("component").alias("entity_id"), "keys", "held", F.lit(True).alias("new"))
        now = written(now.join(to, "entity_id", "left_anti").withColumn("new", F.lit(False)).unionByName(union), "zstd")
    if not settled and not partial:
        raise RuntimeError(f"iterative blocking did not settle in {max_rounds} rounds")

    def performed() -> DataFrame:
        first = pairs.count_numbered(own.select(F.lit("L").alias("collection"), "entity_id", F.col("keys").alias("ids")), "dirty", False).first()[0]
        return own.sparkSession.range(1).select(F.lit(first + sum(map(pairs.count_new, counts[1:]))).cast("long").alias("performed"))

    suggested = useful.agg(F.coalesce(F.sum("comparisons"), F.lit(0)).alias("suggested"))
    return Run(entity_map, compared, number, settled, None if sides else performed, suggested)


def merge(desc: DataFrame, entity_map: DataFrame) -> DataFrame:
    """Merged descriptions: the union of the attribute-value pairs of each class."""
    named = desc.join(entity_map, "entity_id", "left")
    return named.select("collection", F.coalesce("rep_id", "entity_id").alias("entity_id"), "attribute", "value", "kind").distinct()


def savings(run: Run, postings: DataFrame) -> DataFrame:
    """performed (pairs compared), suggested (with repeats) and their ratio."""
    suggested = run.suggested
    if suggested is None:
        suggested = blocks.summary(blocks.unbagged(postings), "dirty").agg(F.coalesce(F.sum("comparisons"), F.lit(0)).alias("suggested"))
    done = run.performed() if run.performed else run.compared.agg(F.count(F.lit(1)).alias("performed"))
    return done.crossJoin(suggested).select("performed", F.col("suggested").cast("string").alias("suggested"), F.round(F.try_divide("performed", F.col("suggested").cast("double")), 10).alias("ratio"))


def gain(postings: DataFrame, truth: DataFrame, run: Run) -> DataFrame:
    """matches, found_by_blocks, found_by_iteration (true pairs in one class), and both recalls."""
    known = truth.select("left_id", "right_id").distinct()
    rep = lambda side: run.entity_map.select(F.col("entity_id").alias(f"{side}_id"), F.col("rep_id").alias(side))
    joined = known.join(rep("left"), "left_id", "left").join(rep("right"), "right_id", "left")
    after = joined.agg(F.count(F.lit(1)).alias("matches"), F.count_if(F.col("left") == F.col("right")).alias("found_by_iteration"))
    before = blocks.same_block(postings, known).agg(F.count(F.lit(1)).alias("found_by_blocks"))
    share = lambda c: F.round(F.try_divide(F.col(c), F.col("matches").cast("double")), 10)
    return after.crossJoin(before).select("matches", "found_by_blocks", "found_by_iteration", share("found_by_blocks").alias("recall_of_blocks"), share("found_by_iteration").alias("recall_of_iteration"))


def gained(run: Run, candidates: DataFrame) -> DataFrame:
    """Pairs of one class that no block held (reached through a third description)."""
    m = run.entity_map
    other = m.select(F.col("entity_id").alias("right_id"), F.col("rep_id").alias("r"))
    inside = m.join(other, m["rep_id"] == other["r"]).where("entity_id < right_id").select(F.col("entity_id").alias("left_id"), "right_id")
    return inside.join(candidates, ["left_id", "right_id"], "left_anti")


# ---------------------------------------------------------------- the sequential reference


def resolve(block_list: Iterable[tuple[str, list[str]]], token_sets: dict[str, set[str]], same: Callable[[set[str], set[str], frozenset, frozenset], bool], max_passes: int | None = None) -> tuple[dict[str, str], int, int]:
    """(entity -> representative, comparisons, passes) for blocks in the order given."""
    # Entities are numbered in the order of their ids, and what a representative was compared with is an integer
    # of bits, so pairs that are done cost no step each and all pairs of a component fit in memory as bits.
    ids = sorted({e for _, members in block_list for e in members})
    number = {e: i for i, e in enumerate(ids)}
    rep = list(range(len(ids)))
    members = [frozenset((e,)) for e in ids]
    tokens = [set(token_sets.get(e, ())) for e in ids]
    numbered = [sorted(number[e] for e in v) for _, v in block_list]
    done = [0] * len(ids)
    compared = passes = 0
    changed = True
    while changed and (max_passes is None or passes < max_passes):
        changed, passes = False, passes + 1
        for block in numbered:
            again = True
            while again:
                again = False
                now = sorted({rep[i] for i in block})
                behind = 0
                for a in now:
                    behind |= 1 << a
                for a in now:
                    behind ^= 1 << a
                    todo = behind & ~done[a]
                    while todo:
                        bit = todo & -todo
                        todo ^= bit
                        done[a] |= bit
                        b = bit.bit_length() - 1
                        compared += 1
                        if same(tokens[a], tokens[b], members[a], members[b]):
                            # The union is a new description: what it was compared with before doesn't count.
                            tokens[a], tokens[b] = tokens[a] | tokens[b], set()
                            members[a], members[b] = members[a] | members[b], frozenset()
                            for e in members[a]:
                                rep[number[e]] = a
                            done[a], gone = 0, ~(1 << a)
                            for x in range(a):
                                done[x] &= gone
                            changed = again = True
                            break
                    if again:
                        break
    return {e: ids[rep[i]] for i, e in enumerate(ids)}, compared, passes


#: Descriptions of a block that are compared together.
ROWS = 256


def resolve_known(block_list: Iterable[np.ndarray], n: int, links: dict[int, set[int]], max_passes: int | None = None) -> tuple[np.ndarray, int, int]:
    """``resolve`` of descriptions 0 to n - 1 whose matches are known: sorted members of the blocks in order, and a symmetric
    table of links.  Pairs up to the next match are compared together, as bits.
    """
    block_list = list(block_list)
    links = {x: set(y) - {x} for x, y in links.items()}
    rep = np.arange(n)
    held = {}  # members of unions
    words = -(-n // 64)
    one = np.uint64(1) << (np.arange(64, dtype=np.uint64))
    after = np.array([~np.uint64(0) << np.uint64(k) << np.uint64(1) if k < 63 else np.uint64(0) for k in range(64)], dtype=np.uint64)

    def behind(a: int) -> np.ndarray:
        row = np.zeros(words, np.uint64)
        row[a >> 6] = after[a & 63]
        row[(a >> 6) + 1 :] = ~np.uint64(0)
        return row

    # Bit b > a of row a: representatives a and b, as they are now, have not been compared.
    todo = np.empty((n, words), np.uint64)
    for a in range(n):
        todo[a] = behind(a)
    compared = passes = 0

    def compare(some: np.ndarray, cols: np.ndarray | slice, bits: np.ndarray) -> int:
        k = 0
        for lo in range(0, len(some), ROWS):
            at = (some[lo : lo + ROWS], cols) if isinstance(cols, slice) else np.ix_(some[lo : lo + ROWS], cols)
            old = todo[at]
            new = old & bits
            k += int(np.bitwise_count(new).sum())
            todo[at] = old ^ new
        return k

    changed = True
    while changed and (max_passes is None or passes < max_passes):
        changed, passes = False, passes + 1
        for block in block_list:
            now = np.unique(rep[block])
            inside, linked = set(now.tolist()), None
            fresh = -1  # union that all before it have yet to be compared with; what is before it is done else
            while True:
                word, bit = now >> 6, one[now & 63]
                cols = np.unique(word)
                bits = np.zeros(len(cols), np.uint64)
                np.bitwise_or.at(bits, np.searchsorted(cols, word), bit)
                if len(cols) * 2 > words:
                    full = np.zeros(words, np.uint64)
                    full[cols] = bits
                    cols, bits = slice(None), full
                linked = sorted(x for x in (links.keys() & inside if linked is None or len(links) < len(linked) else linked) if x in inside and x in links)
                a, b = next(((x, min(y)) for x in linked if (y := [z for z in links[x] if z > x and z in inside])), (-1, -1))
                end = len(now) if a < 0 else int(np.searchsorted(now, a))
                begin = min(end, int(np.searchsorted(now, fresh))) if fresh >= 0 else 0
                if begin:
                    compared += compare(now[:begin], np.array([fresh >> 6]), one[fresh & 63])
                compared += compare(now[begin:end], cols, bits)
                if a < 0:
                    break
                upto = now[now <= b]
                row = np.zeros(words, np.uint64)
                np.bitwise_or.at(row, upto >> 6, one[upto & 63])
                compared += int(np.bitwise_count(todo[a] & row).sum())
                # The union is a new description: what it was compared with before doesn't count.
                todo[a] = behind(a)
                todo[:a, a >> 6] |= one[a & 63]
                gone = held.pop(b, [b])
                held.setdefault(a, [a]).extend(gone)
                rep[gone] = a
                for z in (others := links.pop(b)):
                    links[z].discard(b)
                    if z != a:
                        links[z].add(a)
                links[a] = (links[a] | others) - {a, b}
                inside.discard(b)
                now, fresh, changed = now[now != b], a, True
                linked = sorted({*linked, a})
    return rep, compared, passes


def _sequential_known(keyed: DataFrame, truth: DataFrame, max_passes: int | None) -> DataFrame:
    """``run_sequential`` by truth of (component, block_key, entity_id); a task gets numbers, a row per block."""
    ids = keyed.select("component", "entity_id").distinct()
    ids = written(ids.withColumn("number", F.row_number().over(Window.partitionBy("component").orderBy("entity_id")) - 1), "zstd")
    blocked = keyed.join(ids, ["component", "entity_id"]).groupBy("component", "block_key").agg(F.array_sort(F.collect_set("number")).alias("numbers"))
    both = truth.select(F.col("left_id").alias("entity_id"), F.col("right_id").alias("o")).unionByName(truth.select(F.col("right_id").alias("entity_id"), F.col("left_id").alias("o")))
    other = ids.select("component", F.col("entity_id").alias("o"), F.col("number").alias("at"))
    linked = ids.join(both, "entity_id").join(other, ["component", "o"]).groupBy("component", "entity_id").agg(F.collect_set("at").alias("numbers"))
    facts = ids.join(linked, ["component", "entity_id"], "left")
    rich = blocked.withColumns({"entity_id": F.lit(None).cast("string"), "number": F.lit(None).cast("int")}).unionByName(facts.withColumn("block_key", F.lit(None).cast("string")))

    def one(table):  # noqa: ANN001, ANN202
        import pyarrow as pa
        import pyarrow.compute as pc

        of = pc.is_valid(table.column("number"))
        known = table.filter(of).sort_by("number")
        links = {i: set(x.as_py()) for i, x in enumerate(known.column("numbers")) if x.is_valid}
        blocks_ = table.filter(pc.invert(of)).select(["block_key", "numbers"])
        keys = blocks_.column("block_key").to_pylist()
        lists = [x.values.to_numpy().astype(np.int64) for x in blocks_.column("numbers")]
        rep, n, passes = resolve_known((lists[i] for i in sorted(range(len(keys)), key=keys.__getitem__)), known.num_rows, links, max_passes)
        names = known.column("entity_id")
        same = lambda x, kind: pa.array([x] * len(rep), kind)
        return pa.table({"entity_id": names, "rep_id": names.take(pa.array(rep)), "comparisons": same(n, pa.int64()), "passes": same(passes, pa.int64()), "component": known.column("component")})

    return rich.groupBy("component").applyInArrow(one, "entity_id string, rep_id string, comparisons long, passes long, component string")


def run_sequential(postings: DataFrame, tokens: DataFrame, theta: float | None = None, truth: DataFrame | None = None, max_passes: int | None = None) -> DataFrame:
    """entity_id, rep_id, comparisons, passes; matches by token Jaccard (theta) or by truth.

    One task per connected component of the block graph; a component must fit in it (reference method).
    """
    useful = blocks.useful(postings, "dirty").select("block_key", "entity_id")
    least = useful.groupBy("block_key").agg(F.min("entity_id").alias("m"))
    comp = connected(useful.join(least, "block_key"), "entity_id", "m")
    keyed = useful.join(comp, useful["entity_id"] == comp["node"]).select("component", "block_key", "entity_id")
    if theta is None and truth is not None:
        return _sequential_known(keyed, truth, max_passes)
    # A row per posting, and one per entity with its tokens and links, so that these don't travel with every posting.
    facts = keyed.select("component", F.lit(None).cast("string").alias("block_key"), "entity_id").distinct()
    if truth is None:
        toks = tokens.groupBy("entity_id").agg(F.collect_set("token").alias("tokens"))
        facts = facts.join(toks, "entity_id", "left").withColumn("links", F.array().cast("array<string>"))
    else:
        both = truth.select(F.col("left_id").alias("entity_id"), F.col("right_id").alias("o")).unionByName(truth.select(F.col("right_id").alias("entity_id"), F.col("left_id").alias("o")))
        linked = both.groupBy("entity_id").agg(F.collect_set("o").alias("links"))
        facts = facts.join(linked, "entity_id", "left").withColumn("tokens", F.array().cast("array<string>"))
    rich = keyed.unionByName(facts, allowMissingColumns=True)

    def one(pdf):  # noqa: ANN001, ANN202
        import pandas as pd

        known = pdf[pdf["block_key"].isna()]
        links = {e: set(() if x is None else x) for e, x in zip(known["entity_id"], known["links"], strict=True)}

        def same(ta: set, tb: set, ma: frozenset, mb: frozenset) -> bool:
            if theta is None:
                return any(not links[e].isdisjoint(mb) for e in ma)
            return len(ta & tb) >= theta * max(1, len(ta | tb))

        sets = {e: set(() if x is None else x) for e, x in zip(known["entity_id"], known["tokens"], strict=True)}
        grouped = sorted((k, sorted(set(g))) for k, g in pdf[pdf["block_key"].notna()].groupby("block_key")["entity_id"])
        rep, n, passes = resolve(grouped, sets, same, max_passes)
        return pd.DataFrame({"entity_id": list(rep), "rep_id": list(rep.values()), "comparisons": n, "passes": passes, "component": pdf["component"].iloc[0]})

    return rich.groupBy("component").applyInPandas(one, "entity_id string, rep_id string, comparisons long, passes long, component string")
