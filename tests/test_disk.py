"""Work that must not grow with the number of pairs: what is shuffled, and unions of blocks beside brute force."""

import random

import pytest

from erblock.operators import attr_clustering, blocks, groundtruth, iterative, measures, missed, pairs, token_blocking

POSTINGS = "block_key string, collection string, entity_id string"


def shuffled(spark):
    """Bytes that this application has written to shuffles."""
    spark.sparkContext._jsc.sc().listenerBus().waitUntilEmpty(30_000)
    return spark.sparkContext._jsc.sc().statusStore().executorList(False).apply(0).totalShuffleWrite()


@pytest.mark.parametrize("task", ["clean", "dirty"])
def test_equal_blocks_are_counted_without_a_row_per_pair(spark, task):
    """60 blocks of 200 descriptions, as many dates are: their 10,000 pairs each are counted and not shuffled."""
    rows = [(f"k{k}", c, f"{c.lower()}-of-block-{k}-number-{e}") for k in range(60) for e in range(100) for c in "LR"]
    p = spark.createDataFrame(rows, POSTINGS).localCheckpoint()
    before = shuffled(spark)
    assert pairs.count(p, task).first()[0] == 60 * (100 * 100 if task == "clean" else 200 * 199 // 2)
    assert shuffled(spark) - before < 2_000_000


@pytest.mark.parametrize("task", ["clean", "dirty"])
def test_unions_of_blocks_with_many_keys(spark, task):
    """Blocks of all sizes, classes of several descriptions and an id in both collections, in tiles or one."""
    r = random.Random(3)
    rows = {(f"k{int(r.paretovariate(0.5)) % 400}", c, f"e{e}" if e < 5 else f"{c}{e % 150}") for e in range(400) for c in "LR" for _ in range(r.randint(0, 12))}
    rows |= {("same", c, f"{c}-same-{e}") for e in range(40) for c in "LR"}
    of = {}
    for k, c, e in rows:
        of.setdefault((c, e) if task == "clean" else e, set()).add(k)
    want = sum(not of[a].isdisjoint(of[b]) for a in of for b in of if (a[0] == "L" and b[0] == "R" if task == "clean" else a < b))
    p = spark.createDataFrame(sorted(rows), POSTINGS)
    assert [pairs.count(x, task, *more).first()[0] for x, *more in ((p,), (p, 100, 500), (blocks.bags(p), 7))] == [want] * 3


def test_tiles_repeat_a_posting_for_the_other_side_only(spark):
    """A frequent word on the left, two postings on the right: nothing is repeated for the left's own tiles."""
    rows = [("word", "L", f"left-description-{e}") for e in range(4_000)] + [("word", "R", f"r{e}") for e in range(2)] + [(f"only-{e}", "L", "x") for e in range(50)]
    p = spark.createDataFrame(rows, POSTINGS).localCheckpoint()
    before = shuffled(spark)
    assert pairs.tiled(p, "clean", 20).count() == 8_000
    assert shuffled(spark) - before < 500_000


def test_least_key_without_keys_in_the_shuffle(spark):
    """300 descriptions of 80 keys each against 3: the keys of each aren't shuffled with each of its postings."""
    rows = [(f"frequent-key-{k}", "L", f"l{e}") for e in range(300) for k in range(80)] + [(f"frequent-key-{k}", "R", f"r{e}") for e in range(3) for k in range(e, 80)]
    p = spark.createDataFrame(rows, POSTINGS).localCheckpoint()
    before = shuffled(spark)
    assert sorted(map(tuple, pairs.distinct(p, "clean", "min_key").collect())) == sorted((f"l{a}", f"r{b}") for a in range(300) for b in range(3))
    assert shuffled(spark) - before < 1_000_000


@pytest.mark.parametrize("sides", [False, True])
def test_rounds_with_known_matches_expand_no_pairs(spark, monkeypatch, sides):
    """A matcher that knows its matches leads to the same classes and comparisons as one that is asked for each pair."""
    r = random.Random(5)
    rows = {(f"k{r.randint(0, 25)}", "LR"[e % 2], f"e{e:02}") for e in range(30) for _ in range(r.randint(0, 4))}
    p = spark.createDataFrame(sorted(rows), POSTINGS)
    ids = sorted({e for _, _, e in rows})
    truth = spark.createDataFrame([(*sorted(r.sample(ids, 2)), "x") for _ in range(14)], "left_id string, right_id string, link_type string").localCheckpoint()
    matcher = iterative.oracle(truth)
    slow = iterative.run_rounds(p, lambda candidates, entity_map: matcher(candidates, entity_map), sides=sides)
    want = {x.entity_id: x.rep_id for x in slow.entity_map.collect()}
    expanded = []
    monkeypatch.setattr(iterative.pairs, "raw", lambda postings, task, old=pairs.raw: expanded.append(task) or old(postings, task))
    fast = iterative.run_rounds(p, matcher, sides=sides)
    assert {x.entity_id: x.rep_id for x in fast.entity_map.collect()} == want and fast.rounds == slow.rounds
    assert sorted(map(tuple, fast.compared.collect())) == sorted(map(tuple, slow.compared.collect()))
    assert expanded  # as plans, for whoever reads them
    if not sides:
        assert iterative.savings(fast, p).first() == iterative.savings(slow, p).first()


def test_common_tokens_by_hand_and_without_words_of_one_side_in_the_shuffle(spark, monkeypatch):
    """Words that all of one side have aren't shuffled with each description; the vocabulary sent whole, or its most frequent part."""
    r = random.Random(11)
    rows = [(c, f"{c}{e}", a, " ".join(r.choices([f"Word{w}" for w in range(12)] + [f"only-{c}"], k=r.randint(0, 5))), "literal") for c in "LR" for e in range(25) for a in ("x", "y")]
    rows += [("L", f"long-{e}", "text", " ".join(f"frequentword{w}" for w in range(250)), "literal") for e in range(300)]
    d = spark.createDataFrame(rows, "collection string, entity_id string, attribute string, value string, kind string").localCheckpoint()
    clusters = spark.createDataFrame([(c, "x", "k") for c in "LR"] + [("L", "y", "k"), ("R", "y", "l")], "collection string, attribute string, cluster_id string").localCheckpoint()
    for found, of in ((None, lambda c, a: ""), (clusters, lambda c, a: {"Ly": "k", "Ry": "l"}.get(c + a, "k" if a == "x" else None))):
        bags = {}
        for c, e, a, v, _ in rows:
            bags.setdefault((c, e), set()).update((of(c, a), t) for t in v.lower().replace("-", " ").split() if of(c, a) is not None)
        both = set.intersection(*[set().union(*[b for (c, _), b in bags.items() if c == side]) for side in "LR"])
        want = sorted(len(b & both) for b in bags.values())
        before = shuffled(spark)
        assert sorted(x.n for x in measures.common_tokens(d, found).collect()) == want
        assert shuffled(spark) - before < 400_000
        with monkeypatch.context() as m:
            m.setattr(measures, "fits", lambda df: df.count() <= 3)
            assert sorted(x.n for x in measures.common_tokens(d, found).collect()) == want


def test_missed_report_leaves_no_shuffle_to_its_reader(spark):
    """What is shuffled for the six measures is done, and deleted, before their few rows are read."""
    rows = [(c, f"{c}-description-{e}", "text", " ".join(f"w{(e * 7 + w) % 3001}x{c if e % 2 else ''}" for w in range(40)), "literal") for c in "LR" for e in range(300)]
    d = spark.createDataFrame(rows, "collection string, entity_id string, attribute string, value string, kind string").localCheckpoint()
    t = spark.createDataFrame([(f"L-description-{e}", f"R-description-{e}", "x") for e in range(300)], "left_id string, right_id string, link_type string").localCheckpoint()
    report = missed.report(token_blocking.build(d), t, groundtruth.edges(d))
    before = shuffled(spark)
    got = {x.measure: (x.numerator, x.denominator) for x in report.collect()}
    assert got["missed_pairs"] == (150, 150) and got["descriptions_with_neighbours"] == (0, 300)
    assert shuffled(spark) - before < 10_000


@pytest.mark.parametrize("task", ["clean", "dirty"])
def test_measures_shuffle_numbers_and_not_keys(spark, task):
    """A true pair is looked up by the numbers of its blocks; the keys, which don't compress, stay where they are."""
    r = random.Random(9)
    keys = [f"{r.getrandbits(256):064x}" for _ in range(2_000)]
    rows = [(c, f"{c}{e}", r.sample(keys, 100)) for e in range(200) for c in "LR"] + [("L", "none", [])]
    bags = spark.createDataFrame(rows, "collection string, entity_id string, keys array<string>").localCheckpoint()
    truth = spark.createDataFrame([(f"L{e}", f"R{e}", "x") for e in range(200)], "left_id string, right_id string, link_type string").localCheckpoint()
    before = shuffled(spark)
    got = measures.quality(bags, bags, truth, task).first()
    moved = shuffled(spark) - before
    of = {(c, e): set(k) for c, e, k in rows}
    assert got.tp == sum(not of["L", f"L{e}"].isdisjoint(of["R", f"R{e}"]) for e in range(200)) and got.tp + got.fn == 200
    ids = sorted(of)
    assert got.distinct_pairs == sum(not of[a].isdisjoint(of[b]) for a in ids for b in ids if (a[0] < b[0] if task == "clean" else a < b))
    assert got.exhaustive == str(201 * 200 if task == "clean" else 401 * 400 // 2)
    assert moved < 3_500_000, moved


def test_bags_of_values_are_those_of_postings(spark):
    """Made without a row per token, with a row for a description without any."""
    desc = spark.createDataFrame([("L", "a", "name", "Red red, box", "literal"), ("L", "a", "size", "12 red", "literal"), ("L", "b", "name", "-", "literal"), ("R", "a", "label", "red Fox", "literal"), ("R", "c", "other", "zzz", "literal")], "collection string, entity_id string, attribute string, value string, kind string")
    for of in (token_blocking, attr_clustering):
        want = {(x.collection, x.entity_id): set(x["keys"]) for x in blocks.bags(of.build(desc)).collect()}
        got = of.bags(desc).collect()
        assert sorted((x.collection, x.entity_id) for x in got) == [("L", "a"), ("L", "b"), ("R", "a"), ("R", "c")]
        assert all(len(x["keys"]) == len(set(x["keys"])) and set(x["keys"]) == want.get((x.collection, x.entity_id), set()) for x in got)
