"""The engine on the given tables and on small data: counts, measures, missed matches, iterative blocking, joins in time, sinks."""

import datetime
import itertools
import random

import pytest
from pyspark.sql import functions as F

from erblock import registry
from erblock.functions.cut import discard, fits, written
from erblock.operators import around, attr_clustering, blocks, groundtruth, iterative, measures, missed, pairs, token_blocking, uri_infix
from erblock.plans import workloads
from erblock.sources import ingest, views

SF = "/root/testdata/sf0.001"
POSTINGS = "block_key string, collection string, entity_id string"
LINK = "left_id string, right_id string, link_type string"


def _postings(spark, seed, n=30, keys=12):
    r = random.Random(seed)
    rows = {(f"k{r.randint(0, keys)}", "L" if e % 2 else "R", f"e{e}") for e in range(n) for _ in range(r.randint(0, 5))}
    rows |= {("all", "L" if e % 2 else "R", f"e{e}") for e in range(n) if e % 3}
    return rows, spark.createDataFrame(sorted(rows), POSTINGS)


@pytest.mark.parametrize("seed", range(2))
@pytest.mark.parametrize("task", ["clean", "dirty"])
def test_pairs_counted_by_signatures(spark, seed, task):
    rows, p = _postings(spark, seed)
    want = set()
    for (k, c, e), (l, d, f) in itertools.product(rows, rows):
        if k == l and (c == "L" and d == "R" if task == "clean" else e < f):
            want.add((e, f))
    for bits, most in ((1, 4000), (60, 4000), (24, 3)):
        assert pairs.count(p, task, bits, most).first()[0] == len(want)
    assert pairs.distinct(p, task).count() == pairs.distinct(p, task, "min_key").count() == len(want)
    full = pairs.estimate(p, task, rate=1.0).first()
    assert full.distinct_pairs == pytest.approx(len(want))


def test_purge_and_hashed_keys(spark):
    _, p = _postings(spark, 7)
    assert blocks.purge(p, "dirty").count() == p.count()
    few = blocks.summary(blocks.purge(p, "dirty", 20), "dirty")
    assert few.agg(F.max("comparisons")).first()[0] <= 20
    hashed = blocks.hash_keys(p)
    assert hashed.count() == p.count() and hashed.select("block_key").distinct().count() == p.select("block_key").distinct().count()
    assert blocks.summary(hashed, "dirty").agg(F.sum("comparisons")).first() == blocks.summary(p, "dirty").agg(F.sum("comparisons")).first()


def test_ingest_of_truth_and_collections(spark):
    triples = spark.createDataFrame(
        [("x", "a", "same", "b", "uri"), ("x", "b", "same", "c", "uri"), ("x", "c", "name", "n", "literal"), ("x", "d", "same", "a", "uri")],
        "collection string, subject string, predicate string, object string, object_kind string",
    )
    truth = spark.createDataFrame([("b", "a", "equivalence"), ("a", "d", "equivalence")], LINK)
    assert ingest.hide_truth(triples, "same").count() == 1
    assert sorted(r.subject for r in ingest.hide_truth(triples, "same", truth).collect()) == ["b", "c"]
    d = ingest.descriptions(triples)
    assert {r.entity_id for r in ingest.keep_linked(d, truth, "left").collect()} == {"a", "b"}
    both = ingest.combine_clean(d, d)
    assert both.where("collection = 'R'").count() == 4 and ingest.combine_dirty(d, d).count() == 8


def test_passages_are_found_without_comparing_all(spark):
    docs = spark.createDataFrame(
        [(1, "a b c d e f g h i"), (2, "xa b c d e f g hx"), (3, "a b c d e f  g h"), (4, None), (5, "short p"), (6, ""), (7, "a b c d e f g h " * 3)], "doc_id long, text string"
    )
    items = spark.createDataFrame([(1, "a b c d e f g h"), (2, "ort"), (3, None), (4, "b c d e f g h"), (5, "")], "item_id long, text string")
    want = {(d.doc_id, i.item_id) for d in docs.collect() for i in items.collect() if d.text is not None and i.text is not None and i.text in d.text}
    assert {tuple(r) for r in views.contained(docs, items).collect()} == want


@pytest.mark.parametrize("name", ["d1", "d2", "d3", "d4", "d5"])
def test_missed_matches_have_content(spark, name):
    d, t = views.load(spark, SF, name, "dirty")
    got = {r.measure: r.numerator for r in missed.report(token_blocking.build(d), t, groundtruth.edges(d)).collect()}
    assert got["missed_pairs"] > 0 and got["descriptions_with_neighbours"] > 0
    if name in ("d2", "d3", "d4"):
        assert got["pairs_with_matching_neighbours"] > 0 and got["descriptions_with_matched_neighbours"] > 0
    if name == "d2":
        assert got["pairs_with_common_match"] > 0


def test_matches_have_matching_neighbours_more_often(spark):
    rows = {(r.name, r.kind): r for r in registry.queries()["st_report"](spark, SF).collect()}
    assert {n for n, _ in rows} == set(registry.LINKED)
    for n in ("d2", "d3", "d4"):
        assert rows[n, "match"].with_matching_neighbours > rows[n, "non_match"].with_matching_neighbours
    d, t = views.load(spark, SF, "d2", "clean")
    wrong = missed.sample_non_matches(d, t, 50)
    assert wrong.count() == 50 and wrong.join(t, ["left_id", "right_id"]).count() == 0


def test_invariants_of_missed_matches(spark):
    d, t = views.load(spark, SF, "d2", "clean")
    r = missed.split_by_clusters(token_blocking.build(d), attr_clustering.build(d), t).first()
    assert r.missed_token_only == 0 and r.missed_attribute == r.missed_token + r.split
    infixes, literals = uri_infix.infix_postings(uri_infix.infixes(d)), token_blocking.build(d, kinds=("literal",))
    r = missed.split_by_parts(literals, infixes, uri_infix.build(d), t).first()
    assert r.missed_uri <= r.without_token_and_infix


def test_methods_behave_as_reported(spark):
    some = ("d2", "d3", "d4", "d6")
    rows = {(r.method, r.collection, r.task): r for r in workloads.matrix(spark, SF, some, ("token", "attribute", "uri")).collect()}
    for c in some:
        token, attribute = rows["token", c, "clean"], rows["attribute", c, "clean"]
        assert attribute.recall <= token.recall and attribute.distinct_pairs <= token.distinct_pairs
        assert attribute.precision >= token.precision or attribute.tp < token.tp
        assert rows["token", c, "dirty"].redundancy >= 1
    assert rows["token", "d6", "dirty"].rr < 0 and rows["token", "d6", "dirty"].h3r is None
    assert rows["uri", "d4", "clean"].recall > rows["token", "d4", "clean"].recall  # shared naming
    assert rows["uri", "d3", "clean"].recall <= rows["token", "d3", "clean"].recall  # opaque ids
    assert not any(m.startswith("uri") and c == "d6" for m, c, _ in rows)
    assert all(r.precision is not None and r.f is not None for r in rows.values())


def test_links_of_other_kinds(spark):
    got = {(r.dataset, r.link_type): r.recall for r in registry.queries()["rl_recall_by_link"](spark, SF).collect()}
    assert got["copies", "is_like"] > got["shipments", "subject"] > got["shipments", "coverage"] > got["users", "subject"]
    assert got["customers", "based_near"] > got["shipments", "coverage"]


@pytest.mark.parametrize("seed", range(2))
def test_rounds_reach_the_sequential_partition(spark, seed):
    """Oracle matcher, which stays true under merging: rounds and the method to the letter agree."""
    r = random.Random(seed)
    rows, p = _postings(spark, seed, 24, 30)
    ids = sorted({e for _, _, e in rows})
    truth = spark.createDataFrame([(*sorted(r.sample(ids, 2)), "equivalence") for _ in range(10)], LINK)
    tokens = p.select("entity_id", F.col("block_key").alias("token")).distinct()
    run = iterative.run_rounds(p, iterative.oracle(truth))
    one = iterative.run_sequential(p, tokens, truth=truth)
    got = {x.entity_id: x.rep_id for x in run.entity_map.collect()}
    for x in one.collect():
        assert got[x.entity_id] == got[x.rep_id]
    assert len({got[x.entity_id] for x in one.collect()}) == one.select("rep_id").distinct().count()
    gain = iterative.gain(p, truth, run).first()
    assert gain.found_by_iteration >= gain.found_by_blocks


def test_jaccard_rounds_end_where_nothing_is_alike(spark):
    r = random.Random(11)
    rows = {(f"t{r.randint(0, 14)}", "L", f"e{e}") for e in range(18) for _ in range(5)}
    p = spark.createDataFrame(sorted(rows), POSTINGS)
    tokens = p.select("entity_id", F.col("block_key").alias("token"))
    run = iterative.run_rounds(p, iterative.jaccard(tokens, 0.6))
    rep = {x.entity_id: x.rep_id for x in run.entity_map.collect()}
    sets = {}
    for t, _, e in rows:
        sets.setdefault(rep[e], set()).add(t)
    for a, b in itertools.combinations(sets, 2):
        assert len(sets[a] & sets[b]) < 0.6 * len(sets[a] | sets[b])


def test_no_gain_between_two_clean_collections(spark):
    """Descriptions that have no duplicate on their own side gain nothing from merging."""
    d, t = views.load(spark, SF, "d6", "clean")
    p = token_blocking.build(d)
    gain = iterative.gain(p, t, iterative.run_rounds(p, iterative.oracle(t), sides=True)).first()
    assert gain.recall_of_iteration == gain.recall_of_blocks


def test_asof_and_interval_joins(spark):
    r = random.Random(3)
    start = datetime.datetime(2024, 1, 1)
    make = lambda n, i: [(i * 1000 + k, None if r.random() < 0.05 else ("hot" if r.random() < 0.5 else f"u{r.randint(0, 4)}"), start + datetime.timedelta(seconds=r.randint(0, 400_000) // 600 * 600)) for k in range(n)]
    a, b = make(150, 1), make(150, 2)
    schema = "event_id long, user_id string, ts timestamp"
    left, right = spark.createDataFrame(a, schema), spark.createDataFrame(b, schema)
    got = {x.event_id: x.as_of for x in around.asof_join(left, right, "user_id", "ts").collect()}
    for i, u, at in a:
        before = [t for _, v, t in b if u is not None and v == u and t <= at]
        assert got[i] == (max(before) if before else None)
    near = {(x.left_id, x.right_id) for x in around.interval_join(left, right, "user_id", "ts", "event_id", 1800).collect()}
    assert near == {(i, j) for i, u, x in a for j, v, y in b if u is not None and u == v and abs((x - y).total_seconds()) <= 1800}


def test_sinks(spark, tmp_path):
    rows, p = _postings(spark, 5)
    around.save_postings(p, str(tmp_path / "p"), 8)
    one = around.postings_of(spark, str(tmp_path / "p"), "k3", 8)
    assert {tuple(x) for x in one.collect()} == {x for x in rows if x[0] == "k3"}
    assert "PartitionFilters: [isnotnull(bucket" in one._jdf.queryExecution().toString()
    kept = written(p)
    assert sorted(map(tuple, kept.collect())) == sorted(rows) and fits(kept) and not fits(kept, 100)
    discard(kept)
    assert fits(spark.createDataFrame([(["a" * 100] * 3, [(1, 2)])], "x array<string>, y array<struct<a:long,b:long>>"))


def test_statistics_name_all_collections(spark):
    for q in ("ds_collection", "ds_common_tokens_median"):
        assert {r.name for r in registry.queries()[q](spark, SF).collect()} == set(views.COLLECTIONS)
    d, t = views.load(spark, SF, "d2", "clean")
    assert measures.characteristics(d, t).where("collection = 'R'").first().duplicates > 0
    assert uri_infix.applicable(d).first().applicable
    few = {u: attr_clustering.find_clusters(d, min_similarity=0.5, unmatched=u) for u in ("drop", "glue")}
    assert few["glue"].count() > few["drop"].count() and few["glue"].where("cluster_id = 'rest'").count() > 0
