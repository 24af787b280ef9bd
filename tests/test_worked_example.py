"""The seven descriptions of the worked example, and an eighth; expected values computed by hand."""

import pytest
from pyspark.sql import functions as F

from erblock import registry
from erblock.operators import attr_clustering, blocks, iterative, measures, pairs, token_blocking, uri_infix
from erblock.plans import workloads
from erblock.sources import ingest, views

#: The example's descriptions.
EXAMPLE = {
    "e1": [("about", "Eiffel Tower"), ("architect", "Sauvestre"), ("year", "1889"), ("located", "Paris")],
    "e2": [("about", "Statue of Liberty"), ("architect", "Bartholdi Eiffel"), ("year", "1886"), ("located", "NY")],
    "e3": [("about", "Auguste Bartholdi"), ("born", "1834"), ("work", "Paris")],
    "e4": [("about", "Joan Tower"), ("born", "1938")],
    "e5": [("work", "Lady Liberty"), ("artist", "Bartholdi"), ("location", "NY")],
    "e6": [("work", "Eiffel Tower"), ("year-constructed", "1889"), ("location", "Paris")],
    "e7": [("work", "Bartholdi Fountain"), ("year-constructed", "1876"), ("location", "Washington")],
    "e8": [("work", "Statue of Lib."), ("architect", "Eiffel"), ("year-constructed", "1886")],
}
SCHEMA = "collection string, entity_id string, attribute string, value string, kind string"


def example(spark, ids):
    return spark.createDataFrame([("L" if e < "e5" else "R", e, a, v, "literal") for e in ids for a, v in EXAMPLE[e]], SCHEMA)


@pytest.fixture(scope="module")
def seven(spark):
    return example(spark, [f"e{i}" for i in range(1, 8)]).cache()


@pytest.fixture(scope="module")
def truth(spark):
    return spark.createDataFrame([("e1", "e6", "equivalence"), ("e2", "e5", "equivalence")], "left_id string, right_id string, link_type string")


def test_token_blocking_dirty(seven, truth):
    q = measures.quality(token_blocking.build(seven), seven, truth, "dirty").first()
    assert (q.blocks, q.comparisons, q.distinct_pairs, q.exhaustive) == (7, "18", 13, "21")
    assert (q.recall, q.precision, q.rr, q.h3r) == (1, round(2 / 13, 10), round(1 / 7, 10), 0.25)


def test_token_blocking_clean(seven, truth):
    q = measures.quality(token_blocking.build(seven), seven, truth, "clean", "min_key").first()
    assert (q.comparisons, q.distinct_pairs, q.exhaustive, q.recall, q.precision, q.h3r) == ("13", 8, "12", 1, 0.25, None)
    assert q.rr == round(-1 / 12, 10)


@pytest.mark.parametrize(("floor", "pairs_", "raw"), [(0.0, "16 25 36 37 46", 10), (0.3, "16 25 37 46", 9)])
def test_attribute_clustering(seven, floor, pairs_, raw):
    p = attr_clustering.build(seven, min_similarity=floor)
    got = {(r.left_id, r.right_id) for r in pairs.distinct(p, "clean").collect()}
    assert got == {(f"e{x[0]}", f"e{x[1]}") for x in pairs_.split()}
    assert blocks.summary(p, "clean").agg(F.sum("comparisons")).first()[0] == raw


def test_pair_methods_agree(seven):
    p = token_blocking.build(seven)
    for task in ("dirty", "clean"):
        exact = {tuple(r) for r in pairs.distinct(p, task).collect()}
        assert exact == {tuple(r) for r in pairs.distinct(p, task, "min_key").collect()}
        assert exact == {tuple(r) for r in pairs.tiled(p, task, 2).distinct().collect()}
        assert exact <= {tuple(r) for r in pairs.all_pairs(seven, task).collect()}


def tokens(d):
    return token_blocking.description_tokens(d).select("entity_id", "token").distinct()


def partition(rows):
    out = {}
    for r in rows:
        out.setdefault(r.rep_id, set()).add(r.entity_id)
    return sorted("".join(sorted(x)) for x in out.values() if len(x) > 1)


def test_iterative_finds_what_no_block_holds(spark):
    eight = example(spark, EXAMPLE)
    p = token_blocking.build(eight)
    run = iterative.run_rounds(p, iterative.jaccard(tokens(eight), 0.3))
    assert run.converged and partition(run.entity_map.collect()) == ["e1e6", "e2e5e8"]
    gained = {tuple(r) for r in iterative.gained(run, pairs.distinct(p, "dirty")).collect()}
    assert gained == {("e5", "e8")}
    rows = iterative.run_sequential(p, tokens(eight), theta=0.3).collect()
    assert partition(rows) == ["e1e6", "e2e5e8"]


def test_uri_parts(spark):
    urls = ["http://liris.test/olivier.aubert/foaf.rdf#me", "http://liris.test/ann.b/foaf.rdf#me", "http://liris.test/carl.d/foaf.rdf#me", "http://liris.test/eve.f/foaf.rdf#me"]
    d = spark.createDataFrame([("L", u, "a", "x", "literal") for u in urls], SCHEMA)
    rows = uri_infix.strip_suffix(uri_infix.strip_prefix(uri_infix.uris(d))).collect()
    assert {(r.infix, r.suffix) for r in rows if "olivier" in r.uri} == {("/olivier.aubert", "/foaf.rdf#me")}


def test_ingest(spark, tmp_path):
    (tmp_path / "a.nt").write_text('<http://x/a> <http://p> "one \\"two\\"" .\n_:b <http://p> <http://x/a> .\nbroken\n# note\n')
    triples, rejected = ingest.read_ntriples(spark, str(tmp_path / "a.nt"))
    assert rejected.count() == 1 and triples.count() == 2
    assert [r.value for r in ingest.descriptions(triples).collect()] == ['one "two"']


def test_empty(spark, truth):
    none = spark.createDataFrame([], SCHEMA)
    q = measures.quality(token_blocking.build(none), none, truth.limit(0), "dirty").first()
    assert (q.blocks, q.comparisons, q.recall, q.precision) == (0, "0", None, None)


def test_large_block_counts():
    """A block of 10**10 members must not overflow."""
    from pyspark.sql import SparkSession

    s = SparkSession.getActiveSession()
    one = s.createDataFrame([(10**10, 0)], "n_left long, n_right long").select(blocks.comparisons("dirty").alias("c")).first().c
    assert int(one) == 10**10 * (10**10 - 1) // 2


def test_count_paths_expand_no_pairs(seven):
    plan = blocks.summary(token_blocking.build(seven), "dirty")._jdf.queryExecution().toString()
    assert "Join" not in plan and "Cartesian" not in plan


SMALL = "/root/testdata/sf0.001"


def test_sequential_blocks_hold_the_text(spark):
    """Every true pair with a common token in any attribute ends in one class."""
    d, t = views.load(spark, SMALL, "d5", "dirty")
    want = {tuple(r) for r in blocks.same_block(token_blocking.build(d), t).collect()}
    rep = {r.entity_id: r.rep_id for r in registry.QUERIES["it_sequential"](spark, SMALL).collect()}
    assert want and all(a in rep and rep[a] == rep.get(b) for a, b in want)


def test_pairs_are_counted_without_the_largest_block(seven):
    for p in (token_blocking.build(seven), token_blocking.build(seven).limit(0)):
        for task in ("dirty", "clean"):
            assert pairs.count(p, task).first()[0] == pairs.distinct(p, task).count()


@pytest.mark.parametrize("method", ["token", "attribute", "uri"])
def test_d3_has_all_measures(spark, method):
    rows = workloads.quality(spark, SMALL, "d3", method).collect()
    assert len(rows) == (1 if method == "attribute" else 2) and all(None not in (r.distinct_pairs, r.fp, r.tn, r.precision) for r in rows)


def test_merged_descriptions_are_compared_anew(spark):
    sets = {"a": range(1, 10), "b": range(1, 13), "c": [*range(1, 9), 10]}
    t = spark.createDataFrame([(e, str(x)) for e, v in sets.items() for x in v], "entity_id string, token string")
    p = t.select(F.col("token").alias("block_key"), F.lit("L").alias("collection"), "entity_id")
    run = iterative.run_rounds(p, iterative.jaccard(t, 0.8))
    # Three pairs, then the union of a and c against b.
    assert partition(run.entity_map.collect()) == ["abc"] and run.compared.count() == 4
    assert partition(iterative.run_sequential(p, t, theta=0.8).collect()) == ["abc"]
    with pytest.raises(RuntimeError):
        iterative.run_rounds(p, iterative.jaccard(t, 0.8), max_rounds=1)
    assert partition(iterative.run_rounds(p, iterative.jaccard(t, 0.8), max_rounds=1, partial=True).entity_map.collect()) == ["ac"]


def test_comparisons_of_methods_are_over_all_collections(spark, monkeypatch):
    def matrix(spark, sf, collections=registry.ALL):
        cells = [(m, c, views.COLLECTIONS[c].role, "clean", 1, "2", 1, 0, 1.0, 0.5, 0.5, 0.6) for c in collections for m in ("token", "attribute")]
        return spark.createDataFrame(cells, "method string, collection string, role string, task string, blocks long, comparisons string, tp long, fn long, recall double, precision double, rr double, h3r double")

    monkeypatch.setattr(workloads, "matrix", matrix)
    assert {r.collection for r in registry.QUERIES["cmp_delta"](spark, "").collect()} == set(views.COLLECTIONS)
    cube = registry.QUERIES["cmp_cube"](spark, "").collect()
    assert {(r.role, r.collection) for r in cube if r.collection and r.method} == {(c.role, n) for n, c in views.COLLECTIONS.items()}
    for name in ("cmp_delta", "cmp_cube"):
        assert all(f"'{c}' AS collection" in registry.ORACLE[name] for c in views.COLLECTIONS)
