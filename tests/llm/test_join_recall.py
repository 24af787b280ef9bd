"""Recall of the join at its threshold, and texts that only share a passage."""

import random

import numpy as np

from erblock.llm import ngram_join


def _words(r, n):
    return [f"w{r.randint(0, 10**6)}" for _ in range(n)]


def test_pairs_just_above_the_threshold_are_found(spark):
    r = random.Random(3)
    rows, linked = [], 0
    for i in range(300):
        base = _words(r, 104)  # 100 shingles
        changed = 11 if i % 2 else 12  # 89 of 111 shingles in common, or 88 of 112
        rows += [(2 * i, " ".join(base)), (2 * i + 1, " ".join(base[:-changed] + _words(r, changed)))]
        linked += changed == 11
    got = ngram_join.near_duplicates(spark.createDataFrame(rows, "doc_id long, text string")).collect()
    found = {x.doc_id for x in got if x.n_links == 1}
    assert len(found) == 2 * linked and {d // 2 % 2 for d in found} == {1}
    assert all(x.class_id == x.doc_id // 2 * 2 for x in got if x.doc_id in found)


def test_a_common_passage_makes_no_component(spark):
    """Texts that share half their shingles meet in some bands and are dropped there by the posterior."""
    r = random.Random(4)
    passage = _words(r, 60)
    rows = [(i, " ".join(passage + _words(r, 60))) for i in range(400)]
    got = ngram_join.near_duplicates(spark.createDataFrame(rows, "doc_id long, text string")).collect()
    assert all(x.n_links == 0 and x.class_id == x.doc_id for x in got)
    sigs = np.stack([ngram_join.signature(ngram_join.shingle_hashes(t.encode())).astype(np.uint16) for _, t in rows])
    src, _ = ngram_join.bucket_links(np.arange(400), sigs, ngram_join.needed(0.8))
    assert len(src) < 40
    twice = np.concatenate([sigs[:2], sigs[:2]])
    assert list(zip(*ngram_join.bucket_links(np.arange(4), twice, ngram_join.needed(0.8)), strict=True)) == [(2, 0), (3, 1)]


def test_large_buckets_are_linked_whole(spark, monkeypatch):
    r = random.Random(5)
    base = _words(r, 104)
    rows = [(i, " ".join(base[:-1] + _words(r, 1))) for i in range(60)]
    df = spark.createDataFrame(rows, "doc_id long, text string")
    small = sorted((x.doc_id, x.class_id, x.n_links) for x in ngram_join.near_duplicates(df).collect())
    monkeypatch.setattr(ngram_join, "BUCKET", 5)  # read on the driver
    assert sorted((x.doc_id, x.class_id, x.n_links) for x in ngram_join.near_duplicates(df).collect()) == small
    assert small == [(i, 0, 59) for i in range(60)]
