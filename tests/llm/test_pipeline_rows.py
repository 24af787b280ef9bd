"""Stages of the pipeline against brute force: null and repeated ids, null texts, odd characters, clashing columns."""

import hashlib
import random
import re
from collections import Counter

import numpy as np
import pytest

import corpus_pipeline
from erblock.llm import mixing, quality_rules, suffix_dedup

SCHEMA = "doc_id long, text string, lang string, source string, n_chars long, row string, k long, spans int, n_words int, fail_bits string, kept_text string, h long, copies int, _t string, x double, n_bytes long, total long"
WORD = re.compile(r"[^\x20\x09-\x0D]+")
CLASH = ("r", 1, 2, 3, "f", "kt", 4, 5, "t", 0.5, 6, 7)


def _docs(spark, rows):
    return spark.createDataFrame([(i, t, "en", s, None if t is None else len(t), *CLASH) for i, t, s in rows], SCHEMA)


def _words(r, n, letters="abcdéßg日"):
    return " ".join("".join(r.choice(letters) for _ in range(r.randint(1, 7))) for _ in range(n))


def _marks(texts, length=200):
    seen = Counter(b[i : i + length] for b in texts for i in range(len(b) - length + 1))
    out = []
    for b in texts:
        m = np.zeros(len(b), bool)
        for i in range(len(b) - length + 1):
            if seen[b[i : i + length]] > 1:
                m[i : i + length] = True
        out.append(m)
    return out


def _corpus(r):
    shared = [_words(r, 45), _words(r, 50, "日本語é"), "�" * 90]
    texts = [None, "", "a real � stays", _words(r, 80)]
    for i in range(40):
        texts.append(f"{_words(r, r.randint(5, 30))}{shared[i % 3][r.randint(0, 9) :]}{_words(r, r.randint(0, 9))}")
    return [(i % 37 if i % 9 else None, t, "ab"[i % 2] if i % 5 else None) for i, t in enumerate(texts)] + [(7, texts[7], "a"), (7, texts[7], "a"), (7, texts[8], "b")]


def test_repeats_stage_keeps_characters_nulls_and_columns(spark):
    rows = _corpus(random.Random(1))
    docs = _docs(spark, rows)
    out = corpus_pipeline.repeats(spark, docs, "")
    assert out.columns == docs.columns
    want = Counter()
    for (i, t, s), m in zip(rows, _marks([(t or "").encode() for _, t, _ in rows]), strict=True):
        if not m.any():
            want[i, t, None if t is None else len(t), s] += 1
            continue
        kept, at = [], 0
        for c in t:
            n = len(c.encode())
            if not m[at : at + n].any():
                kept.append(c)
            at += n
        if kept:
            want[i, "".join(kept), len(kept), s] += 1
    got = out.collect()
    assert Counter((x.doc_id, x.text, x.n_chars, x.source) for x in got) == want
    assert {tuple(x)[5:] for x in got} == {CLASH}
    assert any("�" in (x.text or "") for x in got)


@pytest.mark.parametrize(("hot_times", "group_bytes"), [(2000, 1 << 26), (3, 1 << 26), (2000, 3000), (3, 2000)])
def test_hot_keys_and_large_groups_change_nothing(spark, hot_times, group_bytes):
    r = random.Random(4)
    line = _words(r, 60)
    texts = [f"{_words(r, r.randint(0, 20))} {line[: r.randint(150, 330)]} {_words(r, r.randint(0, 20))}" for _ in range(60)] + ["ab" * 300, "ab" * 200, "a" * 900, "q" + "a" * 250]
    got = suffix_dedup.remove_repeats(_docs(spark, [(i, t, "a") for i, t in enumerate(texts)]), hot_times=hot_times, group_bytes=group_bytes).collect()
    data = [t.encode() for t in texts]
    want = []
    for i, (b, m) in enumerate(zip(data, _marks(data), strict=True)):
        runs = int((np.diff(np.concatenate([[False], m]).astype(int)) == 1).sum())
        want.append((i, len(b), int(m.sum()), runs, hashlib.sha256(bytes(np.frombuffer(b, np.uint8)[~m])).hexdigest()))
    assert sorted(map(tuple, got)) == want


def test_external_induction_equals_the_one_in_memory():
    r = random.Random(6)
    contexts = {}
    for _ in range(500):
        o = r.randint(0, 20)
        contexts[o, bytes(r.choice(b"ab") for _ in range(r.randint(25, 25 + o)))] = r.choice((1, 1, 1, 2))
    items = [(0, o, x, t) for (o, x), t in sorted(contexts.items())]
    plain = suffix_dedup.repeated_windows(items, 25)
    for memory in (1 << 26, 70_000, 3000):
        group = suffix_dedup.LargeGroup(25, 4000, memory)
        for i, (_, o, x, t) in enumerate(items):
            group.add(o, i, x, t)
        assert [(i, runs) for _, i, runs in group.solve()] == [(i, runs) for i, runs in enumerate(plain) if runs]


def test_mix_stage_judges_each_row_by_its_source(spark):
    rows = _corpus(random.Random(2))
    docs = _docs(spark, rows)
    out = corpus_pipeline.mix(spark, docs, "")
    assert out.columns == docs.columns
    got = Counter((x.doc_id, x.text, x.source) for x in out.collect())
    sizes = {}
    for _, t, s in rows:
        sizes[s] = sizes.get(s, 0) + len(WORD.findall(t or ""))
    names = sorted((s for s in sizes if s is not None)) + [None] * (None in sizes)
    weight = dict(zip(names, (3, 1, 2) * len(names), strict=False))
    left, target, free = 1.5 * sum(sizes.values()), {}, set(names)
    while free:
        share = left / sum(weight[s] for s in free)
        full = {s for s in free if weight[s] * share >= 2 * sizes[s]}
        if not full:
            target |= {s: weight[s] * share for s in free}
            break
        target |= {s: 2 * sizes[s] for s in full}
        left, free = left - sum(2 * sizes[s] for s in full), free - full
    want = Counter()
    for s in names:
        mine = [(int(hashlib.md5(("null" if i is None else str(i)).encode()).hexdigest()[:12], 16), i, t) for i, t, x in rows if x == s]
        copies = int(target[s] // sizes[s]) if sizes[s] else 0
        rest, under = target[s] - copies * sizes[s], 0
        more = {}
        for h in sorted({h for h, _, _ in mine}):
            here = sum(len(WORD.findall(t or "")) for g, _, t in mine if g == h)
            more[h] = under + here <= rest or (under <= rest and under + here - rest < rest - under)
            under += here
        for h, i, t in mine:
            want[i, t, s] += copies + more[h]
    assert got == +want
    assert {tuple(x)[5:] for x in out.collect()} == {CLASH}
    assert mixing.repeated(docs.limit(0)).count() == 0


def test_quality_stage_and_ledger_with_clashing_columns(spark):
    rows = _corpus(random.Random(3))
    docs = _docs(spark, rows)
    kept = corpus_pipeline.quality(spark, docs, "")
    assert kept.columns == docs.columns
    led = quality_rules.ledger(docs)
    assert led.columns.count("n_words") == led.columns.count("fail_bits") == 1
    assert Counter((x.doc_id, x.text) for x in kept.collect()) == Counter((x.doc_id, x.text) for x in led.where("fail_bits = 0").collect())
    assert Counter(x.n_words for x in led.collect()) == Counter(len(WORD.findall(t or "")) for _, t, _ in rows)


def test_near_duplicates_stage_with_clashing_columns(spark):
    rows = _corpus(random.Random(5))
    docs = _docs(spark, rows)
    kept = corpus_pipeline.near_duplicates(spark, docs, "")
    assert kept.columns == docs.columns
    assert {tuple(x)[5:] for x in kept.collect()} == {CLASH}


def test_run_of_all_stages(spark, tmp_path):
    r = random.Random(8)
    rows = [(i, _words(r, 60), "ab"[i % 2]) for i in range(30)] + [(3, None, "a"), (None, _words(r, 50), None)]
    _docs(spark, rows).write.parquet(str(tmp_path / "documents.parquet"))
    out = corpus_pipeline.run(spark, str(tmp_path)).collect()
    assert {x.doc_id for x in out} <= {i for i, _, _ in rows} and len(out) > 20
    empty = _docs(spark, rows).limit(0)
    for _, stage in corpus_pipeline.STAGES:
        assert stage(spark, empty, "").count() == 0


def test_repeats_without_broadcasts(spark, monkeypatch):
    rows = _corpus(random.Random(9))
    docs = _docs(spark, rows)
    want = Counter(map(tuple, suffix_dedup.remove_repeats(docs).collect()))
    texts = Counter((x.doc_id, x.text) for x in corpus_pipeline.repeats(spark, docs, "").collect())
    monkeypatch.setattr(suffix_dedup, "fits", lambda df: False)
    assert Counter(map(tuple, suffix_dedup.remove_repeats(docs).collect())) == want
    assert Counter((x.doc_id, x.text) for x in corpus_pipeline.repeats(spark, docs, "").collect()) == texts
