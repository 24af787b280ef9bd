"""The corpus operators against brute force, library encoders and hand-made cases."""

import base64
import hashlib
import math
import random
import re
from collections import Counter

import numpy as np
import public_tokenizers as P
import pytest
from pyspark.sql import functions as F

from erblock.llm import byte_bpe, chat_format, lm_scoring, mixing, ngram_join, quality_rules, suffix_dedup, token_counts, topk_search, url_filter

SCHEMA = "doc_id long, text string, lang string, source string, n_chars long"
WORD = re.compile(r"[^\x20\x09-\x0D]+")


def corpus(n=60, seed=3):
    r = random.Random(seed)
    words = ["".join(r.choice("abcdéfg") for _ in range(r.randint(1, 7))) for _ in range(300)]
    shared = " ".join(r.choice(words) for _ in range(60))
    texts = []
    for i in range(n):
        t = " ".join(r.choice(words) for _ in range(r.randint(12, 120)))
        texts.append(t if i % 3 else f"{t}\n{shared} {t[:30]}")
    texts += [texts[0], texts[0], texts[3] + " more", None, "", " \n ", "one", "a" * 900, "ab " * 400, "x" * 5000]
    return texts


@pytest.fixture(scope="module")
def docs(spark):
    rows = [(i, t, "en", [None, "a", "b", "é"][i % 4], len(t or "")) for i, t in enumerate(corpus())]
    rows += [(None, "no id but some words to look at in here", "en", "a", 1), (5, rows[5][1], "en", "a", 1)]
    return spark.createDataFrame(rows, SCHEMA).cache()


def texts_of(docs):
    return [(r.doc_id, r.text or "") for r in docs.collect()]


def test_suffix_dedup_is_exact(docs):
    rows = [t.encode() for _, t in texts_of(docs)]
    seen = Counter(b[i : i + 200] for b in rows for i in range(len(b) - 199))
    want = Counter()
    for (d, t), b in zip(texts_of(docs), rows, strict=True):
        m = np.zeros(len(b), bool)
        for i in range(len(b) - 199):
            if seen[b[i : i + 200]] > 1:
                m[i : i + 200] = True
        runs = int((np.diff(np.concatenate([[False], m]).astype(int)) == 1).sum())
        kept = bytes(np.frombuffer(b, np.uint8)[~m])
        want[d, len(b), int(m.sum()), runs, hashlib.sha256(kept).hexdigest()] += 1
    assert Counter(tuple(r) for r in suffix_dedup.remove_repeats(docs).select("doc_id", "n_bytes", "n_removed", "n_spans", "kept_sha256").collect()) == want


def test_induction_with_small_memory():
    r = random.Random(1)
    contexts = [(r.randint(0, 3), o, bytes(r.choice(b"ab") for _ in range(o + r.randint(40, 60))), r.randint(1, 2) if r.random() < 0.1 else 1) for o in (r.randint(0, 12) for _ in range(300))]
    got = suffix_dedup.repeated_windows(contexts, 12, run_bytes=2000, memory_bytes=1000)
    assert got == suffix_dedup.repeated_windows(contexts, 12)


def test_near_duplicates_are_exact(docs):
    rows = texts_of(docs)
    sets = []
    for _, t in rows:
        w = WORD.findall(t)
        sets.append({tuple(w[i : i + 5]) for i in range(max(1, len(w) - 4))} if w else set())
    linked = [[j for j in range(len(rows)) if j != i and sets[i] and 10 * len(sets[i] & sets[j]) >= 8 * len(sets[i] | sets[j])] for i in range(len(rows))]
    got = Counter((r.doc_id, r.n_links) for r in ngram_join.near_duplicates(docs).collect())
    assert got == Counter((d, len(x)) for (d, _), x in zip(rows, linked, strict=True))


def test_bayes_table_grows():
    need = ngram_join.needed(0.8)
    assert list(need) == [16, 32, 48, 64, 80, 96] and sorted(need.values()) == list(need.values()) and need[96] < 77


def test_keep_one(docs):
    kept = ngram_join.keep_one(docs)
    assert kept.columns == docs.columns
    ids = [r.doc_id for r in kept.collect()]
    assert 0 in ids and 60 not in ids and 61 not in ids


def test_byte_bpe_equals_library(docs):
    ranks = {base64.b64decode(a): int(b) for a, b in map(bytes.split, open(P.path("byte_bpe_50k.tiktoken"), "rb"))}
    import tiktoken

    lib = tiktoken.Encoding("own", pat_str=P.PATTERN, mergeable_ranks=ranks, special_tokens={})
    own = byte_bpe.tokenizer(P.path("byte_bpe_50k.tiktoken"), P.PATTERN)
    r = random.Random(2)
    odd = ["".join(r.choice("ab  \n\t'sé日　\xa0<|>19🙂") for _ in range(r.randint(0, 50))) for _ in range(2000)] + ["a" * 20000, "<|endoftext|>"]
    for t in [t for _, t in texts_of(docs)] + odd:
        ids = own.encode(t)
        assert ids == lib.encode_ordinary(t) and own.decode(ids) == t.encode()
    back = byte_bpe.decode_documents(byte_bpe.encode_documents(docs, P.path("byte_bpe_50k.tiktoken"), P.PATTERN), P.path("byte_bpe_50k.tiktoken"), P.PATTERN)
    assert Counter(r.data.decode() for r in back.collect()) == Counter(t for _, t in texts_of(docs))


def test_token_counts_equal_library(docs):
    import sentencepiece

    lib = sentencepiece.SentencePieceProcessor(model_file=P.path("piece_bpe_32k.model"))
    own = token_counts.counter(P.path("piece_bpe_32k.model"))
    assert 10_000 < len(own.whole) < len(own.rank)
    r = random.Random(4)
    odd = ["".join(r.choice("ab  \n▁s<s>é日🙂1") for _ in range(r.randint(0, 40))) for _ in range(2000)]
    for t in odd:
        assert own.count(t) == len(lib.encode(t))
    got = {(r.doc_id, r.n_bytes, r.n_tokens) for r in token_counts.token_counts(docs, P.path("piece_bpe_32k.model")).collect()}
    assert got == {(d, len(t.encode()), len(lib.encode(t))) for d, t in texts_of(docs)}


def test_quality_rules(docs, spark):
    got = Counter()
    led = quality_rules.ledger(docs)
    for r in led.collect():
        got[r.doc_id, r.n_words, r.word_chars, r.n_repeat_words, r.n_dup_lines] += 1
    want = Counter()
    for d, t in texts_of(docs):
        w = WORD.findall(t)
        wins = Counter(tuple(w[i : i + 5]) for i in range(len(w) - 4))
        hit = {j for i in range(len(w) - 4) if wins[tuple(w[i : i + 5])] > 1 for j in range(i, i + 5)}
        lines = [x for x in t.split("\n") if WORD.search(x)]
        want[d, len(w), sum(map(len, w)), len(hit), len(lines) - len(set(lines))] += 1
    assert got == want
    ab = {r.rule: (r.n_failed, r.n_only) for r in quality_rules.ablations(led).collect()}
    assert ab["few_words"][0] >= ab["few_words"][1] > 0
    assert quality_rules.patterns(led).agg(F.sum("n_docs")).first()[0] == docs.count()


def test_mixing(docs):
    rows = mixing.mix(docs).collect()
    assert sorted(map(tuple, rows), key=str) == sorted(map(tuple, mixing.mix(docs).collect()), key=str)
    by = {}
    for r in rows:
        by.setdefault(r.source, []).append(r)
        assert 0 <= r.n_copies <= 2
    total = sum(r.size for r in rows)
    assert sum(x[0].target for x in by.values()) == pytest.approx(1.5 * total)
    for x in by.values():
        assert abs(sum(r.size * r.n_copies for r in x) - x[0].target) <= max(r.size for r in x)


def test_chat_format(spark):
    rows = [(1, 0, "user", "hi <|end|>\n"), (1, 1, "assistant", "</s>[INST] \\ [\\/INST]"), (2, 0, "user", "hi <|end|>\n"), (2, 1, "assistant", None), (3, 0, None, "<\\|x|>"), (None, 0, "assistant", "é"), (4, 0, "a|>\nb%", "t")]
    convs = spark.createDataFrame([(*r, 1) for r in rows], "conv_id long, turn long, role string, text string, path int")
    want = {}
    for c, _, role, text in rows:
        want.setdefault(c, []).append((role or "", text or ""))
    tree = chat_format.prefix_tree(convs, 1)
    for r in chat_format.read_back(tree).collect():
        assert chat_format.parse(r.formatted) == want[r.conv_id]
        assert r.loss_text == "".join(t for role, t in want[r.conv_id] if role == "assistant")
    assert sum(r.new_text.count("hi ") for r in tree.collect()) == 1  # the shared turn is emitted once
    for r in tree.collect():
        assert [s.position for s in r.spans] == [sum(x.stop - x.start for x in r.spans[:i]) for i in range(len(r.spans))]


def test_top_k(spark):
    r = np.random.default_rng(1)
    x = np.floor(r.normal(size=(700, 12)) * 40).astype(np.int64)
    x[50:300] = x[10]
    rows = [(i, [float(v) / 256 for v in row]) for i, row in enumerate(x)] + [(9001, None), (9002, [None] * 12), (9003, [math.nan] * 12), (9004, [])]
    df = spark.createDataFrame(rows, "vec_id long, embedding array<double>")
    got = sorted(map(tuple, topk_search.top_k(df, F.col("vec_id") % 50 == 0).collect()))
    assert got == sorted(topk_search.brute_force(np.arange(700), x, list(range(0, 700, 50)), 5))


def test_url_filter(spark):
    urls = ["http://a.org/x", "HTTP://B.Example.ORG/es/q", "http://example.org/en/12?x", "http://x.com/fr/1", "http://x.com/de/1", "http://x.net/de/1", None, "nothing", "http://org", "http://notorg/"] * 3
    df = spark.createDataFrame(list(enumerate(urls)), "page_id long, url string")
    got = {r.page_id: r for r in url_filter.judge(df).collect()}
    assert len(got) == len(urls)
    assert [got[i].rule for i in range(10)] == ["org/", "example.org/es/", "example.org/en/1", "com/fr/", "com/de/", None, None, None, None, None]
    assert (got[1].host, got[1].path) == ("b.example.org", "/es/q") and (got[6].host, got[6].path) == ("", "")
    assert all(r.verdict in ("allow", "block") for r in got.values())


def test_lm(docs):
    rows = lm_scoring.score(docs).collect()
    assert len(rows) == docs.count()
    t = [x for x in texts_of(docs)]
    assert Counter(r.n_tokens for r in rows) == Counter(len(WORD.findall(x)) + 1 for _, x in t)
    assert all(math.isfinite(r.score) and math.isfinite(r.base_score) for r in rows)


def test_lm_learns():
    seqs = [np.array([1, 2, 40] * 20 + [lm_scoring.END], dtype=np.int16) for _ in range(200)]
    own = np.bincount(np.concatenate(seqs), minlength=lm_scoring.OWN)[: lm_scoring.OWN].astype(float)
    classes = np.bincount(lm_scoring.CLASS_OF[np.concatenate(seqs)], minlength=lm_scoring.CLASSES).astype(float)
    start = lm_scoring.initial(own, classes)
    t = lm_scoring.Trainer(start)
    for _ in range(25):
        t.sweep(seqs)
    assert lm_scoring.log_likelihood(t.flat, seqs[:1])[0] > 0.7 * lm_scoring.log_likelihood(start, seqs[:1])[0]


def test_empty_tables(spark):
    none = spark.createDataFrame([], SCHEMA)
    assert suffix_dedup.remove_repeats(none).count() == 0
    assert ngram_join.near_duplicates(none).count() == 0
    assert mixing.mix(none).count() == 0
    assert lm_scoring.score(none).count() == 0
    assert byte_bpe.digests(none, P.path("byte_bpe_50k.tiktoken"), P.PATTERN).count() == 0
    assert quality_rules.ledger(none).count() == 0
    assert topk_search.top_k(spark.createDataFrame([], "vec_id long, embedding array<float>"), F.lit(True)).count() == 0
    assert chat_format.digests(spark.createDataFrame([], "conv_id long, turn long, role string, text string")).count() == 0
    assert url_filter.judge(spark.createDataFrame([], "page_id long, url string")).count() == 0


def test_pipeline(docs, spark):
    import corpus_pipeline

    d = docs.where("doc_id is not null").dropDuplicates(["doc_id"])
    for name, stage in corpus_pipeline.STAGES[:-1]:
        out = stage(spark, d, "")
        assert out.columns == docs.columns, name
        d = out.cache()
    last = corpus_pipeline.STAGES[-1][1](spark, d, "")
    assert last.count() == d.count() > 0
