"""One row of each near-duplicate class, with repeated rows, shared ids and null ids, against brute force."""

import random
import re

import corpus_pipeline

WORD = re.compile(r"[^\x20\x09-\x0D]+")


def test_one_row_of_each_class(spark):
    r = random.Random(5)
    base = [" ".join(f"w{r.randint(0, 400)}" for _ in range(60)) for _ in range(8)]
    rows = [(i, t) for i, t in enumerate(base)]
    rows += [(0, base[0]), (0, base[0]), (0, base[0] + " more"), (20, base[1] + " more")]
    rows += [(None, base[2]), (None, "no id " + base[3][:90]), (None, "no id " + base[3][:90]), (None, "no id " + base[4][:90]), (None, "no id " + base[4][:90] + " x")]
    rows += [(30, None), (31, " "), (31, " ")]
    docs = spark.createDataFrame([(d, t, "en", "a", len(t or "")) for d, t in rows], "doc_id long, text string, lang string, source string, n_chars long")
    sets = []
    for _, t in rows:
        w = WORD.findall(t or "")
        sets.append({tuple(w[i : i + 5]) for i in range(max(1, len(w) - 4))} if w else set())
    label = list(range(len(rows)))
    for i in range(len(rows)):
        for j in range(i):
            if sets[i] and 10 * len(sets[i] & sets[j]) >= 8 * len(sets[i] | sets[j]):
                label = [label[j] if x == label[i] else x for x in label]
    kept = [(x.doc_id, x.text) for x in corpus_pipeline.near_duplicates(spark, docs, "").collect()]
    assert sorted(label[rows.index(x)] for x in kept if x[1] and x[1].strip()) == sorted({x for x, s in zip(label, sets, strict=True) if s})
    assert sum(not (t or "").strip() for _, t in kept) == 3
    assert sorted(d for d, t in kept if d is not None) == [0, 1, 2, 3, 4, 5, 6, 7, 30, 31, 31]
