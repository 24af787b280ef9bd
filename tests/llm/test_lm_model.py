"""The language model: base columns against brute force, the network against a plain reading of its formulas."""

import math
import zlib
from collections import Counter

import numpy as np

from erblock.llm import lm_scoring as L


def _plain(flat, slots):
    """Log probability of one sequence, word by word, in double precision."""
    p = {k: v.astype(np.float64) for k, v in L.unpack(flat).items()}
    n, h, total, before = L.HIDDEN, np.zeros(L.HIDDEN), 0.0, L.START
    for s in slots:
        gx, gh = p["x"][before], h @ p["u"]
        z, r = (1 / (1 + np.exp(-(gx[a : a + n] + gh[a : a + n]))) for a in (0, n))
        h = z * h + (1 - z) * np.tanh(gx[2 * n :] + r * gh[2 * n :])
        out = h @ p["w"] + p["b"]
        total += out[L.CLASS_OF[s]] - np.log(np.exp(out).sum())
        if s < L.OWN:
            k = s // L.WIDTH
            inside = h @ p["v"][k] + p["c"][k]
            total += inside[s % L.WIDTH] - np.log(np.exp(inside).sum())
        before = s
    return total


def _weights(seed=3):
    rng = np.random.default_rng(seed)
    return (rng.standard_normal(L.SIZE) * 0.3).astype(np.float32)


def test_log_likelihood_carries_the_state_over_whole_texts():
    rng = np.random.default_rng(0)
    docs = [rng.integers(0, L.END + 1, n).astype(np.int16) for n in (1, 7, 300, 0, 2500, 40)]
    got = L.log_likelihood(_weights(), docs)
    assert np.allclose(got, [_plain(_weights(), d) for d in docs], rtol=1e-4, atol=1e-3)


def test_probabilities_sum_to_one():
    h = np.tile(np.random.default_rng(1).standard_normal(L.HIDDEN).astype(np.float32) * 0.4, (L.END + 1, 1))
    assert abs(np.exp(L.log_outputs(L.unpack(_weights()), h, np.arange(L.END + 1, dtype=np.int16))).sum() - 1) < 1e-4


def test_gradient_of_a_window():
    rng = np.random.default_rng(2)
    trainer = L.Trainer(_weights(4))
    target = rng.integers(0, L.END + 1, (5, 3)).astype(np.int16)
    source = rng.integers(0, L.START + 1, (5, 3)).astype(np.int16)
    fresh, real = np.zeros((5, 3), bool), np.ones((5, 3), bool)
    fresh[2, 1], real[4, 2] = True, False
    h = rng.standard_normal((3, L.HIDDEN)).astype(np.float32) * 0.2

    def loss(flat):
        p, state, total = L.unpack(flat), h.copy(), 0.0
        for t in range(5):
            state[fresh[t]] = 0
            state = L._step(p, L._gates(p["x"], source[t]), state)[0]
            total -= float((L.log_outputs(p, state, target[t]) * real[t]).sum())
        return total / real.sum()

    g, _ = trainer.gradient(target, source, fresh, real, h.copy())
    for name, part in L.unpack(np.arange(L.SIZE)).items():
        used = part.ravel()[np.argsort(-np.abs(g[part.ravel()]))[:6]]
        for i in used:
            up, down = trainer.flat.copy(), trainer.flat.copy()
            up[i] += 0.01
            down[i] -= 0.01
            assert abs((loss(up) - loss(down)) / 0.02 - g[i]) < 2e-3 + 0.02 * abs(g[i]), name


def test_head_is_cut_by_the_histogram(spark):
    counts = spark.createDataFrame([("", 50), *((f"w{i}", 1 + i % 7) for i in range(70))], "word string, c long")
    assert [n for _, n in L.head_words(counts, 25)] == [7] * 10 + [6] * 10
    assert len(L.head_words(counts, 70)) == 70
    assert L.head_words(counts, 9) == []


def test_base_columns_against_brute_force(spark):
    rng = np.random.default_rng(5)
    texts = [" ".join(f"W{int(x) ** 2 % 97}" for x in rng.integers(0, 60, n)) for n in rng.integers(0, 60, 80)]
    rows = [(i, t, "x") for i, t in enumerate(texts)] + [(3, texts[3], "x"), (None, "w1 lone word Ä", "x"), (81, None, "x"), (82, " \n\t", "x"), (83, "rare " * 30_000, "x")]
    got = L.score(spark.createDataFrame(rows, "doc_id long, text string, word string")).collect()
    training = [L.tokens((t or "").encode()) for i, t, _ in rows if zlib.crc32(("null" if i is None else str(i)).encode()) % 5 != 1]
    c = Counter(w for ws in training for w in [*ws, b""])
    n, v = sum(c.values()), len(c)
    want = []
    for i, t, _ in rows:
        ws = [*L.tokens((t or "").encode()), b""]
        base = sum(math.log10((c[w] + 0.5) / (n + 0.5 * (v + 1))) for w in ws)
        want.append((-1 if i is None else i, zlib.crc32(("null" if i is None else str(i)).encode()) % 5 == 1, len(ws), sum(w in c for w in ws), n, round(base, 6)))
    assert sorted((-1 if r["doc_id"] is None else r["doc_id"], r["held_out"], r["n_tokens"], r["n_known"], r["train_tokens"], round(r["base_score"], 6)) for r in got) == sorted(want)
    assert all(math.isfinite(r["score"]) and r["score"] < 0 for r in got)
