"""Groups of contexts that are larger than the bound of what a task holds."""

import random

import xxhash

from erblock.llm import suffix_dedup


def test_a_large_group_is_not_held(monkeypatch):
    r = random.Random(2)
    rows = []
    for h, n in ((1, 30), (2, 900), (3, 40)):
        for _ in range(n):
            o = r.randint(0, 12)
            x = bytes(r.choice(b"ab") for _ in range(r.randint(12, 12 + o)))
            rows += [(h, 0, o, xxhash.xxh64(x).intdigest() - (1 << 63), x, 1)] * (1 + (r.random() < 0.1))
    rows.sort()
    want = sorted(suffix_dedup.shard_runs(iter(rows), 12))
    merged = sorted({x[:5] for x in rows})
    plain = suffix_dedup.repeated_windows([((h, c), o, x, sum(y[:5] == (h, c, o, i, x) for y in rows)) for h, c, o, i, x in merged], 12)
    assert want == sorted((*x[:4], runs) for x, runs in zip(merged, plain, strict=True) if runs)
    held, inner = [], suffix_dedup.repeated_windows
    monkeypatch.setattr(suffix_dedup, "repeated_windows", lambda items, *a: held.append(len(items)) or inner(items, *a))
    assert sorted(suffix_dedup.shard_runs(iter(rows), 12, group_bytes=20_000, run_bytes=50_000, memory_bytes=1000)) == want
    assert sum(held) < 100
