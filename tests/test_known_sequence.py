"""The sequential method by known matches beside the one that compares pair by pair."""

import random
import time

import numpy as np

from erblock.operators import iterative


def test_comparisons_and_classes_are_those_of_comparing_one_by_one():
    r = random.Random(5)
    for trial in range(250):
        n = r.choice([2, 5, 12, 40, 150])
        blocks = [sorted(r.sample(range(n), r.randint(2, n))) for _ in range(r.randint(1, 12))]
        links: dict[int, set[int]] = {}
        for _ in range(r.randint(0, n // 2)):
            a, b = r.randrange(n), r.randrange(n)
            links.setdefault(a, set()).add(b)
            links.setdefault(b, set()).add(a)
        name = lambda i: f"{i:03}"
        inside = sorted({i for x in blocks for i in x})
        at = {e: i for i, e in enumerate(inside)}
        passes = r.choice([1, 2, None])
        listed = [(f"k{j:02}", [name(i) for i in x]) for j, x in enumerate(blocks)]
        same = lambda ta, tb, ma, mb: any(name(y) in mb for e in ma for y in links.get(int(e), ()))  # noqa: E731, B023
        rep, compared, took = iterative.resolve(listed, {}, same, passes)
        numbered = {at[x]: {at[z] for z in y if z in at} for x, y in links.items() if x in at}
        got = iterative.resolve_known([np.array([at[i] for i in x]) for x in blocks], len(inside), numbered, passes)
        assert [name(inside[i]) for i in got[0]] == [rep[name(e)] for e in inside] and got[1:] == (compared, took), trial


def test_pairs_are_not_compared_one_by_one():
    n = 3_000
    began = time.process_time()
    rep, compared, passes = iterative.resolve_known([np.arange(n)] * 3, n, {7: {2_000}, 2_000: {7}}, 1)
    assert rep[2_000] == 7 and (rep == np.arange(n)).sum() == n - 1 and passes == 1
    # Seven rows and a part of the eighth, the union with the seven, and the others.
    assert compared == 7 * 2_999 - 21 + 1_993 + 7 + 2_992 * 2_991 // 2 and time.process_time() - began < 2
