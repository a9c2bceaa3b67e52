"""Greedy string tiling held against trying everything."""

import random
import time

import numpy as np
import pytest

from placeminer.llm import tiling


def greedy(doc, item, least):
    """Tiles by trying every pair of positions: the longest first, then the first in the document, then in the item."""
    d, t, out = [False] * len(doc), [False] * len(item), []
    while True:
        best = (0, 0, 0)
        for a in range(len(doc)):
            for s in range(len(item)):
                n = 0
                while a + n < len(doc) and s + n < len(item) and doc[a + n] == item[s + n] and not d[a + n] and not t[s + n]:
                    n += 1
                best = max(best, (n, -a, -s))
        n, a, s = best[0], -best[1], -best[2]
        if n < least:
            return out
        for k in range(n):
            d[a + k] = t[s + k] = True
        out.append((a, s, n))


def found(doc, items):
    seeds = tiling.Seeds([(k, " ".join(i)) for k, i in enumerate(items)])
    return {f[0]: f[1:] for f in seeds.found(tiling.WordHashes().of(tiling.normal(" ".join(doc))))}


@pytest.mark.parametrize("pairs", [0, 100_000])
@pytest.mark.parametrize("letters", [1, 2, 3, 6])
def test_both_ways_equal_trying_everything(monkeypatch, pairs, letters):
    monkeypatch.setattr(tiling, "PAIRS", pairs)
    rng = random.Random(letters)
    for _ in range(40):
        items = [[str(rng.randrange(letters)) for _ in range(rng.randint(5, 18))] for _ in range(2)]
        doc = [str(rng.randrange(letters + 1)) for _ in range(rng.randint(0, 30))]
        k = rng.randrange(len(items[0]))
        doc[5 : 5 + len(items[0][k:])] = items[0][k:]
        got = found(doc, items)
        for i, item in enumerate(items):
            want = greedy(doc, item, tiling.MIN_TILE)
            assert got.get(i, (0, 0, len(item), 0))[:2] == (len(want), sum(n for _, _, n in want))
            assert got.get(i, (0, 0, 0, 0))[3] == max((n for _, _, n in want), default=0)


def test_a_million_equal_words():
    began = time.time()
    got = found(["same"] * 1_000_000, [["same"] * 200, [*["same"] * 90, "x", *["same"] * 60], ["other"] * 20])
    assert got == {0: (1, 200, 200, 200), 1: (2, 150, 151, 90)} and time.time() - began < 60


def test_a_long_text_that_repeats_a_phrase():
    doc = "one two three four five six".split() * 100_000
    got = found(doc, [doc[:300], [*doc[:8], "seven", *doc[:8]]])
    assert got == {0: (1, 300, 300, 300), 1: (2, 16, 17, 8)}


def test_windows_are_equal_wherever_they_stand():
    h = np.array([1, 2, 3, 4, 5, 9, 1, 2, 3, 4, 5], np.uint64)
    w = tiling.verified_windows(h, 5)
    assert w[0] == w[6] and len(set(w.tolist())) == len(w) - 1
