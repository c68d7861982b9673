"""Searches from a removed set's neighbours say the same as a search of the whole graph, and look at few of its vertices."""

import random

from coverdp.operators.connectivity import Separation, separates
from coverdp.operators.treedec import adjacency


def test_same_as_a_whole_search():
    r = random.Random(4)
    seen = set()
    for _ in range(3000):
        n = r.randint(2, 14)
        edges = [(a, b) for a in range(n) for b in range(a + 1, n) if r.random() < r.choice([0.1, 0.2, 0.4])]
        if not edges:
            continue
        adj = adjacency(*zip(*edges))
        marked = {v for v in range(n) if r.random() < r.choice([0.3, 1])}
        removed = set(r.sample(range(n), r.randint(0, min(n, 4))))
        want = separates(adj, removed, marked & set(adj))
        assert Separation(adj, marked).test(removed) == want
        seen.add(want)
    assert seen == {True, False}


def test_a_large_graph_is_not_walked_for_each_set():
    class Counted(dict):
        looks = 0

        def __getitem__(self, v):
            Counted.looks += 1
            return dict.__getitem__(self, v)

    w = 60
    edges = [(k, k + 1) for k in range(w * w) if k % w < w - 1] + [(k, k + w) for k in range(w * (w - 1))]
    adj = Counted(adjacency(*zip(*edges)))
    parted = Separation(adj, set(adj))
    Counted.looks = 0
    for k in range(100):
        at = 5 * w + 5 + k % 50 + k // 50 * w
        assert not parted.test({at, at + 1, at + w, at + w + 1})
    assert Counted.looks < 100 * w * w / 10
    assert parted.test({1, w})  # a corner
