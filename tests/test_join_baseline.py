"""The join baseline for 4-cycles: wedges over the same ends, in one turn and in several, on ids that lie either way."""

import itertools
import random

import pytest

from coverdp import patterns as P
from coverdp.model import target_graph
from coverdp.operators import search


@pytest.mark.parametrize("most", [search.TURN_WEDGES, 40])
@pytest.mark.parametrize("hubs", ["low", "high"])
def test_squares(spark, monkeypatch, most, hubs):
    rnd = random.Random(3)
    edges = {tuple(rnd.sample(range(14), 2)) for _ in range(36)} | {((0 if hubs == "low" else 99), v) for v in range(1, 12)}
    edges = {(min(e), max(e)) for e in edges}
    near = {frozenset(e) for e in edges}
    want = set()
    for four in itertools.combinations(sorted({v for e in edges for v in e}), 4):
        for b, c, d in itertools.permutations(four[1:]):
            if b < d and all(frozenset(x) in near for x in ((four[0], b), (b, c), (c, d), (d, four[0]))):
                want.add((four[0], b, c, d))
    monkeypatch.setattr(search, "TURN_WEDGES", most)
    g = target_graph(None, spark.createDataFrame(sorted(edges), "src long, dst long"))
    got = [tuple(r["mapping"]) for r in search.join_enumerate(g, P.cycle(4)).collect()]
    assert len(got) == len(want) and set(got) == want


def test_squares_make_no_long_paths(spark, monkeypatch):
    """A star of 3,000 leaves and one square: paths through its hub would be millions, wedges below the hub are few."""
    star = [(5000, v) for v in range(3000)] + [(0, 4000), (1, 4000)]
    g = target_graph(None, spark.createDataFrame(star, "src long, dst long"))
    sizes = []

    def counted(df, f=search.materialise):
        out = f(df)
        sizes.append(out.count())
        return out

    monkeypatch.setattr(search, "materialise", counted)
    assert [r["mapping"] for r in search.join_enumerate(g, P.cycle(4)).collect()] == [[0, 4000, 1, 5000]]
    assert max(sizes) <= len(star)
