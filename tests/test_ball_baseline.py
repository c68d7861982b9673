"""The ball baseline solves its many small pieces together."""

from coverdp import patterns as P
from coverdp.model import target_graph
from coverdp.operators import baselines, search


def test_balls_are_solved_in_batches(spark, monkeypatch):
    asked = []
    solve = baselines.solve_pieces
    monkeypatch.setattr(baselines, "solve_pieces", lambda *a, **o: asked.append(o.get("engine", "batch")) or solve(*a, **o))
    w = 7
    edges = [(k, k + 1) for k in range(w * w) if k % w < w - 1] + [(k, k + w) for k in range(w * (w - 1))] + [(0, w + 1)]
    g = target_graph(None, spark.createDataFrame(edges, "src long, dst long"))
    for p in (P.cycle(4), P.TRIANGLE):
        want = sorted(tuple(r["mapping"]) for r in search.join_enumerate(g, p).collect())
        assert want and sorted(tuple(r["mapping"]) for r in baselines.ball_list(g, p).collect()) == want
    assert asked == ["batch", "batch"]
