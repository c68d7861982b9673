"""What the kernel drops is on no occurrence."""

import random

import pytest

from coverdp import patterns as P
from coverdp.model import target_graph
from coverdp.operators import kernel as K
from coverdp.operators import search


def graph(spark, edges):
    return target_graph(None, spark.createDataFrame(sorted(edges), "src long, dst long"))


def used(edges, p, spark):
    g = graph(spark, edges)
    rows = [r["mapping"] for r in search.join_enumerate(g, p, images=False).collect()]
    return {(min(m[a], m[b]), max(m[a], m[b])) for m in rows for a, b in p.edges}


@pytest.mark.parametrize("p", [P.TRIANGLE, P.DIAMOND, P.BOWTIE, P.clique(4), P.clique(5), P.wheel(4), P.cycle(4)])
@pytest.mark.parametrize("local", [0, K.LOCAL_TRIANGLES])
def test_every_occurrence_stays(spark, monkeypatch, p, local):
    monkeypatch.setattr(K, "LOCAL_TRIANGLES", local)
    r = random.Random(p.k * 100 + len(p.edges))
    edges = {(a, b) for a in range(24) for b in range(a + 1, 24) if r.random() < (0.5 if p.k == 5 else 0.25)}
    left = {tuple(x) for x in K.kernel(graph(spark, edges), p).edges.collect()}
    assert used(edges, p, spark) <= left <= edges


def test_a_forest_needs_no_repetition(spark):
    edges = [(i // 3, i) for i in range(1, 40)]
    got = search.decide(graph(spark, edges), P.TRIANGLE).first()
    assert (got["found"], got["reps"]) == (False, 0)
    assert search.list_occurrences(graph(spark, edges), P.TRIANGLE).count() == 0


def test_a_holed_lattice_peels_away_before_cliques_are_sought(spark):
    r, w = random.Random(3), 30
    edges = [(k, k + 1) for k in range(w * w) if k % w < w - 1] + [(k, k + w) for k in range(w * (w - 1))]
    edges += [(k, k + w + 1) for k in range(w * (w - 1)) if k % w < w - 1 and r.random() < 0.95]
    assert search.decide(graph(spark, edges), P.clique(4)).first()["reps"] == 0


@pytest.mark.parametrize("p", [P.path(3, ("u", "v", "w")), P.path(4, ("u", "v", None, "u")), P.cycle(4), P.Pattern(3, ((0, 1), (0, 2), (1, 2)), ("u", None, "u"))])
def test_labels_leave_every_occurrence(spark, p):
    r = random.Random(9)
    edges = [(a, b) for a in range(40) for b in range(a + 1, 40) if r.random() < 0.06]
    v = spark.createDataFrame([(i, r.choice("uvwx")) for i in range(40)], "id long, label string")
    g = target_graph(v, spark.createDataFrame(edges, "src long, dst long"))
    small = K.kernel(g, p)
    want = sorted(tuple(x["mapping"]) for x in search.join_enumerate(g, p, images=False).collect())
    assert sorted(tuple(x["mapping"]) for x in search.join_enumerate(small, p, images=False).collect()) == want


def test_chains_without_the_asked_neighbours_are_dropped(spark):
    labels = ["view", "click", "purchase", "view", "view", "click", "view", "error"]
    v = spark.createDataFrame(list(enumerate(labels)), "id long, label string")
    g = target_graph(v, spark.createDataFrame([(i, i + 1) for i in range(7)], "src long, dst long"))
    small = K.kernel(g, P.path(3, ("view", "click", "purchase")))
    assert sorted(x["id"] for x in small.vertices.collect()) == [0, 1, 2]
    assert sorted(map(tuple, small.edges.collect())) == [(0, 1), (1, 2)]


def test_only_edges_to_equal_labels_at_one_vertex_stay(spark):
    r = random.Random(7)
    edges = {(a, b) for a in range(40) for b in range(a + 1, 40) if r.random() < 0.08}
    label = {i: r.choice("abcdefghijklmnop") for i in range(39)}  # the last has none
    v = spark.createDataFrame([(i, label.get(i)) for i in range(40)], "id long, label string")
    g = target_graph(v, spark.createDataFrame(sorted(edges), "src long, dst long"))
    near = {i: [x for e in edges if i in e for x in e if x != i] for i in range(40)}
    wedges = {(min(a, c), b, max(a, c)) for b in near for a in near[b] for c in near[b] if a != c and label.get(a) == label.get(c) is not None}
    left = {tuple(x) for x in K.kernel(g, P.WEDGE, (0, 2)).edges.collect()}
    assert left == {(min(x, b), max(x, b)) for a, b, c in wedges for x in (a, c)}
    assert 0 < len(left) < len(edges)
    got = {tuple(x["mapping"]) for x in search.list_occurrences(g, P.WEDGE, alike=(0, 2)).collect()}
    assert wedges <= {(min(a, c), b, max(a, c)) for a, b, c in got}


def test_lines_of_a_repeated_doc_id_are_gathered(spark, tmp_path):
    from coverdp.sources.graphs import document_line_chain

    for name, rows in (("one", [(1, "a\na\nb\n\na"), (2, None), (3, ""), (4, "x\ny")]), ("two", [(1, "a\nb"), (1, "a\nb")])):
        spark.createDataFrame(rows, "doc_id long, text string").write.parquet(str(tmp_path / name / "documents.parquet"))
    g = document_line_chain(spark, str(tmp_path / "one"))
    base = 1 << 20
    assert {tuple(e) for e in g.edges.collect()} == {(base, base + 1), (base + 1, base + 2), (base + 2, base + 3), (4 * base, 4 * base + 1)}
    assert "Exchange" not in g.edges._jdf.queryExecution().executedPlan().toString()
    assert {r["id"] for r in document_line_chain(spark, str(tmp_path / "two")).vertices.collect()} == {base, base + 1}
