"""A large graph is searched by a part first, and wholly where the part holds nothing."""

from pathlib import Path

from coverdp import patterns as P
from coverdp.model import target_graph
from coverdp.operators import blocks, clustering, disconnected, search
from coverdp.runtime import shared_folder
from coverdp.sources.graphs import order_lattice_graph


def _path_with_triangle(spark, at):
    edges = [(i, i + 1) for i in range(399)] + [(at, at + 2)]
    return target_graph(None, spark.createDataFrame(edges, "src long, dst long"))


def test_part_first_then_whole(spark, monkeypatch):
    monkeypatch.setattr(search, "PART_IDS", 40)
    sizes = []
    monkeypatch.setattr(search, "kernel", lambda g, *a, f=search.kernel: sizes.append(g.vertices.count()) or f(g, *a))
    assert sorted(search.find(_path_with_triangle(spark, 5), P.TRIANGLE)[0]) == [5, 6, 7]
    assert len(sizes) == 1 and sizes[0] < 60
    sizes.clear()
    assert sorted(search.find(_path_with_triangle(spark, 300), P.TRIANGLE)[0]) == [300, 301, 302]
    assert sizes[0] < 60 and sizes[1:] == [400]
    assert search.find(target_graph(None, spark.range(399).selectExpr("id AS src", "id + 1 AS dst")), P.TRIANGLE)[0] is None


def test_disconnected_patterns_take_a_part_first_and_few_copies_at_once(spark, tiny, monkeypatch):
    g = order_lattice_graph(spark, tiny)
    n = g.vertices.count()
    sizes, draw = [], disconnected.colourings
    monkeypatch.setattr(disconnected, "colourings", lambda g, c, reps, *x: sizes.append((g.vertices.count(), reps)) or draw(g, c, reps, *x))
    monkeypatch.setattr(disconnected, "PART_IDS", 100)
    monkeypatch.setattr(search, "PART_IDS", 100)
    monkeypatch.setattr(disconnected, "COPY_IDS", 300)
    assert disconnected.decide_disconnected(g, P.TWO_TRIANGLES).first()["found"]
    assert sizes and all(v < n / 2 and reps <= max(1, 300 // v) for v, reps in sizes)


def test_local_clustering_gathers_no_rows_of_python_objects(spark, tiny, monkeypatch):
    g = order_lattice_graph(spark, tiny)
    want = {tuple(r) for r in clustering.exponential_shift_clustering(g, 6.0, 2, engine="distributed").select("rep", "id", "center", "level", "shift").collect()}
    monkeypatch.setattr(type(g.edges), "toPandas", None)
    got = clustering.exponential_shift_clustering(g, 6.0, 2, engine="local").select("rep", "id", "center", "level", "shift").collect()
    assert {tuple(r) for r in got} == want


def test_small_batches_and_turns_list_the_same_and_leave_no_windows(spark, tiny, monkeypatch):
    g = order_lattice_graph(spark, tiny)
    want = {tuple(r["mapping"]) for r in search.join_enumerate(g, P.cycle(4)).collect()}
    monkeypatch.setattr(search, "BATCH_ROWS", 12 * g.vertices.count())
    monkeypatch.setattr(search, "TURN_ROWS", g.vertices.count() // 2)
    monkeypatch.setattr(clustering, "LOCAL_EDGES", 10)
    monkeypatch.setattr(blocks, "BLOCK_IDS", 400)
    solve, tables = search.solve_pieces, []
    monkeypatch.setattr(search, "solve_pieces", lambda pieces, *a, **k: tables.append(pieces) or solve(pieces, *a, **k))
    folder = Path(shared_folder(spark).removeprefix("file:"))
    before = {x.name for x in folder.iterdir()}
    got = [tuple(r["mapping"]) for r in search.list_occurrences(g, P.cycle(4)).collect()]
    assert set(got) == want and len(got) == len(want)
    assert len(tables) > 3  # several batches, the first of several turns
    assert all("start" not in spark.read.parquet(str(x)).columns for x in folder.iterdir() if x.name.startswith("coverdp") and x.name not in before)
