"""Query keys of the engine and the SQL that gives the same rows on the same tables."""

from __future__ import annotations

import math
from collections.abc import Callable

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from coverdp import measures as ms
from coverdp import patterns as P
from coverdp.model import KIND, TargetGraph
from coverdp.operators import baselines, connectivity, cover, disconnected, dp_dist, dp_local, embedding, paths, search, treedec
from coverdp.operators.clustering import cluster_levels, exponential_shift_clustering
from coverdp.plans import relational
from coverdp.runtime import is_empty, materialise, table
from coverdp.sources import graphs as G
from coverdp.streaming import events as streams

Query = Callable[[SparkSession, str], DataFrame]
QUERIES: dict[str, Query] = {}
ORACLES: dict[str, str] = {}


def query(name: str, sql: str | None = None):
    def put(f: Query) -> Query:
        QUERIES[name] = f
        if sql:
            ORACLES[name] = sql
        return f

    return put


def fixed(g: TargetGraph) -> TargetGraph:
    """A graph that is read again and again, written once."""
    return TargetGraph(materialise(g.vertices), materialise(g.edges))


def one(spark: SparkSession, **values) -> DataFrame:
    """A single row."""
    return spark.range(1).select(*(F.lit(v).alias(k) for k, v in values.items()))


# SQL of the graphs: a common table e(src, dst) with src < dst
E_LATTICE = """o AS (SELECT o_orderkey AS k, o_orderstatus AS s FROM orders), c AS (SELECT count(*) AS n, CAST(floor(sqrt(count(*))) AS BIGINT) AS w FROM o),
e AS (SELECT k AS src, k + 1 AS dst FROM o, c WHERE k % w < w - 1 AND k + 1 < n
 UNION ALL SELECT k, k + w FROM o, c WHERE k + w < n
 UNION ALL SELECT k, k + w + 1 FROM o, c WHERE s = 'F' AND k % w < w - 1 AND k + w + 1 < n
 UNION ALL SELECT k + 1, k + w FROM o, c WHERE s = 'O' AND k % w < w - 1 AND k + w < n)"""
E_FAN = f"""ch AS (SELECT event_id AS a, lead(event_id) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS b FROM events),
e AS (SELECT event_id AS src, {KIND} + user_id AS dst FROM events UNION ALL SELECT least(a, b), greatest(a, b) FROM ch WHERE b IS NOT NULL
 UNION ALL SELECT DISTINCT {KIND} + x.user_id, {KIND} + x.user_id + 1 FROM events x WHERE x.user_id + 1 IN (SELECT user_id FROM events))"""
PTS = "p AS (SELECT vec_id AS id, CAST(embedding[1] AS DOUBLE) AS x, CAST(embedding[2] AS DOUBLE) AS y FROM embeddings)"
E_GABRIEL = PTS + """, e AS (SELECT a.id AS src, b.id AS dst FROM p a JOIN p b ON a.id < b.id WHERE NOT EXISTS
 (SELECT 1 FROM p r WHERE r.id <> a.id AND r.id <> b.id AND (r.x - a.x) * (r.x - b.x) + (r.y - a.y) * (r.y - b.y) < 0))"""
E_RNG = PTS + """, e AS (SELECT a.id AS src, b.id AS dst FROM p a JOIN p b ON a.id < b.id WHERE NOT EXISTS
 (SELECT 1 FROM p r WHERE r.id <> a.id AND r.id <> b.id
  AND (r.x - a.x) * (r.x - a.x) + (r.y - a.y) * (r.y - a.y) < (a.x - b.x) * (a.x - b.x) + (a.y - b.y) * (a.y - b.y)
  AND (r.x - b.x) * (r.x - b.x) + (r.y - b.y) * (r.y - b.y) < (a.x - b.x) * (a.x - b.x) + (a.y - b.y) * (a.y - b.y)))"""
E_HIERARCHY = f"""e AS (SELECT {KIND} + n_regionkey AS src, {2 * KIND} + n_nationkey AS dst FROM nation
 UNION ALL SELECT {2 * KIND} + c_nationkey, {3 * KIND} + c_custkey FROM customer UNION ALL SELECT {3 * KIND} + o_custkey, {4 * KIND} + o_orderkey FROM orders)"""
E_CONVERSATION = f"""t AS (SELECT conv_id * 64 + turn AS id, conv_id, turn, role, {KIND} + conv_id * 8 + CASE role WHEN 'system' THEN 0 WHEN 'user' THEN 1 ELSE 2 END AS hub FROM conversations),
e AS (SELECT a.id AS src, b.id AS dst FROM t a JOIN t b ON a.conv_id = b.conv_id AND b.turn = a.turn + 1 UNION ALL SELECT DISTINCT id, hub FROM t)"""
E_ORDER_PART = f"e AS (SELECT DISTINCT {KIND} + l_orderkey AS src, {2 * KIND} + l_partkey AS dst FROM lineitem)"
E_RING = "z AS (SELECT count(*) AS n FROM nation), e AS (SELECT least(n_nationkey, (n_nationkey + 1) % n) AS src, greatest(n_nationkey, (n_nationkey + 1) % n) AS dst FROM nation, z)"
E_WHEEL = E_RING.replace("e AS (", "rim AS (") + f", e AS (SELECT src, dst FROM rim UNION ALL SELECT n_nationkey, {KIND} FROM nation)"
E_TORUS = """c AS (SELECT CAST(floor(sqrt(count(*))) AS BIGINT) AS w, count(*) // CAST(floor(sqrt(count(*))) AS BIGINT) AS h FROM orders), o AS (SELECT o_orderkey AS k, w, h FROM orders, c WHERE o_orderkey < w * h),
x AS (SELECT k AS a, CASE WHEN k % w = w - 1 THEN k - (w - 1) ELSE k + 1 END AS b FROM o UNION ALL SELECT k, (k + w) % (w * h) FROM o), e AS (SELECT DISTINCT least(a, b) AS src, greatest(a, b) AS dst FROM x WHERE a <> b)"""
GRAPHS = {
    "lattice": (G.order_lattice_graph, E_LATTICE),
    "fan": (G.event_fan_graph, E_FAN),
    "gabriel": (G.embedding_gabriel_graph, E_GABRIEL),
    "rng": (G.embedding_rng_graph, E_RNG),
    "hierarchy": (G.hierarchy_graph, E_HIERARCHY),
    "conversation": (G.conversation_graph, E_CONVERSATION),
    "order_part": (G.order_part_graph, E_ORDER_PART),
    "ring": (G.nation_ring, E_RING),
    "torus": (G.order_torus_graph, E_TORUS),
}
for _name, (_build, _sql) in GRAPHS.items():
    query(f"{_name}_edges", f"WITH {_sql} SELECT src, dst FROM e")(lambda s, d, b=_build: b(s, d).edges)

V = ("a", "b", "c", "d", "f", "g")


def pattern_sql(e: str, p: P.Pattern, keep: str = "", select: str | None = None) -> str:
    """A self-join chain that gives each image once, as a mapping with the least of its rearrangements."""
    order, seen, parts = p.order, [], []
    for v in order:
        near = [q for q in seen if q in p.neighbours[v]]
        if not seen:
            parts.append(f"(SELECT DISTINCT src AS x FROM r) n{v}")
        else:
            parts.append(f"JOIN r e{v} ON e{v}.src = {'n' if near[0] == order[0] else 'e'}{near[0]}.{'x' if near[0] == order[0] else 'dst'}" if near else f"CROSS JOIN (SELECT DISTINCT src AS dst FROM r) e{v}")
        seen.append(v)
    at = {v: f"n{v}.x" if v == order[0] else f"e{v}.dst" for v in order}
    cond = [f"EXISTS (SELECT 1 FROM r z WHERE z.src = {at[a]} AND z.dst = {at[b]})" for a, b in p.edges if not any((a if order.index(a) > order.index(b) else b) == v and [q for q in order[: order.index(v)] if q in p.neighbours[v]][:1] == [b if v == a else a] for v in order[1:])]
    cond += [f"{at[a]} <> {at[b]}" for a in range(p.k) for b in range(a + 1, p.k) if b not in p.neighbours[a]]
    for a in p.automorphisms:
        if a != tuple(range(p.k)):
            cond.append("[" + ", ".join(at[v] for v in range(p.k)) + "] <= [" + ", ".join(at[a[v]] for v in range(p.k)) + "]")
    cols = select or ", ".join(f"{at[v]} AS {V[v]}" for v in range(p.k))
    return f"WITH {e}, r AS (SELECT src, dst FROM e UNION ALL SELECT dst, src FROM e) SELECT {cols} FROM {' '.join(parts)} WHERE {' AND '.join(cond) or 'TRUE'}{keep}"


def columns(mapping: DataFrame, k: int) -> DataFrame:
    return mapping.select(*(F.get("mapping", F.lit(i)).alias(V[i]) for i in range(k)))


def _list(key: str, graph: str, p: P.Pattern) -> None:
    build, e = GRAPHS[graph]
    query(key, pattern_sql(e, p))(lambda s, d: columns(search.list_occurrences(fixed(build(s, d)), p), p.k))


for _key, _graph, _p in (
    ("list_triangles_lattice", "lattice", P.TRIANGLE),
    ("list_triangles_fan", "fan", P.TRIANGLE),
    ("list_c4_gabriel", "gabriel", P.cycle(4)),
    ("list_c5_gabriel", "gabriel", P.cycle(5)),
    ("list_c6_gabriel", "gabriel", P.cycle(6)),
    ("list_diamonds_lattice", "lattice", P.DIAMOND),
    ("list_c4_torus", "torus", P.cycle(4)),
):
    _list(_key, _graph, _p)


def _decide(key: str, graph: str, p: P.Pattern, **options) -> None:
    build, e = GRAPHS[graph]
    query(key, pattern_sql(e, p, select="count(*) > 0 AS found"))(lambda s, d: search.decide(fixed(build(s, d)), p, **options).select("found"))


_decide("decide_triangle_lattice", "lattice", P.TRIANGLE)
_decide("decide_triangle_lattice_safe_window", "lattice", P.TRIANGLE, window="safe")
_decide("decide_clique4_lattice", "lattice", P.clique(4))
_decide("decide_clique4_gabriel", "gabriel", P.clique(4))
_decide("decide_clique5_gabriel", "gabriel", P.clique(5))
_decide("decide_triangle_hierarchy", "hierarchy", P.TRIANGLE)
_decide("decide_c4_conversation", "conversation", P.cycle(4))
_decide("torus_c4", "torus", P.cycle(4), family="bounded_genus")
_decide("decide_bowtie_lattice", "lattice", P.BOWTIE)
_decide("decide_wheel4_gabriel", "gabriel", P.wheel(4))
_decide("decide_triangle_gabriel_layers", "gabriel", P.TRIANGLE, engine="layers")


@query("count_c4_lattice", pattern_sql(E_LATTICE, P.cycle(4), select="count(*) AS images, count(*) * 8 AS mappings"))
def _count_c4(s, d):
    return search.count_occurrences(fixed(G.order_lattice_graph(s, d)), P.cycle(4))


@query("count_by_mode", pattern_sql(E_GABRIEL, P.TRIANGLE, select="count(*) AS images, count(*) * 6 AS mappings, count(*) > 0 AS found"))
def _modes(s, d):
    g = fixed(G.embedding_gabriel_graph(s, d))
    listed = search.list_occurrences(g, P.TRIANGLE, images=False).count()
    return search.count_occurrences(g, P.TRIANGLE).select("images", F.lit(listed).cast("long").alias("mappings"), F.lit(search.find(g, P.TRIANGLE)[0] is not None).alias("found"))


@query("list_triangles_join_baseline", pattern_sql(E_LATTICE, P.TRIANGLE))
def _join_baseline(s, d):
    return columns(search.join_enumerate(G.order_lattice_graph(s, d), P.TRIANGLE), 3)


@query("list_c4_order_part_join_baseline", pattern_sql(E_ORDER_PART, P.cycle(4)))
def _join_general(s, d):
    return columns(search.join_enumerate(G.order_part_graph(s, d), P.cycle(4)), 4)


ROLES = P.path(4, ("user", "assistant", "user", "assistant"))


@query(
    "list_paths_conversation",
    """WITH t AS (SELECT conv_id * 64 + turn AS id, conv_id, turn, role FROM conversations)
    SELECT a.id AS a, b.id AS b, c.id AS c, d.id AS d FROM t a JOIN t b ON a.conv_id = b.conv_id AND abs(a.turn - b.turn) = 1 JOIN t c ON b.conv_id = c.conv_id AND abs(b.turn - c.turn) = 1 AND c.id <> a.id
    JOIN t d ON c.conv_id = d.conv_id AND abs(c.turn - d.turn) = 1 AND d.id <> b.id AND d.id <> a.id WHERE a.role = 'user' AND b.role = 'assistant' AND c.role = 'user' AND d.role = 'assistant'""",
)
def _paths(s, d):
    return columns(search.list_occurrences(fixed(G.conversation_graph(s, d)), ROLES), 4)


FUNNEL_SQL = """WITH c AS (SELECT event_id AS a, event_type AS t, lead(event_id) OVER w AS b, lead(event_type) OVER w AS t2, lead(event_id, 2) OVER w AS c, lead(event_type, 2) OVER w AS t3
    FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id))"""


@query(
    "funnel_paths_events",
    FUNNEL_SQL + """ SELECT a, b, c FROM c WHERE t = 'view' AND t2 = 'click' AND t3 = 'purchase' UNION ALL SELECT c, b, a FROM c WHERE t = 'purchase' AND t2 = 'click' AND t3 = 'view'""",
)
def _funnel(s, d):
    return columns(search.list_occurrences(fixed(G.event_chain_graph(s, d)), P.path(3, ("view", "click", "purchase"))), 3)


@query("list_stars_hierarchy", f"SELECT {2 * KIND} + c_nationkey AS a, {3 * KIND} + c_custkey AS b, {4 * KIND} + o_orderkey AS c FROM customer JOIN orders ON o_custkey = c_custkey")
def _chains(s, d):
    return columns(search.list_occurrences(fixed(G.hierarchy_graph(s, d)), P.path(3, ("nation", "customer", "order"))), 3)


@query("find_one_house_lattice", "SELECT TRUE AS found, CAST(0 AS BIGINT) AS missing_edges")
def _house(s, d):
    g = fixed(G.order_lattice_graph(s, d))
    m, _ = search.find(g, P.HOUSE)
    need = s.createDataFrame([(min(m[a], m[b]), max(m[a], m[b])) for a, b in P.HOUSE.edges] if m else [], "src long, dst long")
    return one(s, found=m is not None, missing_edges=need.join(g.edges, ["src", "dst"], "left_anti").count()).select("found", F.col("missing_edges").cast("long").alias("missing_edges"))


@query("decide_two_triangles_fan", "SELECT TRUE AS found")
def _two_triangles(s, d):
    return disconnected.decide_disconnected(fixed(G.event_fan_graph(s, d)), P.TWO_TRIANGLES).select("found")


@query("decide_three_edges_ring", "SELECT TRUE AS found")
def _three_edges(s, d):
    return disconnected.decide_disconnected(fixed(G.nation_ring(s, d)), P.THREE_EDGES, solver="join").select("found")


@query("list_two_edges_nation", pattern_sql(E_RING, P.TWO_EDGES))
def _two_edges(s, d):
    return columns(disconnected.list_disconnected(fixed(G.nation_ring(s, d)), P.TWO_EDGES, solver="join"), 4)


# covers and clusters
def _flag(key: str, sql: str, metrics: Callable[[SparkSession, str], DataFrame], names: tuple[str, ...]) -> None:
    query(key, sql)(lambda s, d: metrics(s, d).where(F.col("metric").isin(*names)).select("metric", "ok"))


def _true(*names: str) -> str:
    return " UNION ALL ".join(f"SELECT '{x}' AS metric, TRUE AS ok" for x in names)


_lattice_cluster = lambda s, d: ms.cluster_measures(fixed(G.order_lattice_graph(s, d)), P.TRIANGLE)
_crop_cover = lambda s, d: ms.cover_measures(fixed(G.lattice_crop(s, d, 30)), P.TRIANGLE)
_flag("cluster_measures_lattice", _true("crossing_rate", "cluster_radius", "survival_rate"), _lattice_cluster, ("crossing_rate", "cluster_radius", "survival_rate"))
_flag("cover_measures_lattice", _true("window_multiplicity", "cover_size", "window_width", "states_per_node", "triples_total", "decomposition_nodes", "violations"), _crop_cover, ("window_multiplicity", "cover_size", "window_width", "states_per_node", "triples_total", "decomposition_nodes", "violations"))
_flag("listing_quality_fan", _true("recall", "precision", "iterations"), lambda s, d: ms.listing_quality(fixed(G.event_fan_graph(s, d)), P.TRIANGLE), ("recall", "precision", "iterations"))
_flag("listing_quality_gabriel_diamond", _true("recall", "precision", "iterations"), lambda s, d: ms.listing_quality(fixed(G.embedding_gabriel_graph(s, d)), P.DIAMOND), ("recall", "precision", "iterations"))


@query("beta_ablation", "SELECT m AS factor, TRUE AS crossing_ok FROM (VALUES (1), (2), (4)) t(m)")
def _ablation(s, d):
    g = fixed(G.order_lattice_graph(s, d))
    out = None
    for m in (1, 2, 4):
        row = ms.crossing_rate(g, m * 3.0).select(F.lit(m).alias("factor"), F.col("ok").alias("crossing_ok"))
        out = row if out is None else out.union(row)
    return out


@query("cluster_partition", "SELECT r AS rep, count(*) AS n FROM orders, (VALUES (0), (1), (2)) t(r) GROUP BY r")
def _partition(s, d):
    c = exponential_shift_clustering(fixed(G.order_lattice_graph(s, d)), 6.0, 3)
    return c.groupBy("rep").agg(F.count_distinct("id").alias("n"))


_RING_CLUSTER = """WITH v AS (SELECT n_nationkey AS id, CAST(floor(-ln((CAST(('0x' || substr(md5('1|' || r || '|' || n_nationkey), 1, 13)) AS BIGINT) + 0.5) / 4503599627370496.0) * 4000000) AS BIGINT) AS shift, r AS rep FROM nation, (VALUES (0), (1)) t(r)),
z AS (SELECT count(*) AS n FROM nation), o AS (SELECT a.rep, a.id, c.id AS center, least(abs(a.id - c.id), n - abs(a.id - c.id)) AS dist, c.shift FROM v a JOIN v c ON a.rep = c.rep, z)
SELECT rep, id, CAST(arg_min(center, (dist * 1000000 - shift) * 1000 + center) AS BIGINT) AS center, CAST(arg_min(dist, (dist * 1000000 - shift) * 1000 + center) AS INTEGER) AS level FROM o GROUP BY rep, id"""


@query("cluster_assignment_nation", _RING_CLUSTER)
def _assignment(s, d):
    return exponential_shift_clustering(fixed(G.nation_ring(s, d)), 4.0, 2).select("rep", F.col("id").cast("int").alias("id"), "center", "level")


@query("cluster_assignment_distributed", _RING_CLUSTER)
def _assignment_distributed(s, d):
    return exponential_shift_clustering(fixed(G.nation_ring(s, d)), 4.0, 2, engine="distributed").select("rep", F.col("id").cast("int").alias("id"), "center", "level")


@query("cluster_bucketed_partition", "SELECT count(*) AS n, TRUE AS centres_inside FROM nation")
def _bucketed(s, d):
    c = materialise(exponential_shift_clustering(fixed(G.nation_ring(s, d)), 4.0, 1, mode="bucketed"))
    own = c.where("id = center and level = 0").count() == c.select("center").distinct().count()
    return c.agg(F.count_distinct("id").alias("n")).withColumn("centres_inside", F.lit(own))


@query("cluster_levels_min_root", "SELECT TRUE AS ok")
def _levels(s, d):
    g = fixed(G.nation_ring(s, d))
    c = materialise(exponential_shift_clustering(g, 4.0, 2))
    lv = cluster_levels(g, c, "min_id")
    bad = lv.groupBy("rep", "center").agg(F.min("level").alias("lo"), F.min_by("level", "id").alias("root"), F.count("*").alias("n")).where("lo <> 0 or root <> 0")
    return one(s, ok=is_empty(bad) and lv.count() == c.count())


@query("single_bfs_cover_sizes", """WITH RECURSIVE z AS (SELECT count(*) AS n FROM nation), l AS (SELECT n_nationkey AS id, CAST(least(n_nationkey, n - n_nationkey) AS INTEGER) AS level FROM nation, z), t AS (SELECT max(level) AS top FROM l)
SELECT CAST(s.start AS INTEGER) AS start, count(*) AS n FROM l, t, (SELECT unnest(range(0, 100)) AS start) s WHERE s.start <= greatest(0, top - 2) AND level BETWEEN s.start AND s.start + 2 GROUP BY s.start""")
def _single(s, d):
    v, _ = cover.single_bfs_cover(fixed(G.nation_ring(s, d)), 2, 0)
    return v.groupBy("start").agg(F.count("*").alias("n"))


@query("ball_cover_sizes", f"""WITH {E_GABRIEL}, r AS (SELECT src, dst FROM e UNION ALL SELECT dst, src FROM e), b AS (SELECT id AS center, id FROM p UNION SELECT src, dst FROM r UNION SELECT x.src, y.dst FROM r x JOIN r y ON x.dst = y.src)
SELECT center, count(*) AS n FROM b GROUP BY center""")
def _balls(s, d):
    v, _ = cover.ball_cover(fixed(G.embedding_gabriel_graph(s, d)), 2)
    return v.groupBy("center").agg(F.count("*").alias("n"))


@query("sequential_baseline_fan", pattern_sql(E_FAN, P.TRIANGLE))
def _sequential(s, d):
    return columns(baselines.sequential_list(fixed(G.event_fan_graph(s, d)), P.TRIANGLE, KIND), 3)


@query("ball_baseline_c4_gabriel", pattern_sql(E_GABRIEL, P.cycle(4)))
def _balls_solved(s, d):
    return columns(baselines.ball_list(fixed(G.embedding_gabriel_graph(s, d)), P.cycle(4)), 4)


@query("recovered_cells_lattice", pattern_sql(E_LATTICE, P.TRIANGLE, select="count(*) AS images, count(*) * 3 AS cells"))
def _recovered(s, d):
    return ms.recovered_cells(search.list_occurrences(fixed(G.order_lattice_graph(s, d)), P.TRIANGLE))


@query("least_degrees", " UNION ALL ".join(f"SELECT * FROM (WITH {GRAPHS[name][1]}, q AS (SELECT count(*) AS n FROM (SELECT src AS id FROM e UNION ALL SELECT dst FROM e) GROUP BY id) SELECT '{name}' AS graph, min(n) AS least, min(n) <= 5 AS planar_possible FROM q)" for name in ("lattice", "gabriel", "rng", "fan", "torus")))
def _least_degrees(s, d):
    out = None
    for name in ("lattice", "gabriel", "rng", "fan", "torus"):
        row = ms.least_degree(GRAPHS[name][0](s, d)).select(F.lit(name).alias("graph"), "least", "planar_possible")
        out = row if out is None else out.union(row)
    return out


@query("color_coding_triangle_gabriel", "SELECT TRUE AS found")
def _color_coding(s, d):
    return baselines.color_coding_decide(fixed(G.embedding_gabriel_graph(s, d)), P.TRIANGLE).select("found")


# decompositions, layers and paths
def _gabriel_windows(s, d, d_levels=1):
    g = fixed(G.embedding_gabriel_graph(s, d))
    return g, materialise(cover.treewidth_cover(g, P.TRIANGLE, 1, 1, d_levels)[1])


@query("decomposition_violations", "SELECT CAST(0 AS BIGINT) AS plain, CAST(0 AS BIGINT) AS fill, CAST(0 AS BIGINT) AS binary, CAST(0 AS BIGINT) AS balanced")
def _violations(s, d):
    _, e = _gabriel_windows(s, d, 2)
    bags = materialise(treedec.elimination_decomposition(e))
    counts = {"plain": bags, "fill": treedec.elimination_decomposition(e, "fill"), "binary": treedec.binarize(bags), "balanced": treedec.balanced_decomposition(bags)}
    return one(s, **{k: treedec.violations(e, b).count() for k, b in counts.items()}).select(*(F.col(k).cast("long").alias(k) for k in counts))


_HIER_LAYERS = f"""WITH {E_HIERARCHY}, c AS (SELECT c_custkey, c_nationkey, count(o_orderkey) AS n FROM customer LEFT JOIN orders ON o_custkey = c_custkey GROUP BY ALL),
cl AS (SELECT {3 * KIND} + c_custkey AS node, {2 * KIND} + c_nationkey AS up, CASE WHEN n = 0 THEN 0 WHEN n > 1 THEN 1 ELSE 0 END AS layer FROM c),
l0 AS (SELECT {4 * KIND} + o_orderkey AS node, 0 AS layer FROM orders),
n0 AS (SELECT {2 * KIND} + n_nationkey AS node, {KIND} + n_regionkey AS up FROM nation),
nl AS (SELECT n0.node, n0.up, coalesce((SELECT max(layer) + CASE WHEN (SELECT count(*) FROM cl y WHERE y.up = n0.node AND y.layer = max(x.layer)) > 1 THEN 1 ELSE 0 END FROM cl x WHERE x.up = n0.node), 0) AS layer FROM n0),
rl AS (SELECT {KIND} + r_regionkey AS node, coalesce((SELECT max(layer) + CASE WHEN (SELECT count(*) FROM nl y WHERE y.up = {KIND} + r_regionkey AND y.layer = max(x.layer)) > 1 THEN 1 ELSE 0 END FROM nl x WHERE x.up = {KIND} + r_regionkey), 0) AS layer FROM region),
ly AS (SELECT node, layer FROM l0 UNION ALL SELECT node, layer FROM cl UNION ALL SELECT node, layer FROM nl UNION ALL SELECT node, layer FROM rl)"""


def hierarchy_tree(s: SparkSession, d: str) -> DataFrame:
    g = G.hierarchy_graph(s, d)
    return g.vertices.select(F.col("id").alias("node")).join(g.edges.select(F.col("dst").alias("node"), F.col("src").alias("parent")), "node", "left")


@query("layer_numbers_hierarchy", _HIER_LAYERS + " SELECT node, CAST(layer AS INTEGER) AS layer FROM ly")
def _layers(s, d):
    return paths.layer_numbers(hierarchy_tree(s, d), "peel")


@query("layer_numbers_contracted", _HIER_LAYERS + " SELECT node, CAST(layer AS INTEGER) AS layer FROM ly")
def _layers_contracted(s, d):
    return paths.layer_numbers(hierarchy_tree(s, d), "contract")


@query("path_count_by_layer", _HIER_LAYERS + ", up AS (SELECT a.node, a.layer, b.layer AS above FROM ly a LEFT JOIN e ON e.dst = a.node LEFT JOIN ly b ON b.node = e.src) SELECT CAST(layer AS INTEGER) AS layer, count(*) AS n FROM up WHERE above IS NULL OR above <> layer GROUP BY layer")
def _path_counts(s, d):
    return paths.path_decomposition(materialise(hierarchy_tree(s, d))).select("layer", "path").distinct().groupBy("layer").agg(F.count("*").alias("n"))


@query("dom_layer_numbers")
def _dom_layers(s, d):
    g = fixed(G.dom_tree_graph(s, d))
    tree = g.vertices.select(F.col("id").alias("node")).join(g.edges.select(F.col("dst").alias("node"), F.col("src").alias("parent")), "node", "left")
    return paths.layer_numbers(tree, "peel").groupBy("layer").agg(F.count("*").alias("n"))


#: Two unary functions (l, m), 0 <= l <= m < 9, and an argument from each line item.
_FAMILY_SQL = """SELECT DISTINCT CAST(l_suppkey % (l_partkey % 9 + 1) AS INTEGER) AS l2, CAST(l_partkey % 9 AS INTEGER) AS m2, CAST(l_linenumber % (floor(l_quantity)::BIGINT % 9 + 1) AS INTEGER) AS l1, CAST(floor(l_quantity)::BIGINT % 9 AS INTEGER) AS m1, CAST(l_orderkey % 12 AS INTEGER) AS x FROM lineitem"""


@query("layer_family_closed", f"""WITH f AS ({_FAMILY_SQL}), i AS (SELECT *, CASE WHEN x < l1 THEN m1 WHEN x <= m1 THEN m1 + 1 ELSE x END AS y,
 CASE WHEN m2 < m1 THEN l1 WHEN m2 = m1 OR m1 >= l2 THEN 0 WHEN m1 + 1 = l2 THEN l1 ELSE l2 END AS l, greatest(m1, m2) AS m FROM f)
SELECT count(*) AS cases, count(*) FILTER (WHERE CASE WHEN y < l2 THEN m2 WHEN y <= m2 THEN m2 + 1 ELSE y END <> CASE WHEN x < l THEN m WHEN x <= m THEN m + 1 ELSE x END) AS wrong FROM i""")
def _family(s, d):
    m2, m1 = F.col("l_partkey") % 9, F.floor("l_quantity") % 9
    rows = table(s, d, "lineitem").select((F.col("l_suppkey") % (m2 + 1)).alias("l2"), m2.alias("m2"), (F.col("l_linenumber") % (m1 + 1)).alias("l1"), m1.alias("m1"), (F.col("l_orderkey") % 12).alias("x"))
    return paths.family_closed(rows.distinct())


# the program as reachability
def _ring_windows(s, d):
    g = fixed(G.nation_ring(s, d, 1))
    return g, materialise(cover.treewidth_cover(g, P.TRIANGLE, 1, 1)[1])


@query("dag_reach_modes", "SELECT TRUE AS same")
def _reach_modes(s, d):
    _, e = _ring_windows(s, d)
    n = materialise(dp_dist.number_pieces(e))
    dag = materialise(dp_dist.match_dag(n, s.createDataFrame([], "piece_no long, id long"), P.TRIANGLE, 0))
    sets = [materialise(dp_dist.reach(dag, m)) for m in ("none", "all", "forest")]
    return one(s, same=all(baselines.windows_agree(sets[0], x) for x in sets[1:]) and not is_empty(sets[0]))


@query("dag_forest_unique", "SELECT CAST(0 AS BIGINT) AS branching")
def _forest(s, d):
    _, e = _ring_windows(s, d)
    dag = dp_dist.match_dag(materialise(dp_dist.number_pieces(e)), s.createDataFrame([], "piece_no long, id long"), P.TRIANGLE, 0)
    return dp_dist.lift_forest(dag).groupBy("node").count().where("count > 1").agg(F.count("*").alias("branching"))


@query("shortcut_counts", "SELECT * FROM (VALUES ('all', TRUE, TRUE), ('forest', TRUE, TRUE), ('none', TRUE, TRUE)) t(mode, jumps_bounded, rounds_bounded)")
def _shortcut_counts(s, d):
    # paths of the lowest layer of the proximity graph's windows: jumps against the matches, rounds against those without jumps
    n = materialise(dp_dist.number_pieces(_gabriel_windows(s, d)[1]))
    dag = materialise(dp_dist.match_dag(n, s.createDataFrame([], "piece_no long, id long"), P.TRIANGLE, 0))
    size = dag.select(F.explode(F.array("src", "dst")).alias("id")).where("id is not null").distinct().count()
    seen: list[tuple[str, int, int]] = []
    for mode in ("none", "all", "forest"):
        dp_dist.reach(dag, mode, seen)
    most = {"none": 0, "all": size * math.ceil(math.log2(max(2, size))), "forest": 2 * size}
    return s.createDataFrame([(m, jumps <= most[m], rounds <= seen[0][1]) for m, rounds, jumps in seen], "mode string, jumps_bounded boolean, rounds_bounded boolean")


@query("sequential_equals_parallel", "SELECT TRUE AS same")
def _parallel(s, d):
    _, e = _ring_windows(s, d)
    return _same_windows(s, e)


def _same_windows(s: SparkSession, e: DataFrame) -> DataFrame:
    par = materialise(dp_dist.solve_window_parallel(e, P.TRIANGLE).select(*cover.PIECE, "found"))
    seq = dp_local.piece_measures(e, P.TRIANGLE).select(*cover.PIECE, (F.col("found") > 0).alias("found"))
    return one(s, same=baselines.windows_agree(par, seq) and not is_empty(par))


@query("sequential_equals_parallel_gabriel", "SELECT TRUE AS same")
def _parallel_gabriel(s, d):
    # every window of the proximity graph, whether it holds a triangle or not
    return _same_windows(s, _gabriel_windows(s, d)[1])


@query("list_triangles_nation_layers", pattern_sql(E_WHEEL, P.TRIANGLE))
def _list_layers(s, d):
    return columns(search.list_occurrences(fixed(G.nation_ring(s, d, 1)), P.TRIANGLE, engine="layers"), 3)


# embeddings and connectivity
@query("vertex_face_graph_lattice", f"WITH {E_LATTICE} SELECT (SELECT n FROM c) AS n, count(*) AS m, count(*) - (SELECT n FROM c) + 2 AS f FROM e")
def _euler(s, d):
    return embedding.euler(fixed(G.order_lattice_graph(s, d)))


for _key, _build, _k in (
    ("nation_ring", lambda s, d: G.nation_ring(s, d), 2),
    ("nation_wheel", lambda s, d: G.nation_ring(s, d, 1), 3),
    ("nation_bipyramid", lambda s, d: G.nation_ring(s, d, 2), 4),
    ("supplier_antiprism", G.supplier_antiprism_graph, 5),
    ("customer_nation", G.customer_nation_supplier_graph, 0),
):
    query(f"connectivity_{_key}", f"SELECT {_k} AS kappa")(lambda s, d, b=_build: one(s, kappa=connectivity.vertex_connectivity(fixed(b(s, d)))))


@query("connectivity_lattice_crop", "SELECT TRUE AS same")
def _crop_connectivity(s, d):
    g = fixed(G.lattice_crop(s, d, 4))
    want = connectivity.connectivity_bruteforce([tuple(r) for r in g.edges.collect()], [r["id"] for r in g.vertices.collect()])
    return one(s, same=connectivity.vertex_connectivity(g) == want)


@query("minimum_cut_wheel", "SELECT 3 AS size, TRUE AS cuts")
def _witness(s, d):
    g = fixed(G.nation_ring(s, d, 1))
    cut = connectivity.minimum_vertex_cut(g)
    adj = treedec.adjacency(*zip(*[tuple(r) for r in g.edges.collect()], strict=True))
    return one(s, size=len(cut), cuts=connectivity.separates(adj, set(cut), set(adj)))


@query("cut_vertices_fan", f"""WITH u AS (SELECT DISTINCT user_id AS u FROM events) SELECT {KIND} + a.u AS id FROM u a WHERE EXISTS (SELECT 1 FROM u b WHERE b.u IN (a.u - 1, a.u + 1))""")
def _cut_fan_rows(s, d):
    # a user's events hang on the rest by their hub alone
    return connectivity.cut_vertices(fixed(G.event_fan_graph(s, d)))


@query("cut_vertices_ring", "SELECT CAST(0 AS BIGINT) AS n")
def _cut_ring_rows(s, d):
    return connectivity.cut_vertices(fixed(G.nation_ring(s, d))).agg(F.count("*").alias("n"))


@query("connected_predicates", """SELECT * FROM (VALUES ('ring', TRUE, TRUE, FALSE), ('wheel', TRUE, TRUE, TRUE), ('customers', FALSE, FALSE, FALSE)) t(graph, one, two, three)""")
def _predicates(s, d):
    out = None
    for name, build in (("ring", G.nation_ring), ("wheel", lambda s, d: G.nation_ring(s, d, 1)), ("customers", G.customer_nation_supplier_graph)):
        g = fixed(build(s, d))
        first = connectivity.is_connected(g)
        second = first and connectivity.is_biconnected(g)
        row = one(s, graph=name, one=first, two=second, three=second and connectivity.is_triconnected(g))
        out = row if out is None else out.union(row)
    return out


@query("cut_vertices_hierarchy", f"WITH {E_HIERARCHY}, r AS (SELECT src AS id FROM e UNION ALL SELECT dst FROM e) SELECT id FROM r GROUP BY id HAVING count(*) > 1")
def _cut_forest(s, d):
    return connectivity.forest_cut_vertices(G.hierarchy_graph(s, d))


@query("components_conversation", f"WITH {E_CONVERSATION}, m AS (SELECT conv_id, min(id) AS component FROM t GROUP BY conv_id) SELECT t.id, m.component FROM t JOIN m USING (conv_id) UNION SELECT t.hub, m.component FROM t JOIN m USING (conv_id)")
def _components(s, d):
    return connectivity.connected_components(fixed(G.conversation_graph(s, d)))


@query("contract_nations", "SELECT (SELECT count(*) FROM region) AS n, CAST(0 AS BIGINT) AS m")
def _contract(s, d):
    g = G.hierarchy_graph(s, d)
    c = connectivity.connected_components(fixed(g)).withColumnRenamed("component", "to")
    q = connectivity.contract(g, c)
    return q.vertices.agg(F.count("*").alias("n")).crossJoin(q.edges.agg(F.count("*").alias("m")))  # one row each


@query("separating_c4_marked", "SELECT * FROM (VALUES ('wheel', FALSE, FALSE), ('bipyramid', TRUE, TRUE)) t(graph, program, enumerated)")
def _separating(s, d):
    # two poles and two nations part the ring; a hub and three neighbours don't
    out = None
    for name, hubs in (("wheel", 1), ("bipyramid", 2)):
        g = fixed(G.nation_ring(s, d, hubs))
        marked = g.vertices.select("id")
        row = one(s, graph=name, program=connectivity.decide_separating_cycle(g, 4, marked), enumerated=not is_empty(connectivity.enumerate_then_separate(g, P.cycle(4), marked)))
        out = row if out is None else out.union(row)
    return out


_C4_GABRIEL = pattern_sql(E_GABRIEL, P.cycle(4))


@query("enumerate_then_separate", f"""WITH RECURSIVE found AS ({_C4_GABRIEL}), {E_GABRIEL}, r AS (SELECT src, dst FROM e UNION ALL SELECT dst, src FROM e),
reach(a, b, c, d, id) AS (SELECT a, b, c, d, (SELECT min(id) FROM p WHERE id NOT IN (a, b, c, d)) FROM found
 UNION SELECT x.a, x.b, x.c, x.d, r.dst FROM reach x JOIN r ON r.src = x.id WHERE r.dst <> x.a AND r.dst <> x.b AND r.dst <> x.c AND r.dst <> x.d)
SELECT a, b, c, d FROM reach GROUP BY a, b, c, d HAVING count(*) < (SELECT count(*) FROM p) - 4""")
def _enumerate(s, d):
    g = fixed(G.embedding_gabriel_graph(s, d))
    return columns(connectivity.enumerate_then_separate(g, P.cycle(4), g.vertices.select("id")), 4)


@query("separating_uncontracted_counterexample", "SELECT FALSE AS contracted, TRUE AS uncontracted")
def _uncontracted(s, d):
    # a ring: removing three in a row never separates it, but a window by itself looks separated
    g = fixed(G.nation_ring(s, d))
    marked = g.vertices.select("id")
    return one(s, contracted=connectivity.decide_separating(g, P.WEDGE, marked), uncontracted=connectivity.decide_separating(g, P.WEDGE, marked, contract_rest=False))


# guards, bounds and simulations
@query("guard_report", " UNION ALL ".join(f"SELECT * FROM (WITH {e}, q AS (SELECT count(DISTINCT id) AS n FROM (SELECT src AS id FROM e UNION ALL SELECT dst FROM e)) SELECT '{k}' AS graph, n, m, m <= 3 * n - 6 AS planar_possible FROM q, (SELECT count(*) AS m FROM e))" for k, (_, e) in GRAPHS.items()))
def _guards(s, d):
    out = None
    for k, (build, _) in GRAPHS.items():
        e = build(s, d).edges
        n = e.select(F.col("src").alias("id")).union(e.select("dst")).agg(F.count_distinct("id").alias("n"))
        row = n.crossJoin(e.agg(F.count("*").alias("m"))).select(F.lit(k).alias("graph"), "n", "m", (F.col("m") <= 3 * F.col("n") - 6).alias("planar_possible"))  # one row each
        out = row if out is None else out.union(row)
    return out


@query("guard_planar", "SELECT 'lattice' AS graph, TRUE AS planar_possible UNION ALL SELECT 'order_part', FALSE UNION ALL SELECT 'fan', TRUE")
def _planar(s, d):
    out = None
    for k in ("lattice", "order_part", "fan"):
        row = ms.check_target(fixed(GRAPHS[k][0](s, d))).select(F.lit(k).alias("graph"), "planar_possible")
        out = row if out is None else out.union(row)
    return out


@query("apex_window_width")
def _apex(s, d):
    g = fixed(G.lattice_crop(s, d, 12))
    hub = g.vertices.select(F.col("id").alias("src"), F.lit(KIND).cast("long").alias("dst"))
    apex = TargetGraph(g.vertices.unionByName(s.createDataFrame([(KIND, "apex", None, None)], "id long, label string, x double, y double")), g.edges.union(hub))
    both = ms.window_widths(g, P.TRIANGLE).agg(F.max("width").alias("plain")).crossJoin(ms.window_widths(fixed(apex), P.TRIANGLE).agg(F.max("width").alias("apex")))  # one row each
    return both.withColumn("wider", F.col("apex") > F.col("plain"))


@query("coloring_hit_rate", f"""WITH {E_RING}, c AS (SELECT r AS rep, n_nationkey AS id, CAST(floor((CAST(('0x' || substr(md5('1|colour|' || r || '|' || n_nationkey), 1, 13)) AS BIGINT) + 0.5) / 4503599627370496.0 * 2) AS INTEGER) AS colour FROM nation, (SELECT unnest(range(0, 64)) AS r)),
w AS (SELECT a.rep, a.colour, e.src, e.dst FROM e JOIN c a ON a.id = e.src JOIN c b ON b.id = e.dst AND b.rep = a.rep AND b.colour = a.colour)
SELECT 4 * (SELECT count(*) FROM w x JOIN w y ON x.rep = y.rep AND x.colour = 0 AND y.colour = 1) AS hits, 64 * 4 * (SELECT count(*) FROM e x JOIN e y ON x.src <> y.src AND x.src <> y.dst AND x.dst <> y.src AND x.dst <> y.dst) AS total, TRUE AS near""")
def _hits(s, d):
    return ms.coloring_hits(fixed(G.nation_ring(s, d)), P.TWO_EDGES)


@query("coin_flip_tail", """WITH t AS (SELECT string_agg(CASE WHEN (CAST(('0x' || substr(md5('1|' || c_custkey || '|' || i), 1, 13)) AS BIGINT) + 0.5) / 4503599627370496.0 < 0.5 THEN 'h' ELSE 't' END, '' ORDER BY i) AS tosses FROM customer, (SELECT unnest(range(1, 65)) AS i) GROUP BY c_custkey)
SELECT CAST(r AS INTEGER) AS run, avg(CASE WHEN contains(tosses, repeat('h', r)) THEN 1 ELSE 0 END) <= least(1, 64 * power(2, -r)) AS ok, count(*) FILTER (WHERE contains(tosses, repeat('h', r))) AS held FROM t, (SELECT CAST(unnest(range(4, 15)) AS INTEGER) AS r) GROUP BY r""")
def _flips(s, d):
    return ms.coin_flip_tail(table(s, d, "customer").select(F.col("c_custkey").alias("id"))).select("run", "ok", "held")


@query("bounds_table", f"""WITH b AS (SELECT count(DISTINCT c_custkey) AS n FROM customer UNION SELECT count(DISTINCT o_orderkey) FROM orders UNION SELECT count(DISTINCT event_id) FROM events),
g AS (SELECT k, n, log2(3 * k + 1) AS lk, log2(n) AS ln, log2(log2(n)) AS lln, log2(k) AS kk FROM (VALUES (3), (4), (6)) a(k), b)
SELECT 'color_splitting' AS method, k, n, round({math.log2(math.e)!r} * k + sqrt(k) * ln + lln, 4) AS log2_work, round(kk + lln, 4) AS log2_depth FROM g
UNION ALL SELECT 'sequential_cover', k, n, round(3 * k * lk + ln, 4), round(kk + ln, 4) FROM g UNION ALL SELECT 'single_exponential', k, n, round(CAST(18.81 AS DOUBLE) * k + ln, 4), round(CAST(18.81 AS DOUBLE) * k + ln, 4) FROM g
UNION ALL SELECT 'sub_exponential', k, n, round(k / greatest(kk, 1) + ln, 4), round(k / greatest(kk, 1) + ln, 4) FROM g UNION ALL SELECT 'parallel_cover', k, n, round(3 * k * lk + ln + lln, 4), round(kk + 2 * lln, 4) FROM g""")
def _bounds(s, d):
    # sizes of graphs: what the customers, orders and events are as vertices
    sizes = None
    for name, key in (("customer", "c_custkey"), ("orders", "o_orderkey"), ("events", "event_id")):
        row = table(s, d, name).agg(F.count_distinct(key).alias("n"))
        sizes = row if sizes is None else sizes.union(row)
    return baselines.bounds_table(sizes.distinct())


@query("pattern_catalogue", """SELECT * FROM (VALUES ('triangle', 3, 1, 1, 6), ('cycle4', 4, 2, 1, 8), ('cycle6', 6, 3, 1, 12), ('clique4', 4, 1, 1, 24), ('diamond', 4, 2, 1, 4), ('bowtie', 5, 2, 1, 8), ('wheel5', 6, 2, 1, 10), ('house', 5, 2, 1, 2), ('tadpole', 5, 3, 1, 2), ('two_edges', 4, 1, 2, 8), ('two_triangles', 6, 1, 2, 72), ('three_edges', 6, 1, 3, 48)) t(name, k, diameter, components, automorphisms)""")
def _catalogue(s, d):
    every = {"triangle": P.TRIANGLE, "cycle4": P.cycle(4), "cycle6": P.cycle(6), "clique4": P.clique(4), "diamond": P.DIAMOND, "bowtie": P.BOWTIE, "wheel5": P.wheel(5), "house": P.HOUSE, "tadpole": P.TADPOLE, "two_edges": P.TWO_EDGES, "two_triangles": P.TWO_TRIANGLES, "three_edges": P.THREE_EDGES}
    return s.createDataFrame([(n, p.k, p.diameter, len(p.components), len(p.automorphisms)) for n, p in every.items()], "name string, k int, diameter int, components int, automorphisms int")


@query("document_repeat_chain", """WITH l AS (SELECT doc_id, unnest(string_split(text, chr(10))) AS line, generate_subscripts(string_split(text, chr(10)), 1) AS pos FROM documents),
p AS (SELECT doc_id, pos, line, lag(line) OVER (PARTITION BY doc_id ORDER BY pos) AS b FROM l), f AS (SELECT doc_id, line, row_number() OVER (PARTITION BY doc_id ORDER BY pos) - 1 AS at FROM p WHERE b IS NULL OR b <> line)
SELECT x.doc_id * 1048576 + x.at AS a, x.doc_id * 1048576 + x.at + 1 AS b, x.doc_id * 1048576 + x.at + 2 AS c FROM f x JOIN f y ON x.doc_id = y.doc_id AND y.at = x.at + 2 AND x.line = y.line""")
def _repeat_chain(s, d):
    g = G.document_line_chain(s, d)
    m = materialise(search.list_occurrences(g, P.WEDGE, alike=(0, 2)))
    m = m.select(F.get("mapping", F.lit(0)).alias("a"), F.get("mapping", F.lit(1)).alias("b"), F.get("mapping", F.lit(2)).alias("c"))
    ends = m.select(F.explode(F.array("a", "c")).alias("id")).distinct()
    named = materialise(g.vertices.join(F.broadcast(ends) if m.count() <= 500_000 else ends, "id", "left_semi").select("id", "label"))
    lab = lambda c: named.select(F.col("id").alias(c), F.col("label").alias(f"l{c}"))
    both = m.join(lab("a"), "a").join(lab("c"), "c").where("la = lc")
    return both.select(F.least("a", "c").alias("a"), "b", F.greatest("a", "c").alias("c"))


def queries() -> dict[str, Query]:
    return QUERIES | relational.QUERIES | streams.QUERIES


def oracle_sql() -> dict[str, str]:
    return ORACLES | relational.ORACLES | streams.ORACLES
