"""Graphs built from the given tables; planar by construction unless said otherwise."""

from __future__ import annotations

import math
from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from coverdp.model import KIND, TargetGraph, target_graph
from coverdp.runtime import is_empty, materialise, table

#: Points that a nearest-region search sends to every task.
MOST_POINTS = 500_000


def _pair(a: Column | str, b: Column | str) -> list[Column]:
    a, b = (F.col(x) if isinstance(x, str) else x for x in (a, b))
    return [F.least(a, b).cast("long").alias("src"), F.greatest(a, b).cast("long").alias("dst")]


def _kind(j: int, key: str) -> Column:
    return F.lit(j * KIND) + F.col(key).cast("long")


def hierarchy_graph(spark: SparkSession, d: str) -> TargetGraph:
    """region - nation - customer - orders by foreign key: a forest."""
    nation, customer, orders = (table(spark, d, t) for t in ("nation", "customer", "orders"))
    edges = nation.select(*_pair(_kind(1, "n_regionkey"), _kind(2, "n_nationkey")))
    edges = edges.union(customer.select(*_pair(_kind(2, "c_nationkey"), _kind(3, "c_custkey"))))
    edges = edges.union(orders.select(*_pair(_kind(3, "o_custkey"), _kind(4, "o_orderkey"))))
    v = table(spark, d, "region").select(_kind(1, "r_regionkey").alias("id"), F.lit("region").alias("label"))
    v = v.union(nation.select(_kind(2, "n_nationkey"), F.lit("nation"))).union(customer.select(_kind(3, "c_custkey"), F.lit("customer"))).union(orders.select(_kind(4, "o_orderkey"), F.lit("order")))
    return target_graph(v, edges)


def event_chain_edges(events: DataFrame) -> DataFrame:
    """Each event with the user's next one."""
    w = W.partitionBy("user_id").orderBy("ts", "event_id")
    return events.select("event_id", F.lead("event_id").over(w).alias("next")).where("next is not null").select(*_pair("event_id", "next"))


def event_fan_graph(spark: SparkSession, d: str) -> TargetGraph:
    """A hub for each user with spokes to its events, the events in a path by time, the hubs chained.

    Drawn in the plane: hubs on a line by user, each user's events in order on a line above, within half a unit.
    """
    events = table(spark, d, "events")
    users = events.select("user_id").distinct()
    spokes = events.select(*_pair("event_id", _kind(1, "user_id")))
    hubs = users.join(users.select((F.col("user_id") - 1).alias("user_id")), "user_id", "left_semi").select(*_pair(_kind(1, "user_id"), F.lit(KIND + 1) + F.col("user_id")))
    own = W.partitionBy("user_id")
    share = (F.row_number().over(own.orderBy("ts", "event_id")) - 0.5) / F.count("*").over(own)
    v = events.select(F.col("event_id").alias("id"), F.col("event_type").alias("label"), (F.col("user_id") - 0.5 + share).alias("x"), F.lit(1.0).alias("y"))
    v = v.union(users.select(_kind(1, "user_id"), F.lit("user"), F.col("user_id").cast("double"), F.lit(0.0)))
    return target_graph(v, spokes.union(event_chain_edges(events)).union(hubs))


def event_chain_graph(spark: SparkSession, d: str) -> TargetGraph:
    """The users' event paths alone, labelled by event type."""
    events = table(spark, d, "events")
    return target_graph(events.select(F.col("event_id").alias("id"), F.col("event_type").alias("label")), event_chain_edges(events))


def _lattice_edges(o: DataFrame, n: int, w: int) -> DataFrame:
    k, in_row, down = F.col("k"), F.col("k") % w < w - 1, F.col("k") + w < n
    steps = F.array(
        F.when(in_row & (F.col("k") + 1 < n), F.struct(k.alias("a"), (k + 1).alias("b"))),
        F.when(down, F.struct(k.alias("a"), (k + w).alias("b"))),
        F.when((F.col("s") == "F") & in_row & (F.col("k") + w + 1 < n), F.struct(k.alias("a"), (k + w + 1).alias("b"))),
        F.when((F.col("s") == "O") & in_row & down, F.struct((k + 1).alias("a"), (k + w).alias("b"))),
    )
    return o.select(F.explode(F.filter(steps, lambda x: x.isNotNull())).alias("e")).select(*_pair("e.a", "e.b"))


def order_lattice_graph(spark: SparkSession, d: str) -> TargetGraph:
    """Orders on a grid floor(sqrt(n)) wide, with a diagonal by order status in each cell."""
    o = table(spark, d, "orders").select(F.col("o_orderkey").alias("k"), F.col("o_orderstatus").alias("s"), F.col("o_orderpriority").alias("p"))
    n = o.count()
    w = max(1, math.isqrt(n))
    v = o.select(F.col("k").alias("id"), F.col("p").alias("label"), (F.col("k") % w).cast("double").alias("x"), F.floor(F.col("k") / w).cast("double").alias("y"))
    return target_graph(v, _lattice_edges(o, n, w))


def lattice_crop(spark: SparkSession, d: str, side: int) -> TargetGraph:
    """The upper left side x side part of the order lattice."""
    g = order_lattice_graph(spark, d)
    return g.induced(g.vertices.where((F.col("x") < side) & (F.col("y") < side)))


def points(spark: SparkSession, d: str) -> DataFrame:
    e = table(spark, d, "embeddings")
    return e.select(F.col("vec_id").alias("id"), F.col("label").cast("string").alias("label"), F.get("embedding", F.lit(0)).cast("double").alias("x"), F.get("embedding", F.lit(1)).cast("double").alias("y"))


#: Places of a block, and directions in which a place must be closed off before its region is known to be searched whole.
BLOCK, SECTORS = 48, 16


def _reach(v: np.ndarray) -> float:
    """How far a neighbour of the origin may lie, when `v` are other places: each keeps all beyond the line through it, square to it, from the origin."""
    far = np.hypot(v[:, 0], v[:, 1])
    v, far = v[far > 0], far[far > 0]
    ends = np.arange(SECTORS) * (2 * math.pi / SECTORS)
    along = v[:, :1] * np.cos(ends) + v[:, 1:] * np.sin(ends)
    least = np.minimum(along, np.roll(along, -1, axis=1)) / far[:, None]
    bound = np.where(least > 1e-3, far[:, None] / np.maximum(least, 1e-3), np.inf)
    return float(bound.min(axis=0, initial=np.inf).max()) * (1 + 1e-9)


def _free(xy: np.ndarray, i: int, cand: np.ndarray, others: np.ndarray, inside) -> np.ndarray:
    """Of `cand` those whose region with place i holds none of `others`, tried nearest first while many are left."""
    gap = xy[others] - xy[i]
    others = others[np.argsort((gap * gap).sum(axis=1), kind="stable")]
    at, step = 0, 1 if len(cand) > 64 else 64
    while at < len(others) and len(cand):
        cand = cand[~inside(xy, others[at : at + step], i, cand).any(axis=1)]
        at, step = at + step, max(1, min(2 * step, 2_000_000 // max(1, len(cand))))
    return cand


def _neighbours(xy: np.ndarray, rows: np.ndarray, inside) -> tuple[list[np.ndarray], list[np.ndarray]]:
    """(i, j) of the edges of a block of different places, xy sorted by x: what lies near enough to matter is searched, all places where no bound holds."""
    left, right = [], []
    box = xy[rows]
    reach = max(float(np.ptp(box[:, 0])), float(np.ptp(box[:, 1])))
    while len(rows):
        box = xy[rows]
        lo, hi = box.min(axis=0) - reach, box.max(axis=0) + reach
        a, z = np.searchsorted(xy[:, 0], lo[0], side="left"), np.searchsorted(xy[:, 0], hi[0], side="right")
        near = a + np.flatnonzero((xy[a:z, 1] >= lo[1]) & (xy[a:z, 1] <= hi[1]))
        whole = len(near) == len(xy)
        open_ = []
        for i in rows.tolist():
            gap = xy[near] - xy[i]
            far = np.hypot(gap[:, 0], gap[:, 1])
            bound = np.inf
            if len(near) > 1:
                some = np.argpartition(far, 64)[:65] if len(far) > 65 else np.arange(len(far))
                bound = _reach(gap[some])
                if bound == np.inf and len(far) > 65:
                    bound = _reach(gap)
            if bound < reach:
                use = near[far <= bound]
            elif whole:
                use = near
            else:
                open_.append(i)
                continue
            found = _free(xy, i, use[use != i], use[use != i], inside)
            left.append(np.full(len(found), i)), right.append(found)
        rows, reach = np.array(open_, np.int64), 4 * reach if reach > 0 else 1.0
    return left, right


def _proximity(pts: DataFrame, inside: Callable[[np.ndarray, np.ndarray, int, np.ndarray], np.ndarray]) -> DataFrame:
    """Pairs whose region holds no third point. All points go to each task, up to MOST_POINTS of them.

    Equal places are searched once: a point lies in no region of a pair that has an end at its own place. Points
    without a place lie in no region and are in none, so each is paired with every other; those at infinity are tried
    against all.
    """
    spark = pts.sparkSession
    n = pts.count()
    if n > MOST_POINTS:
        raise ValueError(f"{n} points; a proximity graph is built for {MOST_POINTS} at most")
    every = pts.select("id", "x", "y").toPandas()
    ids, xy = every["id"].to_numpy(np.int64), every[["x", "y"]].to_numpy(float) + 0.0  # one zero
    lost, infinite = np.isnan(xy).any(axis=1), np.isinf(xy).any(axis=1)
    nowhere, beyond, beyond_xy = ids[lost], ids[infinite & ~lost], xy[infinite & ~lost]
    ids, xy = ids[~lost & ~infinite], xy[~lost & ~infinite]
    place, member = np.unique(xy, axis=0, return_inverse=True)
    member = member.ravel()
    order = np.argsort(member, kind="stable")
    first = np.searchsorted(member[order], np.arange(len(place) + 1))
    # strips by x, blocks of a strip by y
    strips = max(1, math.isqrt(len(place) // BLOCK))
    strip = np.arange(len(place)) * strips // max(1, len(place))
    dealt = np.lexsort((place[:, 1], strip))
    shared = spark.sparkContext.broadcast((place, ids[order], first, dealt, nowhere, beyond, beyond_xy))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        place, ids, first, dealt, nowhere, beyond, beyond_xy = shared.value

        def pairs(i: np.ndarray, j: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
            """Every point at place i with every one at place j."""
            ni, nj = first[i + 1] - first[i], first[j + 1] - first[j]
            many = ni * nj
            nth = np.arange(int(many.sum())) - np.repeat(np.cumsum(many) - many, many)
            by = np.repeat(nj, many)
            return ids[np.repeat(first[i], many) + nth // by], ids[np.repeat(first[j], many) + nth % by]

        for b in batches:
            for block in b.column(0).to_pylist():
                rows = dealt[block * BLOCK : (block + 1) * BLOCK]
                if len(rows):
                    left, right = _neighbours(place, rows, inside)
                    i, j = np.concatenate([rows, *left]), np.concatenate([rows, *right])
                    src, dst = pairs(i, j)
                    yield pa.record_batch({"src": src[src < dst], "dst": dst[src < dst]})
                if block < len(nowhere):
                    one = nowhere[block]
                    other = np.concatenate([ids, beyond, nowhere[nowhere > one]])
                    yield pa.record_batch({"src": np.minimum(one, other), "dst": np.maximum(one, other)})
                if block < len(beyond):
                    one, both = beyond[block], np.concatenate([place, beyond_xy])
                    rest = np.delete(np.arange(len(both)), len(place) + block)
                    with np.errstate(invalid="ignore"):
                        found = _free(both, len(place) + block, rest, rest, inside)
                    own = found[found < len(place)]
                    other = [ids[first[j] : first[j + 1]] for j in own.tolist()]
                    other = np.concatenate([*other, (x := beyond[found[found >= len(place)] - len(place)])[x > one]])
                    yield pa.record_batch({"src": np.minimum(one, other), "dst": np.maximum(one, other)})

    blocks = max(1, -(-len(place) // BLOCK), len(nowhere), len(beyond))
    tasks = max(8, spark.sparkContext.defaultParallelism)
    return spark.range(blocks).repartition(tasks).mapInArrow(run, "src long, dst long")


def _in_disc(xy, r, i, j):
    """For each place j (rows) and each r (columns) whether r lies in the region of i and j."""
    a, b = (xy[r] - xy[i])[None], xy[r][None] - xy[j][:, None]
    return a[..., 0] * b[..., 0] + a[..., 1] * b[..., 1] < 0


def _in_lune(xy, r, i, j):
    a, b, c = (xy[r] - xy[i])[None], xy[r][None] - xy[j][:, None], xy[i] - xy[j]
    most = (c[:, 0] * c[:, 0] + c[:, 1] * c[:, 1])[:, None]
    return (a[..., 0] * a[..., 0] + a[..., 1] * a[..., 1] < most) & (b[..., 0] * b[..., 0] + b[..., 1] * b[..., 1] < most)


def embedding_gabriel_graph(spark: SparkSession, d: str) -> TargetGraph:
    """The first two coordinates; an edge if no third point lies in the disc over the pair."""
    pts = points(spark, d)
    return target_graph(pts, _proximity(pts, _in_disc))


def embedding_rng_graph(spark: SparkSession, d: str) -> TargetGraph:
    """As above; an edge if no third point is nearer to both ends than they are to each other."""
    pts = points(spark, d)
    return target_graph(pts, _proximity(pts, _in_lune))


def _role() -> Column:
    return F.when(F.col("role") == "system", 0).when(F.col("role") == "user", 1).otherwise(2)


def conversation_graph(spark: SparkSession, d: str) -> TargetGraph:
    """The turns of a conversation in a path, and a hub for each role joined to its turns."""
    c = table(spark, d, "conversations").select("conv_id", "turn", "role")
    turn = (F.col("conv_id") * 64 + F.col("turn")).cast("long")
    hub = F.lit(KIND) + F.col("conv_id") * 8 + _role()
    nxt = c.select("conv_id", (F.col("turn") - 1).alias("turn"))
    chain = c.join(nxt, ["conv_id", "turn"], "left_semi").select(*_pair(turn, turn + 1))
    v = c.select(turn.alias("id"), F.col("role").alias("label")).union(c.select(hub, F.lit("hub")).distinct())
    return target_graph(v, chain.union(c.select(*_pair(turn, hub))))


def nation_ring(spark: SparkSession, d: str, hubs: int = 0) -> TargetGraph:
    """The nations in a ring (connectivity 2); one hub joined to all makes a wheel (3), two a bipyramid (4)."""
    n = table(spark, d, "nation").select(F.col("n_nationkey").cast("long").alias("k"))
    size = n.count()
    edges = n.select(*_pair(F.col("k"), (F.col("k") + 1) % size))
    angle = F.col("k") * (2 * math.pi / size)
    v = n.select(F.col("k").alias("id"), F.lit("nation").alias("label"), F.cos(angle).alias("x"), F.sin(angle).alias("y"))
    for h in range(hubs):
        edges = edges.union(n.select(*_pair(F.col("k"), F.lit(KIND + h))))
        v = v.union(spark.range(1).select(F.lit(KIND + h), F.lit("hub"), F.lit(0.0) if h == 0 else F.lit(float("inf")), F.lit(0.0)))
    return target_graph(v, edges)


def supplier_antiprism_graph(spark: SparkSession, d: str) -> TargetGraph:
    """Suppliers in rings of five, neighbouring rings joined as antiprisms, a pole at each end: connectivity 5."""
    s = table(spark, d, "supplier").select(F.col("s_suppkey").cast("long").alias("k"))
    rings = s.count() // 5
    s = s.where(F.col("k") < rings * 5).select("k", F.floor(F.col("k") / 5).alias("r"), (F.col("k") % 5).alias("j"))
    to = lambda r, j: r * 5 + j % 5
    r, j = F.col("r"), F.col("j")
    edges = s.select(*_pair(F.col("k"), to(r, j + 1)))
    upper = s.where(r < rings - 1)
    edges = edges.union(upper.select(*_pair(F.col("k"), to(r + 1, j)))).union(upper.select(*_pair(F.col("k"), to(r + 1, j + 1))))
    edges = edges.union(s.where(r == 0).select(*_pair(F.col("k"), F.lit(KIND)))).union(s.where(r == rings - 1).select(*_pair(F.col("k"), F.lit(KIND + 1))))
    # rings as polygons of twice the size each, turned by half a step; the outer pole at infinity
    angle, radius = (j - r / 2) * (2 * math.pi / 5), F.pow(F.lit(2.0), r)
    v = s.select(F.col("k").alias("id"), F.lit("supplier").alias("label"), (radius * F.cos(angle)).alias("x"), (radius * F.sin(angle)).alias("y"))
    v = v.union(spark.createDataFrame([(KIND, "pole", 0.0, 0.0), (KIND + 1, "pole", float("inf"), 0.0)], "id long, label string, x double, y double"))
    return target_graph(v, edges)


def order_torus_graph(spark: SparkSession, d: str) -> TargetGraph:
    """The order grid without diagonals on its largest full rectangle, wrapped both ways: genus 1, not planar."""
    o = table(spark, d, "orders").select(F.col("o_orderkey").alias("k"), F.col("o_orderpriority").alias("label"))
    n = o.count()
    w = math.isqrt(n)
    h = n // w
    o = o.where(F.col("k") < w * h)
    right = F.when(F.col("k") % w == w - 1, F.col("k") - (w - 1)).otherwise(F.col("k") + 1)
    return target_graph(o.select(F.col("k").alias("id"), "label"), o.select(*_pair("k", right)).union(o.select(*_pair(F.col("k"), (F.col("k") + w) % (w * h)))))


def apex_lattice_graph(spark: SparkSession, d: str) -> TargetGraph:
    """The order lattice and a hub tied to every order: its local treewidth isn't bounded."""
    g = order_lattice_graph(spark, d)
    v = g.vertices.union(spark.createDataFrame([(KIND, "apex", None, None)], "id long, label string, x double, y double"))
    return target_graph(v, g.edges.union(g.vertices.select(*_pair("id", F.lit(KIND)))))


def order_part_graph(spark: SparkSession, d: str) -> TargetGraph:
    """Orders and their parts: not planar."""
    pairs = table(spark, d, "lineitem").select(_kind(1, "l_orderkey").alias("a"), _kind(2, "l_partkey").alias("b")).distinct()
    v = pairs.select(F.col("a").alias("id"), F.lit("order").alias("label")).union(pairs.select("b", F.lit("part"))).distinct()
    return target_graph(v, pairs.select(*_pair("a", "b")))


def customer_nation_supplier_graph(spark: SparkSession, d: str) -> TargetGraph:
    """Nation hubs with customer and supplier leaves: a forest."""
    n, c, s = table(spark, d, "nation"), table(spark, d, "customer"), table(spark, d, "supplier")
    edges = c.select(*_pair(_kind(1, "c_nationkey"), _kind(2, "c_custkey"))).union(s.select(*_pair(_kind(1, "s_nationkey"), _kind(3, "s_suppkey"))))
    v = n.select(_kind(1, "n_nationkey").alias("id"), F.lit("nation").alias("label")).union(c.select(_kind(2, "c_custkey"), F.lit("customer"))).union(s.select(_kind(3, "s_suppkey"), F.lit("supplier")))
    return target_graph(v, edges)


def document_line_chain(spark: SparkSession, d: str) -> TargetGraph:
    """The lines of each document in a path, equal neighbours merged; labels are hashes of lines.

    A document's lines are cut within its row, so nothing is shuffled; only where a doc_id repeats are they gathered by it.
    """
    docs = table(spark, d, "documents").select("doc_id", F.split("text", "\n").alias("lines"))
    if is_empty(docs.groupBy("doc_id").count().where("count > 1")):
        own = F.filter("lines", lambda x, i: (i == 0) | (x != F.get("lines", i - 1)))
        first = docs.select("doc_id", F.posexplode(own).alias("at", "line")).select("doc_id", F.md5("line").alias("label"), "at")
    else:
        lines = docs.select("doc_id", F.posexplode("lines").alias("pos", "line"))
        w = W.partitionBy("doc_id").orderBy("pos")
        first = lines.withColumn("before", F.lag("line").over(w)).where("before is null or before <> line").select("doc_id", F.md5("line").alias("label"), (F.row_number().over(w) - 1).alias("at"))
    node = F.col("doc_id") * (1 << 20) + F.col("at")
    blank = F.lit(None).cast("double")
    return TargetGraph(first.select(node.alias("id"), "label", blank.alias("x"), blank.alias("y")), first.where("at > 0").select(*_pair(node - 1, node)))


def dom_tree_graph(spark: SparkSession, d: str) -> TargetGraph:
    """Element nesting of pages: one tree a page, labelled by tag; void elements are leaves, unclosed ones end with their parent."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        from html.parser import HTMLParser

        void = set("area base br col embed hr img input link meta source track wbr".split())

        class Nesting(HTMLParser):
            def __init__(self):
                super().__init__()
                self.open, self.rows = [], []

            def handle_starttag(self, tag, attrs):
                self.rows.append((len(self.rows), self.open[-1][1] if self.open else None, tag))
                if tag not in void:
                    self.open.append((tag, self.rows[-1][0]))

            def handle_endtag(self, tag):
                if any(t == tag for t, _ in self.open):
                    while self.open.pop()[0] != tag:
                        pass

        for b in batches:
            ids, parents, tags = [], [], []
            for page, html in zip(b.column(0).to_pylist(), b.column(1).to_pylist(), strict=True):
                p = Nesting()
                p.feed(html or "")
                for i, up, tag in p.rows:
                    ids.append((page << 20) + i), parents.append(None if up is None else (page << 20) + up), tags.append(tag)
            yield pa.record_batch({"id": pa.array(ids, pa.int64()), "parent": pa.array(parents, pa.int64()), "label": pa.array(tags, pa.string())})

    rows = materialise(table(spark, d, "pages").select("page_id", "html").mapInArrow(run, "id long, parent long, label string"))
    return target_graph(rows.select("id", "label"), rows.where("parent is not null").select(*_pair("id", "parent")))
