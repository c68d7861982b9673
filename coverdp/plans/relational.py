"""The relational operators around the methods, each as a query with SQL beside it."""

from __future__ import annotations

import uuid
from collections.abc import Callable
from functools import reduce

import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import Window as W
from pyspark.sql import functions as F

from coverdp.functions import udfs
from coverdp.runtime import shared_folder, table
from coverdp.sources import edgelist
from coverdp.sources import graphs as G

QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {}
ORACLES: dict[str, str] = {}
TABLES = ("region", "nation", "customer", "supplier", "part", "orders", "lineitem", "events", "documents", "embeddings", "pages", "benchmark", "labels", "conversations")
LATTICE = """o AS (SELECT o_orderkey AS k, o_orderstatus AS s, o_orderpriority AS p FROM orders), c AS (SELECT count(*) AS n, CAST(floor(sqrt(count(*))) AS BIGINT) AS w FROM o),
e AS (SELECT k AS src, k + 1 AS dst FROM o, c WHERE k % w < w - 1 AND k + 1 < n UNION ALL SELECT k, k + w FROM o, c WHERE k + w < n
 UNION ALL SELECT k, k + w + 1 FROM o, c WHERE s = 'F' AND k % w < w - 1 AND k + w + 1 < n UNION ALL SELECT k + 1, k + w FROM o, c WHERE s = 'O' AND k % w < w - 1 AND k + w < n),
r AS (SELECT src, dst FROM e UNION ALL SELECT dst, src FROM e)"""


#: Points that the theta join broadcasts.
THETA_POINTS = 20_000


def query(name: str, sql: str | None = None):
    def put(f):
        QUERIES[f"op_{name}"] = f
        if sql:
            ORACLES[f"op_{name}"] = sql
        return f

    return put


@query("scan_parquet_counts", " UNION ALL ".join(f"SELECT '{t}' AS name, count(*) AS n FROM {t}" for t in TABLES))
def _(s, d):
    return reduce(DataFrame.union, (table(s, d, t).agg(F.count("*").alias("n")).select(F.lit(t).alias("name"), "n") for t in TABLES))


@query("scan_projected_columns", "SELECT l_orderkey, l_quantity, l_shipdate FROM lineitem WHERE l_shipdate >= TIMESTAMP '1997-01-01'")
def _(s, d):
    return table(s, d, "lineitem").where(F.col("l_shipdate") >= F.lit("1997-01-01").cast("timestamp")).select("l_orderkey", "l_quantity", "l_shipdate")


@query("sink_edges_roundtrip")
def _(s, d):
    e = G.nation_ring(s, d).edges
    base, rows = f"{shared_folder(s)}/coverdp-edges-{uuid.uuid4().hex}", []
    for kind in ("parquet", "orc", "csv", "json", "text"):
        edgelist.write_edges(e, f"{base}/{kind}", kind)
        rows.append((kind, edgelist.read_edges(s, f"{base}/{kind}", kind).exceptAll(e).count()))
    return s.createDataFrame(rows, "kind string, lost long")


@query("source_edgelist", "SELECT CAST(1 AS BIGINT) AS src, CAST(2 AS BIGINT) AS dst UNION ALL SELECT 2, 3")
def _(s, d):
    edgelist.register(s)
    return s.read.format("edgelist").option("lines", "1 2;3 2").load()


@query("filter_marked_orders", "SELECT o_orderkey FROM orders WHERE o_orderpriority = '1-URGENT' AND o_orderstatus <> 'P'")
def _(s, d):
    return table(s, d, "orders").where("o_orderpriority = '1-URGENT' and o_orderstatus <> 'P'").select("o_orderkey")


@query("case_label_bucket", "SELECT p_partkey, CASE WHEN p_size < 10 THEN 'small' WHEN p_size < 30 THEN 'medium' ELSE 'large' END AS bucket FROM part")
def _(s, d):
    return table(s, d, "part").select("p_partkey", F.when(F.col("p_size") < 10, "small").when(F.col("p_size") < 30, "medium").otherwise("large").alias("bucket"))


@query("join_hash_order_customer", "SELECT o_orderkey, c_mktsegment FROM orders JOIN customer ON c_custkey = o_custkey")
def _(s, d):
    c = table(s, d, "customer").select(F.col("c_custkey").alias("o_custkey"), "c_mktsegment")
    return table(s, d, "orders").select("o_orderkey", "o_custkey").join(c.hint("shuffle_hash"), "o_custkey").select("o_orderkey", "c_mktsegment")


@query("join_broadcast_nation", "SELECT c_custkey, n_name, r_name FROM customer JOIN nation ON n_nationkey = c_nationkey JOIN region ON r_regionkey = n_regionkey")
def _(s, d):
    # nation and region have a fixed number of rows
    c = table(s, d, "customer").join(F.broadcast(table(s, d, "nation")), F.col("c_nationkey") == F.col("n_nationkey"))
    return c.join(F.broadcast(table(s, d, "region")), F.col("n_regionkey") == F.col("r_regionkey")).select("c_custkey", "n_name", "r_name")


@query("join_sortmerge_lineitem", "SELECT o_orderkey, count(*) AS n FROM lineitem JOIN orders ON o_orderkey = l_orderkey GROUP BY o_orderkey")
def _(s, d):
    return table(s, d, "lineitem").select("l_orderkey").join(table(s, d, "orders").select("o_orderkey").hint("merge"), F.col("l_orderkey") == F.col("o_orderkey")).groupBy("o_orderkey").agg(F.count("*").alias("n"))


@query("join_semi_induced", f"WITH {LATTICE} SELECT src, dst FROM e WHERE src IN (SELECT k FROM o WHERE s = 'F') AND dst IN (SELECT k FROM o WHERE s = 'F')")
def _(s, d):
    return G.order_lattice_graph(s, d).induced(table(s, d, "orders").where("o_orderstatus = 'F'").select(F.col("o_orderkey").alias("id"))).edges


@query("join_anti_missing_orders", "SELECT c_custkey FROM customer WHERE c_custkey NOT IN (SELECT o_custkey FROM orders)")
def _(s, d):
    return table(s, d, "customer").join(table(s, d, "orders").select(F.col("o_custkey").alias("c_custkey")), "c_custkey", "left_anti").select("c_custkey")


@query("join_left_degree_zero", "SELECT p_partkey, count(DISTINCT l_orderkey) AS degree FROM part LEFT JOIN lineitem ON l_partkey = p_partkey GROUP BY p_partkey")
def _(s, d):
    deg = table(s, d, "lineitem").select("l_partkey", "l_orderkey").distinct().groupBy(F.col("l_partkey").alias("p_partkey")).agg(F.count("*").alias("degree"))
    return table(s, d, "part").join(deg, "p_partkey", "left").select("p_partkey", F.coalesce("degree", F.lit(0)).alias("degree"))


@query("join_full_outer_degree", "WITH a AS (SELECT l_partkey AS k, count(*) AS lines FROM lineitem WHERE l_quantity > 45 GROUP BY 1), b AS (SELECT p_partkey AS k, p_size FROM part WHERE p_size > 25) SELECT coalesce(a.k, b.k) AS k, lines, p_size FROM a FULL JOIN b ON a.k = b.k")
def _(s, d):
    a = table(s, d, "lineitem").where("l_quantity > 45").groupBy(F.col("l_partkey").alias("k")).agg(F.count("*").alias("lines"))
    return a.join(table(s, d, "part").where("p_size > 25").select(F.col("p_partkey").alias("k"), "p_size"), "k", "full").select("k", "lines", "p_size")


@query("join_self_wedges", f"WITH {LATTICE} SELECT src AS id, count(*) * (count(*) - 1) // 2 AS wedges FROM r GROUP BY src")
def _(s, d):
    a = G.order_lattice_graph(s, d).arcs
    n = a.groupBy("src").agg(F.count("*").alias("n"))
    return n.select(F.col("src").alias("id"), F.expr("n * (n - 1) div 2").alias("wedges"))


@query("join_range_windows", "WITH z AS (SELECT count(*) AS n FROM nation), l AS (SELECT n_nationkey AS id, least(n_nationkey, n - n_nationkey) AS level FROM nation, z) SELECT id, CAST(w.start AS INTEGER) AS start FROM l, (SELECT unnest(range(0, 30)) AS start) w WHERE level BETWEEN w.start AND w.start + 2")
def _(s, d):
    n = table(s, d, "nation")
    size = n.count()
    lv = n.select(F.col("n_nationkey").alias("id"), F.least(F.col("n_nationkey"), size - F.col("n_nationkey")).alias("level"))
    return lv.select("id", F.explode(F.sequence(F.greatest(F.lit(0), F.col("level") - 2), F.col("level"))).alias("start")).select("id", F.col("start").cast("int").alias("start"))


@query("join_interval_events", "SELECT a.event_id AS a, b.event_id AS b FROM events a JOIN events b ON a.user_id = b.user_id AND b.ts > a.ts AND b.ts <= a.ts + INTERVAL 1 HOUR")
def _(s, d):
    # a range join by buckets of an hour: the partner lies in the same or the next one
    hour = F.floor(F.unix_micros(F.col("ts").cast("timestamp")) / 3_600_000_000)
    e = table(s, d, "events").select("event_id", "user_id", "ts", hour.alias("h"))
    a = e.select(F.col("event_id").alias("a"), "user_id", F.col("ts").alias("t"), F.explode(F.array("h", F.col("h") + 1)).alias("h"))
    return a.join(e.withColumnRenamed("event_id", "b"), ["user_id", "h"]).where("ts > t and ts <= t + interval 1 hour").select("a", "b")


@query("join_asof_events", "SELECT e.event_id, p.event_id AS last_purchase FROM events e ASOF LEFT JOIN (SELECT * FROM events WHERE event_type = 'purchase') p ON e.user_id = p.user_id AND e.ts > p.ts WHERE e.event_type = 'error'")
def _(s, d):
    w = W.partitionBy("user_id").orderBy("ts").rowsBetween(W.unboundedPreceding, -1)
    e = table(s, d, "events").select("event_id", "user_id", "ts", "event_type", F.last(F.when(F.col("event_type") == "purchase", F.col("event_id")), ignorenulls=True).over(w).alias("last_purchase"))
    return e.where("event_type = 'error'").select("event_id", "last_purchase")


@query("join_cross_pairs", "SELECT a.r_name AS a, b.r_name AS b FROM region a, region b WHERE a.r_regionkey <> b.r_regionkey")
def _(s, d):
    r = table(s, d, "region")  # five rows
    return r.select(F.col("r_name").alias("a"), F.col("r_regionkey").alias("x")).crossJoin(r.select(F.col("r_name").alias("b"), F.col("r_regionkey").alias("y"))).where("x <> y").select("a", "b")


@query("agg_degree_histogram", f"WITH {LATTICE}, d AS (SELECT src, count(*) AS degree FROM r GROUP BY src) SELECT degree, count(*) AS n FROM d GROUP BY degree")
def _(s, d):
    return G.order_lattice_graph(s, d).degrees().groupBy("degree").agg(F.count("*").alias("n"))


@query("agg_distinct_pairs", "SELECT count(*) AS n FROM (SELECT DISTINCT l_partkey, l_suppkey FROM lineitem)")
def _(s, d):
    return table(s, d, "lineitem").agg(F.count_distinct("l_partkey", "l_suppkey").alias("n"))


@query("agg_filtered", "SELECT user_id, count(*) FILTER (event_type = 'view') AS views, count(*) FILTER (event_type = 'purchase') AS purchases FROM events GROUP BY user_id")
def _(s, d):
    return table(s, d, "events").groupBy("user_id").agg(F.count_if(F.col("event_type") == "view").alias("views"), F.count_if(F.col("event_type") == "purchase").alias("purchases"))


@query("agg_bool_bit", "SELECT user_id, bool_or(event_type = 'error') AS had_error, bit_or(CASE event_type WHEN 'click' THEN 1 WHEN 'error' THEN 2 WHEN 'purchase' THEN 4 WHEN 'signup' THEN 8 ELSE 16 END) AS mask FROM events GROUP BY user_id")
def _(s, d):
    t = F.col("event_type")
    bit = F.when(t == "click", 1).when(t == "error", 2).when(t == "purchase", 4).when(t == "signup", 8).otherwise(16)
    return table(s, d, "events").groupBy("user_id").agg(F.bool_or(t == "error").alias("had_error"), F.bit_or(bit).alias("mask"))


@query("agg_minmax_by", "SELECT o_custkey, min(o_orderkey) FILTER (o_totalprice = m) AS cheapest FROM (SELECT *, min(o_totalprice) OVER (PARTITION BY o_custkey) AS m FROM orders) GROUP BY o_custkey")
def _(s, d):
    return table(s, d, "orders").groupBy("o_custkey").agg(F.min_by("o_orderkey", F.struct("o_totalprice", "o_orderkey")).alias("cheapest"))


@query("agg_collect_bag", "SELECT n_regionkey, string_agg(CAST(n_nationkey AS VARCHAR), ',' ORDER BY n_nationkey) AS bag FROM nation GROUP BY n_regionkey")
def _(s, d):
    return table(s, d, "nation").groupBy("n_regionkey").agg(F.concat_ws(",", F.transform(F.sort_array(F.collect_set("n_nationkey")), lambda x: x.cast("string"))).alias("bag"))


@query("agg_percentile_degree", f"WITH {LATTICE}, d AS (SELECT src, count(*) AS degree FROM r GROUP BY src) SELECT CAST(quantile_cont(degree, 0.5) AS DOUBLE) AS median FROM d")
def _(s, d):
    return G.order_lattice_graph(s, d).degrees().agg(F.percentile("degree", 0.5).alias("median"))


@query("agg_approx_distinct")
def _(s, d):
    return table(s, d, "lineitem").agg(F.approx_count_distinct("l_partkey", 0.02).alias("parts"))


@query("grouping_sets", "SELECT o_orderstatus, o_orderpriority, count(*) AS n FROM orders GROUP BY GROUPING SETS ((o_orderstatus), (o_orderpriority), ())")
def _(s, d):
    return table(s, d, "orders").groupingSets([["o_orderstatus"], ["o_orderpriority"], []], "o_orderstatus", "o_orderpriority").agg(F.count("*").alias("n"))


@query("rollup_graph_labels", "SELECT c_mktsegment, c_nationkey, count(*) AS n FROM customer GROUP BY ROLLUP (c_mktsegment, c_nationkey)")
def _(s, d):
    return table(s, d, "customer").rollup("c_mktsegment", "c_nationkey").agg(F.count("*").alias("n"))


@query("cube_orders", "SELECT o_orderstatus, o_orderpriority, count(*) AS n, CAST(grouping(o_orderstatus) * 2 + grouping(o_orderpriority) AS BIGINT) AS level FROM orders GROUP BY CUBE (o_orderstatus, o_orderpriority)")
def _(s, d):
    return table(s, d, "orders").cube("o_orderstatus", "o_orderpriority").agg(F.count("*").alias("n"), F.grouping_id().alias("level"))


@query("pivot_event_types", "SELECT user_id, count(*) FILTER (event_type = 'click') AS click, count(*) FILTER (event_type = 'view') AS \"view\" FROM events GROUP BY user_id")
def _(s, d):
    return table(s, d, "events").groupBy("user_id").pivot("event_type", ["click", "view"]).count().na.fill(0)


@query("having_hubs", "SELECT user_id, count(*) AS degree FROM events GROUP BY user_id HAVING count(*) > 60")
def _(s, d):
    return table(s, d, "events").groupBy("user_id").agg(F.count("*").alias("degree")).where("degree > 60")


@query("window_event_chain", "SELECT event_id, lead(event_id) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS nxt FROM events")
def _(s, d):
    return table(s, d, "events").select("event_id", F.lead("event_id").over(W.partitionBy("user_id").orderBy("ts", "event_id")).alias("nxt"))


@query("window_rank_degree", """WITH g AS (SELECT c_nationkey, c_custkey, count(o_orderkey) AS n FROM customer LEFT JOIN orders ON o_custkey = c_custkey GROUP BY ALL)
SELECT c_custkey, CAST(rank() OVER w AS INTEGER) AS rk, CAST(dense_rank() OVER w AS INTEGER) AS dr, CAST(row_number() OVER (PARTITION BY c_nationkey ORDER BY n DESC, c_custkey) AS INTEGER) AS rn, CAST(ntile(4) OVER (PARTITION BY c_nationkey ORDER BY n DESC, c_custkey) AS INTEGER) AS q FROM g WINDOW w AS (PARTITION BY c_nationkey ORDER BY n DESC)""")
def _(s, d):
    o = table(s, d, "orders").groupBy(F.col("o_custkey").alias("c_custkey")).agg(F.count("*").alias("n"))
    g = table(s, d, "customer").select("c_nationkey", "c_custkey").join(o, "c_custkey", "left").na.fill(0, ["n"])
    w, v = W.partitionBy("c_nationkey").orderBy(F.desc("n")), W.partitionBy("c_nationkey").orderBy(F.desc("n"), "c_custkey")
    return g.select("c_custkey", F.rank().over(w).alias("rk"), F.dense_rank().over(w).alias("dr"), F.row_number().over(v).alias("rn"), F.ntile(4).over(v).alias("q"))


@query("window_running_rows", "SELECT event_id, count(*) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN 4 PRECEDING AND CURRENT ROW) AS n FROM events")
def _(s, d):
    return table(s, d, "events").select("event_id", F.count("*").over(W.partitionBy("user_id").orderBy("ts", "event_id").rowsBetween(-4, 0)).alias("n"))


@query("window_range_time", "SELECT event_id, count(*) OVER (PARTITION BY user_id ORDER BY epoch_us(ts) // 1000000 RANGE BETWEEN 3600 PRECEDING AND CURRENT ROW) AS n FROM events")
def _(s, d):
    return table(s, d, "events").select("event_id", F.count("*").over(W.partitionBy("user_id").orderBy(F.floor(F.unix_micros(F.col("ts").cast("timestamp")) / 1_000_000)).rangeBetween(-3600, 0)).alias("n"))


@query("window_quiet_runs", """WITH a AS (SELECT user_id, event_type = 'error' AS e, row_number() OVER (PARTITION BY user_id ORDER BY ts, event_id) AS i FROM events), b AS (SELECT user_id, i - row_number() OVER (PARTITION BY user_id ORDER BY i) AS g FROM a WHERE NOT e), c AS (SELECT user_id, g, count(*) AS n FROM b GROUP BY ALL) SELECT user_id, max(n) AS longest FROM c GROUP BY user_id""")
def _(s, d):
    w = W.partitionBy("user_id").orderBy("ts", "event_id")
    a = table(s, d, "events").select("user_id", "event_type", F.row_number().over(w).alias("i")).where("event_type <> 'error'")
    b = a.select("user_id", (F.col("i") - F.row_number().over(W.partitionBy("user_id").orderBy("i"))).alias("g"))
    return b.groupBy("user_id", "g").agg(F.count("*").alias("n")).groupBy("user_id").agg(F.max("n").alias("longest"))


@query("topk_degree", f"WITH {LATTICE} SELECT src AS id, count(*) AS degree FROM r GROUP BY src ORDER BY degree DESC, id LIMIT 20")
def _(s, d):
    return G.order_lattice_graph(s, d).degrees().orderBy(F.desc("degree"), "id").limit(20)


@query("sort_full", "SELECT o_orderkey, o_totalprice FROM orders ORDER BY o_totalprice DESC, o_orderkey")
def _(s, d):
    return table(s, d, "orders").select("o_orderkey", "o_totalprice").orderBy(F.desc("o_totalprice"), "o_orderkey")


@query("union_symmetric_arcs", f"WITH {LATTICE} SELECT src, dst FROM r")
def _(s, d):
    return G.order_lattice_graph(s, d).arcs


@query("intersect_edges", "SELECT o_custkey AS k FROM orders INTERSECT SELECT user_id FROM events")
def _(s, d):
    return table(s, d, "orders").select(F.col("o_custkey").alias("k")).intersect(table(s, d, "events").select("user_id"))


@query("except_edges", "SELECT CAST(0 AS BIGINT) AS n")
def _(s, d):
    return G.embedding_rng_graph(s, d).edges.exceptAll(G.embedding_gabriel_graph(s, d).edges).agg(F.count("*").alias("n"))


@query("except_all", "SELECT l_orderkey FROM lineitem EXCEPT ALL SELECT o_orderkey FROM orders")
def _(s, d):
    return table(s, d, "lineitem").select("l_orderkey").exceptAll(table(s, d, "orders").select("o_orderkey"))


@query("string_tags", "SELECT page_id, CAST(len(regexp_extract_all(html, '<[a-z][a-z0-9]*')) AS INTEGER) AS tags FROM pages")
def _(s, d):
    return table(s, d, "pages").select("page_id", F.size(F.regexp_extract_all("html", F.lit("(<[a-z][a-z0-9]*)"))).alias("tags"))


@query("string_lines", "SELECT doc_id, CAST(len(string_split(text, chr(10))) AS INTEGER) AS lines FROM documents")
def _(s, d):
    return table(s, d, "documents").select("doc_id", F.size(F.split("text", "\n")).alias("lines"))


@query("hash_md5_uniform", "SELECT n_nationkey, CAST(('0x' || substr(md5('1|' || n_nationkey), 1, 13)) AS BIGINT) AS h FROM nation")
def _(s, d):
    return table(s, d, "nation").select("n_nationkey", F.conv(F.substring(F.md5(F.concat_ws("|", F.lit("1"), F.col("n_nationkey").cast("string"))), 1, 13), 16, 10).cast("long").alias("h"))


@query("date_buckets", "SELECT CAST(year(o_orderdate) AS INTEGER) AS y, CAST(date_trunc('month', o_orderdate) AS TIMESTAMP) AS m, count(*) AS n FROM orders GROUP BY ALL")
def _(s, d):
    return table(s, d, "orders").groupBy(F.year("o_orderdate").alias("y"), F.date_trunc("month", "o_orderdate").cast("timestamp").alias("m")).agg(F.count("*").alias("n"))


@query("math_grid_xy", "WITH c AS (SELECT CAST(floor(sqrt(count(*))) AS BIGINT) AS w FROM orders) SELECT o_orderkey AS id, CAST(o_orderkey % w AS DOUBLE) AS x, CAST(o_orderkey // w AS DOUBLE) AS y FROM orders, c")
def _(s, d):
    return G.order_lattice_graph(s, d).vertices.select("id", "x", "y")


@query("bit_masks", "SELECT event_id, CAST(1 << (event_id % 8) AS INTEGER) AS mask, CAST(bit_count(CAST(event_id % 255 AS INTEGER)) AS INTEGER) AS ones FROM events")
def _(s, d):
    return table(s, d, "events").select("event_id", F.expr("shiftleft(1, cast(event_id % 8 as int))").alias("mask"), F.bit_count((F.col("event_id") % 255).cast("int")).alias("ones"))


@query("array_slots", "SELECT n_regionkey, CAST(list_position(list_sort(list(n_nationkey)), max(n_nationkey)) AS BIGINT) AS slot, CAST(list_sum(list(n_nationkey)) AS BIGINT) AS total, bool_or(n_nationkey > 20) AS high FROM nation GROUP BY n_regionkey")
def _(s, d):
    bag = table(s, d, "nation").groupBy("n_regionkey").agg(F.sort_array(F.collect_list(F.col("n_nationkey").cast("long"))).alias("bag"))
    return bag.select("n_regionkey", F.expr("array_position(bag, array_max(bag))").alias("slot"), F.aggregate("bag", F.lit(0).cast("long"), lambda a, x: a + x).alias("total"), F.exists("bag", lambda x: x > 20).alias("high"))


@query("array_intersect", "WITH z AS (SELECT count(*) AS n FROM nation), r AS (SELECT n_nationkey AS a, (n_nationkey + 1) % n AS b FROM nation, z UNION ALL SELECT (n_nationkey + 1) % n, n_nationkey FROM nation, z) SELECT x.a AS u, y.a AS v, count(*) AS common FROM r x JOIN r y ON x.b = y.b AND x.a < y.a GROUP BY ALL")
def _(s, d):
    a = G.nation_ring(s, d).arcs
    nb = a.groupBy("src").agg(F.collect_set("dst").alias("nb"))
    two = a.join(a.select(F.col("src").alias("dst"), F.col("dst").alias("far")), "dst").where("src < far").select(F.col("src").alias("u"), F.col("far").alias("v")).distinct()
    j = two.join(nb.select(F.col("src").alias("u"), F.col("nb").alias("nu")), "u").join(nb.select(F.col("src").alias("v"), F.col("nb").alias("nv")), "v").where(F.arrays_overlap("nu", "nv"))
    return j.select(F.col("u").cast("int").alias("u"), F.col("v").cast("int").alias("v"), F.size(F.array_intersect("nu", "nv")).cast("long").alias("common"))


@query("map_mapping", "SELECT n_regionkey, slot, CAST(n AS INTEGER) AS nation FROM (SELECT n_regionkey, CAST(row_number() OVER (PARTITION BY n_regionkey ORDER BY n_nationkey) - 1 AS INTEGER) AS slot, n_nationkey AS n FROM nation)")
def _(s, d):
    bag = table(s, d, "nation").groupBy("n_regionkey").agg(F.sort_array(F.collect_list("n_nationkey")).alias("bag"))
    m = bag.select("n_regionkey", F.map_from_arrays(F.sequence(F.lit(0), F.size("bag") - 1), "bag").alias("m"))
    return m.select("n_regionkey", F.explode(F.map_entries("m")).alias("e")).select("n_regionkey", F.col("e.key").alias("slot"), F.col("e.value").alias("nation"))


@query("json_props_label", "SELECT CAST(json_extract_string(props, '$.k') AS INTEGER) AS k, count(*) AS n FROM events GROUP BY 1")
def _(s, d):
    return table(s, d, "events").groupBy(F.get_json_object("props", "$.k").cast("int").alias("k")).agg(F.count("*").alias("n"))


@query("recursive_reach", "WITH z AS (SELECT count(*) AS n FROM nation) SELECT CAST(n_nationkey AS BIGINT) AS id, CAST(least(n_nationkey, n - n_nationkey) AS INTEGER) AS level FROM nation, z")
def _(s, d):
    g = G.nation_ring(s, d)
    return s.sql("""WITH RECURSIVE w(id, level) AS (SELECT CAST(0 AS BIGINT), 0 UNION ALL SELECT a.dst, w.level + 1 FROM w JOIN {arcs} a ON a.src = w.id WHERE w.level < 12)
        SELECT id, min(level) AS level FROM w GROUP BY id""", arcs=g.arcs)


@query("subquery_scalar_exists", "SELECT o_orderkey FROM orders o WHERE o_totalprice > 1.5 * (SELECT avg(o_totalprice) FROM orders) AND EXISTS (SELECT 1 FROM lineitem WHERE l_orderkey = o_orderkey AND l_quantity > 45)")
def _(s, d):
    return s.sql("SELECT o_orderkey FROM {o} WHERE o_totalprice > 1.5 * (SELECT avg(o_totalprice) FROM {o}) AND EXISTS (SELECT 1 FROM {l} l WHERE l.l_orderkey = o_orderkey AND l.l_quantity > 45)", o=table(s, d, "orders"), l=table(s, d, "lineitem"))


@query("udf_decode", "SELECT id, CASE WHEN id % 5 >= 2 THEN id % 5 - 2 ELSE -1 - id % 5 END AS d0, CASE WHEN id // 5 % 5 >= 2 THEN id // 5 % 5 - 2 ELSE -1 - id // 5 % 5 END AS d1 FROM (SELECT CAST(n_nationkey AS INTEGER) AS id FROM nation)")
def _(s, d):
    n = table(s, d, "nation").select(F.col("n_nationkey").cast("int").alias("id"))
    got = n.select("id", udfs.decode_match(F.col("id").cast("long"), F.lit(2), F.lit(5)).alias("m"))
    return got.select("id", F.get("m", F.lit(0)).alias("d0"), F.get("m", F.lit(1)).alias("d1"))


@query("udtf_cycle_edges", "WITH z AS (SELECT count(*) AS n FROM nation) SELECT CAST(least(n_nationkey, (n_nationkey + 1) % n) AS BIGINT) AS src, CAST(greatest(n_nationkey, (n_nationkey + 1) % n) AS BIGINT) AS dst FROM nation, z")
def _(s, d):
    udfs.register(s)
    return s.sql(f"SELECT src, dst FROM ring_edges({table(s, d, 'nation').count()})")


@query("cogroup_piece", "SELECT conv_id, count(*) AS turns, count(*) - 1 AS steps FROM conversations GROUP BY conv_id HAVING count(*) = max(turn) + 1 UNION ALL SELECT conv_id, count(*), (SELECT count(*) FROM conversations a JOIN conversations b ON a.conv_id = b.conv_id AND b.turn = a.turn + 1 WHERE a.conv_id = c.conv_id) FROM conversations c GROUP BY conv_id HAVING count(*) <> max(turn) + 1")
def _(s, d):
    c = table(s, d, "conversations").select("conv_id", "turn")
    nxt = c.select("conv_id", (F.col("turn") - 1).alias("turn"))
    steps = c.join(nxt, ["conv_id", "turn"]).select(F.col("conv_id").alias("conv"), F.col("turn").alias("at"))

    def sizes(v: pa.Table, e: pa.Table) -> pa.Table:
        return pa.table({"conv_id": v["conv_id"].slice(0, 1), "turns": pa.array([v.num_rows], pa.int64()), "steps": pa.array([e.num_rows], pa.int64())})

    return c.groupBy("conv_id").cogroup(steps.groupBy("conv")).applyInArrow(sizes, "conv_id long, turns long, steps long")


@query("sql_find_pattern", "WITH z AS (SELECT count(*) AS n FROM nation), e AS (SELECT n_nationkey AS a, (n_nationkey + 1) % n AS b FROM nation, z) SELECT CAST(count(*) AS BIGINT) AS wedges FROM (SELECT x.a FROM e x JOIN e y ON x.b = y.a)")
def _(s, d):
    G.nation_ring(s, d).edges.createOrReplaceTempView("coverdp_edges")
    return udfs.find_pattern(s, "coverdp_edges", "a-b, b-c").agg(F.count("*").alias("wedges"))


@query(
    "join_theta_gabriel",
    """WITH p AS (SELECT vec_id AS id, CAST(embedding[1] AS DOUBLE) AS x, CAST(embedding[2] AS DOUBLE) AS y FROM embeddings)
    SELECT a.id AS src, b.id AS dst FROM p a JOIN p b ON a.id < b.id WHERE NOT EXISTS (SELECT 1 FROM p r WHERE r.id <> a.id AND r.id <> b.id AND (r.x - a.x) * (r.x - b.x) + (r.y - a.y) * (r.y - b.y) < 0)""",
)
def _(s, d):
    """Pairs in whose disc no third point lies: a theta join and an anti-join without an equality. Their sides are points, few by a check."""
    p = table(s, d, "embeddings").select(F.col("vec_id").alias("id"), F.get("embedding", F.lit(0)).cast("double").alias("x"), F.get("embedding", F.lit(1)).cast("double").alias("y"))
    if p.count() > THETA_POINTS:
        raise ValueError(f"more than {THETA_POINTS} points: see the proximity graphs in coverdp.sources.graphs")
    a, b, r = (p.select(*(F.col(c).alias(f"{n}_{c}") for c in ("id", "x", "y"))) for n in "abr")
    pairs = a.join(F.broadcast(b), F.col("a_id") < F.col("b_id"))
    dot = sum(((F.col(f"r_{c}") - F.col(f"a_{c}")) * (F.col(f"r_{c}") - F.col(f"b_{c}")) for c in ("x", "y")), F.lit(0.0))
    free = pairs.join(F.broadcast(r), (F.col("r_id") != F.col("a_id")) & (F.col("r_id") != F.col("b_id")) & (dot < 0), "left_anti")
    return free.select(F.col("a_id").alias("src"), F.col("b_id").alias("dst"))
