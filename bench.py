"""Headline queries at $BENCH_SF_DIR on local[$BENCH_CPUS]: one JSON line."""

from __future__ import annotations

import json
import os
import sys
import time

from pyspark.sql import SparkSession

from coverdp import catalog
from coverdp import patterns as P
from coverdp.operators import search
from coverdp.sources import graphs

HEADLINE = ("lattice_edges", "list_c4_gabriel", "decide_triangle_lattice", "list_triangles_join_baseline", "cluster_partition", "layer_numbers_hierarchy", "vertex_face_graph_lattice", "funnel_paths_events", "op_agg_degree_histogram", "op_join_interval_events")


def main() -> None:
    d, cpus = os.environ.get("BENCH_SF_DIR", "/root/testdata/sf0.1"), os.environ.get("BENCH_CPUS", "8")
    spark = (
        SparkSession.builder.master(f"local[{cpus}]")
        .config("spark.sql.shuffle.partitions", cpus)
        .config("spark.driver.memory", os.environ.get("BENCH_MEMORY", "12g"))
        .config("spark.ui.enabled", "false")
        .config("spark.sql.session.timeZone", "UTC")
        .getOrCreate()
    )
    spark.sparkContext.setLogLevel("ERROR")
    names = sys.argv[1:] or HEADLINE
    took: dict[str, float] = {}
    for name in names:
        began = time.time()
        catalog.queries()[name](spark, d).write.format("noop").mode("overwrite").save()
        took[name] = round(time.time() - began, 3)
        print(f"{name} {took[name]}", file=sys.stderr, flush=True)
    if not sys.argv[1:]:
        # work against n: one repetition's windows solved, vertices a second
        g = catalog.fixed(graphs.order_lattice_graph(spark, d))
        began = time.time()
        search.find(g, P.clique(4), confidence=1 / 17)
        took["one_repetition_clique4"] = round(time.time() - began, 3)
    print(json.dumps({"metric": "total_seconds", "value": round(sum(took.values()), 3), "unit": "sec", "queries": took, "sf": os.path.basename(d.rstrip("/"))}))


if __name__ == "__main__":
    main()
