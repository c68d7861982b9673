"""Streams of events: windows, sessions, joins, and a pattern matcher whose state is a path's program."""

from __future__ import annotations

import uuid
from collections.abc import Callable, Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from coverdp.runtime import shared_folder, ship, table

QUERIES: dict[str, Callable[[SparkSession, str], DataFrame]] = {}
ORACLES: dict[str, str] = {}


def query(name: str, sql: str | None = None):
    def put(f):
        QUERIES[name] = f
        if sql:
            ORACLES[name] = sql
        return f

    return put


def event_stream(spark: SparkSession, d: str) -> DataFrame:
    """The events table as a stream of files."""
    ship(spark)
    schema = spark.read.parquet(f"{d}/events.parquet").schema
    path = f"{d}/events.parquet"
    # a file source watches a folder: one file is named by a pattern
    return spark.readStream.schema(schema).option("pathGlobFilter", "*events*" if _is_file(spark, path) else "*.parquet").parquet(d if _is_file(spark, path) else path)


def timed(events: DataFrame) -> DataFrame:
    """Watermarks need timestamps of the session's time zone."""
    return events.withColumn("ts", F.col("ts").cast("timestamp"))


def _is_file(spark: SparkSession, path: str) -> bool:
    p = spark._jvm.org.apache.hadoop.fs.Path(path)
    return p.getFileSystem(spark._jsc.hadoopConfiguration()).getFileStatus(p).isFile()


def drain(df: DataFrame, mode: str = "complete") -> DataFrame:
    """Run a stream over what there is and give its result as a table. Files in the shared folder hold it, for append; else memory does."""
    spark = df.sparkSession
    tag = uuid.uuid4().hex
    base = f"{shared_folder(spark)}/coverdp-stream-{tag}"
    w = df.writeStream.outputMode(mode).option("checkpointLocation", f"{base}/state").trigger(availableNow=True)
    if mode == "append":
        q = w.format("parquet").option("path", f"{base}/out").start()
    else:
        q = w.format("memory").queryName(f"s{tag}").start()
    q.awaitTermination()
    if q.exception():
        raise q.exception()
    return spark.read.schema(df.schema).parquet(f"{base}/out") if mode == "append" else spark.table(f"s{tag}")


@query("op_stream_tumbling_counts", "SELECT CAST(date_trunc('day', ts) AS TIMESTAMP) AS start, event_type, count(*) AS n FROM events GROUP BY ALL")
def _tumbling(s, d):
    return drain(event_stream(s, d).groupBy(F.window("ts", "1 day"), "event_type").agg(F.count("*").alias("n")).select(F.col("window.start").alias("start"), "event_type", "n"))


@query("op_stream_sliding_counts", "SELECT CAST(date_trunc('day', ts) - to_days(CAST(i AS INTEGER)) AS TIMESTAMP) AS start, count(*) AS n FROM events, (SELECT unnest(range(0, 2)) AS i) GROUP BY ALL")
def _sliding(s, d):
    return drain(event_stream(s, d).groupBy(F.window("ts", "2 days", "1 day")).agg(F.count("*").alias("n")).select(F.col("window.start").alias("start"), "n"))


@query("op_stream_session_counts", """WITH g AS (SELECT user_id, ts, CASE WHEN ts >= lag(ts) OVER w + INTERVAL 6 HOUR OR lag(ts) OVER w IS NULL THEN 1 ELSE 0 END AS new FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts)),
n AS (SELECT user_id, ts, sum(new) OVER (PARTITION BY user_id ORDER BY ts ROWS UNBOUNDED PRECEDING) AS k FROM g) SELECT user_id, min(ts) AS start, count(*) AS n FROM n GROUP BY user_id, k""")
def _sessions(s, d):
    return drain(event_stream(s, d).groupBy("user_id", F.session_window("ts", "6 hours")).agg(F.count("*").alias("n")).select("user_id", F.col("session_window.start").alias("start"), "n"))


@query("op_stream_dedup", "SELECT count(DISTINCT event_id) AS n FROM events")
def _dedup(s, d):
    twice = timed(event_stream(s, d)).withColumn("copy", F.explode(F.array(F.lit(1), F.lit(2))))
    return drain(twice.withWatermark("ts", "10 days").dropDuplicatesWithinWatermark(["event_id"]).select("event_id"), "append").agg(F.count("*").alias("n"))


@query("op_stream_static_join", "SELECT event_id, c_mktsegment FROM events JOIN customer ON c_custkey = user_id")
def _static(s, d):
    c = table(s, d, "customer").select(F.col("c_custkey").alias("user_id"), "c_mktsegment")
    return drain(event_stream(s, d).join(c, "user_id").select("event_id", "c_mktsegment"), "append")


@query("op_stream_interval_join", "SELECT a.event_id AS view_id, b.event_id AS purchase_id FROM events a JOIN events b ON a.user_id = b.user_id AND a.event_type = 'view' AND b.event_type = 'purchase' AND b.ts >= a.ts AND b.ts <= a.ts + INTERVAL 1 DAY")
def _interval(s, d):
    a = timed(event_stream(s, d)).where("event_type = 'view'").select(F.col("event_id").alias("view_id"), F.col("user_id").alias("u"), F.col("ts").alias("t")).withWatermark("t", "2 days")
    b = timed(event_stream(s, d)).where("event_type = 'purchase'").select(F.col("event_id").alias("purchase_id"), "user_id", "ts").withWatermark("ts", "2 days")
    return drain(a.join(b, F.expr("u = user_id and ts >= t and ts <= t + interval 1 day")).select("view_id", "purchase_id"), "append")


@query("op_stream_late_rows")
def _late(s, d):
    return drain(timed(event_stream(s, d)).withWatermark("ts", "1 day").groupBy(F.window("ts", "1 day")).agg(F.count("*").alias("n")).select(F.col("window.start").alias("start"), "n"), "update")


def funnel_matcher(events: DataFrame, labels: tuple[str, ...]) -> DataFrame:
    """first, last (event ids) of consecutive events of a user with these labels. Rows of a batch are put in the order of time; the state is the user's last events, as many as the labels less one."""
    k = len(labels)

    def step(key: tuple, batches: Iterator[pd.DataFrame], state) -> Iterator[pd.DataFrame]:
        rows = pd.concat(list(batches)).sort_values(["ts", "event_id"])
        ids, kinds = (list(state.get[0]), list(state.get[1])) if state.exists else ([], [])
        first, last = [], []
        for i, kind in zip(rows["event_id"].tolist(), rows["event_type"].tolist(), strict=True):
            ids, kinds = [*ids, i][-k:], [*kinds, kind][-k:]
            if tuple(kinds) == labels:
                first.append(ids[0]), last.append(ids[-1])
        state.update((ids[-(k - 1) :] if k > 1 else [], kinds[-(k - 1) :] if k > 1 else []))
        yield pd.DataFrame({"first": first, "last": last})

    return events.select("user_id", "ts", "event_id", "event_type").groupBy("user_id").applyInPandasWithState(step, "first long, last long", "ids array<long>, kinds array<string>", "append", "NoTimeout")


@query("op_stream_funnel", """WITH c AS (SELECT event_id AS a, event_type AS t, lead(event_type) OVER w AS t2, lead(event_id, 2) OVER w AS c, lead(event_type, 2) OVER w AS t3 FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id))
SELECT a AS first, c AS last FROM c WHERE t = 'view' AND t2 = 'click' AND t3 = 'purchase'""")
def _funnel(s, d):
    return drain(funnel_matcher(event_stream(s, d), ("view", "click", "purchase")), "append")
