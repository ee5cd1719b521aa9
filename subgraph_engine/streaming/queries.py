"""Bounded runs of the streams, compared with the batch answer."""

from __future__ import annotations

from pyspark.sql import functions as F

from subgraph_engine.streaming import events as ev

QUERIES: dict = {}
ORACLE_SQL: dict[str, str] = {}


def query(name: str, sql: str | None = None):
    def keep(f):
        QUERIES[name] = f
        if sql is not None:
            ORACLE_SQL[name] = sql
        return f

    return keep


def _start(rows):
    return rows.select(F.col("w.start").cast("timestamp_ntz").alias("start"), *(c for c in rows.columns if c != "w"))


@query("stream_tumbling", "SELECT date_trunc('day', ts) AS start, event_type, count(*) AS n FROM events GROUP BY ALL")
def stream_tumbling(spark, d):
    return _start(ev.run_to_end(spark, ev.tumbling(ev.event_stream(spark, ev.staged(spark, d))), "complete"))


@query("stream_sliding", "SELECT date_trunc('day', ts) - to_days(k) AS start, event_type, count(*) AS n FROM events, (VALUES (0), (1)) t(k) GROUP BY ALL")
def stream_sliding(spark, d):
    return _start(ev.run_to_end(spark, ev.sliding(ev.event_stream(spark, ev.staged(spark, d))), "complete"))


@query(
    "stream_session",
    """SELECT user_id, min(ts) AS start, count(*) AS n FROM (
  SELECT *, sum(CASE WHEN gap THEN 1 ELSE 0 END) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS s FROM (
    SELECT *, coalesce(ts >= lag(ts) OVER (PARTITION BY user_id ORDER BY ts, event_id) + INTERVAL 6 HOUR, true) AS gap FROM events))
GROUP BY user_id, s""",
)
def stream_session(spark, d):
    return _start(ev.run_to_end(spark, ev.sessions(ev.event_stream(spark, ev.staged(spark, d))), "complete"))


@query("stream_dedup", "SELECT DISTINCT event_id, user_id FROM events")
def stream_dedup(spark, d):
    """Every event twice in the input, once in the output."""
    folder = ev.staged(spark, d)
    twice = ev.event_stream(spark, folder)
    twice = twice.withColumn("copy", F.explode(F.array(F.lit(0), F.lit(1))))
    return ev.run_to_end(spark, ev.without_repeats(twice)).select("event_id", "user_id")


@query("stream_static_join", "SELECT event_id, c_name FROM events JOIN customer ON user_id = c_custkey")
def stream_static_join(spark, d):
    customers = spark.read.parquet(f"{d}/customer.parquet").select("c_custkey", "c_name")
    return ev.run_to_end(spark, ev.with_customers(ev.event_stream(spark, ev.staged(spark, d)), customers).select("event_id", "c_name"))


@query(
    "stream_stream_join",
    """SELECT a.event_id AS click, b.event_id AS buy FROM events a JOIN events b
ON a.user_id = b.user_id AND a.event_type = 'click' AND b.event_type = 'purchase' AND b.ts >= a.ts AND b.ts <= a.ts + INTERVAL 1 HOUR""",
)
def stream_stream_join(spark, d):
    return ev.run_to_end(spark, ev.click_then_purchase(ev.event_stream(spark, ev.staged(spark, d)), delay=ev.GENEROUS))


@query("stream_last_event", "SELECT user_id, max_by(event_id, (ts, event_id)) AS event_id, count(*) AS n FROM events GROUP BY 1")
def stream_last_event(spark, d):
    changes = _updates(spark, ev.last_events(ev.event_stream(spark, ev.staged(spark, d))))
    return changes.groupBy("user_id").agg(F.max_by("event_id", "n").alias("event_id"), F.max("n").alias("n"))


def _updates(spark, rows):
    """All updates of a stream, appended batch by batch."""
    out, state = ev.shared_path(spark, "stream-out"), ev.shared_path(spark, "stream-state")
    stream = rows.writeStream.outputMode("update").option("checkpointLocation", state).trigger(availableNow=True)
    stream.foreachBatch(lambda batch, _: batch.write.mode("append").parquet(out)).start().awaitTermination()
    return spark.read.parquet(out)


@query(
    "stream_incremental_wcc",
    """WITH RECURSIVE e AS (SELECT DISTINCT user_id * 2 AS src, day * 2 + 1 AS dst FROM (SELECT user_id, epoch_us(ts) // 86400000000 AS day FROM events)),
a AS (SELECT * FROM e UNION ALL SELECT dst, src FROM e), v AS (SELECT DISTINCT src AS vid FROM a),
w(id, l) USING KEY (id) AS (SELECT vid, vid FROM v UNION
  SELECT a.dst, min(w.l) FROM w JOIN a ON a.src = w.id JOIN recurring.w r ON r.id = a.dst GROUP BY a.dst HAVING min(w.l) < any_value(r.l))
SELECT id AS vid, l AS component FROM w""",
)
def stream_incremental_wcc(spark, d):
    """Users and the days on which they did anything: components grow with the files."""
    rows = ev.event_stream(spark, ev.staged(spark, d, 9)).select("user_id", F.expr("unix_micros(ts) div 86400000000").alias("day"))
    edges = rows.select((F.col("user_id") * 2).alias("src"), (F.col("day") * 2 + 1).alias("dst"))
    return ev.GrowingComponents(spark).follow(edges)
