"""Streaming queries with their batch twins as SQL."""

from __future__ import annotations

from pyspark.sql import functions as F

from paircuration.operators import dedup
from paircuration.plans import oracle_parts as P
from paircuration.sources.scratch import fresh, settle
from paircuration.sources.tables import as_timestamp, load
from paircuration.streaming import jobs

QUERIES, ORACLES = {}, {}


def query(name: str, sql: str | None = None):
    def keep(fn):
        QUERIES[name] = fn
        if sql:
            ORACLES[name] = sql
        return fn
    return keep


_AGG = "event_type, count(*) AS n, round(sum(value), 6) AS total"


@query("stream_tumbling", f"SELECT time_bucket(INTERVAL 1 HOUR, ts) AS start, time_bucket(INTERVAL 1 HOUR, ts) + INTERVAL 1 HOUR AS \"end\", {_AGG} FROM events GROUP BY ALL")
def stream_tumbling(spark, sf):
    return jobs.flat(jobs.run_complete(jobs.windowed(jobs.source(spark, sf, "events"), F.window("ts", "1 hour")), "tumbling"))


@query("stream_sliding", f"SELECT s AS start, s + INTERVAL 2 HOUR AS \"end\", {_AGG} FROM (SELECT *, time_bucket(INTERVAL 1 HOUR, ts) - to_hours(k) AS s FROM events, (SELECT unnest([0, 1]) AS k)) GROUP BY ALL")
def stream_sliding(spark, sf):
    return jobs.flat(jobs.run_complete(jobs.windowed(jobs.source(spark, sf, "events"), F.window("ts", "2 hours", "1 hour")), "sliding"))


_SESSION = """SELECT min(ts) AS start, max(ts) + INTERVAL 30 MINUTE AS "end", user_id, count(*) AS n FROM (
SELECT *, sum(fresh) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS UNBOUNDED PRECEDING) AS s FROM (
SELECT *, CASE WHEN ts - lag(ts) OVER (PARTITION BY user_id ORDER BY ts, event_id) < INTERVAL 30 MINUTE THEN 0 ELSE 1 END AS fresh FROM events)) GROUP BY user_id, s"""


@query("stream_session", _SESSION)
def stream_session(spark, sf):
    return jobs.flat(jobs.run_complete(jobs.sessions(jobs.source(spark, sf, "events")), "session"))


@query("session_batch", _SESSION)
def session_batch(spark, sf):
    events = as_timestamp(load(spark, sf, "events"), "ts")
    return jobs.flat(events.groupBy(F.session_window("ts", "30 minutes").alias("w"), "user_id").agg(F.count(F.lit(1)).alias("n")))


@query("stream_late_drop", "SELECT time_bucket(INTERVAL 1 DAY, ts) AS start, count(*) AS n FROM events GROUP BY 1 HAVING time_bucket(INTERVAL 1 DAY, ts) + INTERVAL 1 DAY <= (SELECT max(ts) - INTERVAL 10 MINUTE FROM events)")
def stream_late_drop(spark, sf):
    """Append mode: a day is stored once the watermark has passed its end, and never changed again."""
    days = jobs.source(spark, sf, "events").withWatermark("ts", "10 minutes").groupBy(F.window("ts", "1 day").alias("w")).agg(F.count(F.lit(1)).alias("n"))
    return jobs.run_append(days, "days").select(F.col("w.start").cast("timestamp_ntz").alias("start"), "n")


@query("stream_dedup", "SELECT DISTINCT user_id, event_type FROM events")
def stream_dedup(spark, sf):
    return jobs.run_append(jobs.source(spark, sf, "events").select("user_id", "event_type").dropDuplicates(["user_id", "event_type"]), "dedup")


@query("stream_dedup_watermark", "SELECT DISTINCT event_id FROM events")
def stream_dedup_watermark(spark, sf):
    events = jobs.source(spark, sf, "events").withWatermark("ts", "1 hour").dropDuplicatesWithinWatermark(["event_id"])
    return jobs.run_append(events.select("event_id"), "dedup-watermark")


@query("stream_static_join", "SELECT event_id, c_mktsegment FROM events JOIN customer ON user_id = c_custkey")
def stream_static_join(spark, sf):
    customers = load(spark, sf, "customer", ["c_custkey", "c_mktsegment"])
    return jobs.run_append(jobs.source(spark, sf, "events").join(customers, F.col("user_id") == F.col("c_custkey")).select("event_id", "c_mktsegment"), "static")


@query("stream_stream_interval_join", "SELECT a.event_id AS view_id, b.event_id AS purchase_id FROM events a JOIN events b ON a.user_id = b.user_id AND a.event_type = 'view' AND b.event_type = 'purchase' AND b.ts >= a.ts AND b.ts <= a.ts + INTERVAL 1 HOUR")
def stream_stream_interval_join(spark, sf):
    a = jobs.source(spark, sf, "events").filter("event_type = 'view'").withWatermark("ts", "2 hours").select(F.col("event_id").alias("view_id"), F.col("user_id").alias("ua"), F.col("ts").alias("ta"))
    b = jobs.source(spark, sf, "events").filter("event_type = 'purchase'").withWatermark("ts", "2 hours").select(F.col("event_id").alias("purchase_id"), F.col("user_id").alias("ub"), F.col("ts").alias("tb"))
    met = a.join(b, F.expr("ua = ub AND tb >= ta AND tb <= ta + interval 1 hour"))
    return jobs.run_append(met.select("view_id", "purchase_id"), "interval")


@query("stream_stateful", "SELECT user_id, count(*) AS n, round(sum(value), 6) AS total FROM events GROUP BY user_id")
def stream_stateful(spark, sf):
    path = fresh(spark, "stateful")
    stored = jobs._each(jobs.running_totals(jobs.source(spark, sf, "events")), path, "update", lambda df, i: df.withColumn("batch", F.lit(i)).write.mode("append").parquet(path))
    rows = spark.read.parquet(path)
    return rows.groupBy("user_id").agg(*[F.max_by(c, "batch").alias(c) for c in stored.columns if c != "user_id"])


_NEAR = [*P.exact("documents", "firsts", "doc_id", P.COLLAPSE.format("text")), *P.near("firsts", "doc_id", "text"), *P.edges("exact"), *P.greedy()]


@query("stream_near_dedup", P.statement(_NEAR, "SELECT doc_id FROM firsts WHERE doc_id NOT IN (SELECT id FROM verdicts WHERE NOT kept)"))
def stream_near_dedup(spark, sf):
    """Documents in four chunks by id through a file stream; the kept rows equal those of the one-pass batch."""
    docs = load(spark, sf, "documents", ["doc_id", "text"])
    first = settle(dedup.exact(docs, F.trim(F.regexp_replace("text", "[ \t\n\r]+", " ")), ["doc_id"]), "firsts")
    top = docs.agg(F.max("doc_id")).first()[0] or 0
    path, index = fresh(spark, "chunks"), fresh(spark, "near-index")
    for i in range(4):  # each chunk arrives and is worked off by a job of its own, which finds the index in its folder
        first.filter((F.col("doc_id") * 4 >= i * (top + 1)) & (F.col("doc_id") * 4 < (i + 1) * (top + 1))).write.mode("append").parquet(path)
        stream = spark.readStream.schema(docs.schema).parquet(path)
        state = jobs.NearDedupStream(spark, folder=index)
        job = stream.writeStream.option("checkpointLocation", f"{path}-state").foreachBatch(lambda df, n, state=state: state.step(df, n) and None).trigger(availableNow=True).start()
        job.awaitTermination()
    return state.kept().select("doc_id")
