"""Stream queries over ``events``: each drains the stream, so its oracle is the batch question."""

from __future__ import annotations

from pyspark.sql import functions as F

from capbuckets.plans.method_queries import brute, with_caps
from capbuckets.plans.registry import Registry
from capbuckets.sources.microdata import table
from capbuckets.streaming import events as S
from capbuckets.streaming.events import event_stream, run_available, stream_histogram

query = Registry()


def _stamp(c):
    return F.date_format(c, "yyyy-MM-dd HH:mm")


@query("SELECT strftime(time_bucket(INTERVAL 1 HOUR, ts), '%Y-%m-%d %H:%M') AS start, event_type, count(*)::BIGINT AS n FROM events GROUP BY ALL")
def st_tumbling(spark, sf):
    s = event_stream(spark, sf).groupBy(F.window("ts", "1 hour"), "event_type").agg(F.count(F.lit(1)).alias("n"))
    return run_available(s, "complete").select(_stamp("window.start").alias("start"), "event_type", "n")


@query("SELECT strftime(time_bucket(INTERVAL 30 MINUTE, ts) - i * INTERVAL 30 MINUTE, '%Y-%m-%d %H:%M') AS start, count(*)::BIGINT AS n FROM events, range(2) r(i) GROUP BY ALL")
def st_sliding(spark, sf):
    s = event_stream(spark, sf).groupBy(F.window("ts", "1 hour", "30 minutes")).agg(F.count(F.lit(1)).alias("n"))
    return run_available(s, "complete").select(_stamp("window.start").alias("start"), "n")


@query("""WITH g AS (SELECT user_id, ts, CASE WHEN ts < lag(ts) OVER (PARTITION BY user_id ORDER BY ts) + INTERVAL 6 HOUR THEN 0 ELSE 1 END AS fresh FROM events),
        s AS (SELECT user_id, ts, sum(fresh) OVER (PARTITION BY user_id ORDER BY ts ROWS UNBOUNDED PRECEDING) AS k FROM g)
        SELECT user_id, strftime(min(ts), '%Y-%m-%d %H:%M') AS start, count(*)::BIGINT AS n FROM s GROUP BY user_id, k""")
def st_session(spark, sf):
    s = event_stream(spark, sf).groupBy(F.session_window("ts", "6 hours"), "user_id").agg(F.count(F.lit(1)).alias("n"))
    return run_available(s, "complete").select("user_id", _stamp("session_window.start").alias("start"), "n")


@query("SELECT DISTINCT user_id, event_type FROM events")
def st_dedup(spark, sf):
    s = event_stream(spark, sf).select("user_id", "event_type").dropDuplicates(["user_id", "event_type"])
    return run_available(s)


@query("SELECT event_id FROM events")
def st_dedup_watermark(spark, sf):
    """Repeats of an event within the watermark's delay are dropped; state is kept no longer than that."""
    s = event_stream(spark, sf)
    twice = s.union(s).withWatermark("ts", "31 days").dropDuplicatesWithinWatermark(["event_id"]).select("event_id")
    return run_available(twice)


@query("SELECT event_id, n_name FROM events JOIN nation ON user_id % 25 = n_nationkey")
def st_static_join(spark, sf):
    n = table(spark, sf, "nation").select("n_nationkey", "n_name")
    return run_available(event_stream(spark, sf).join(F.broadcast(n), F.col("user_id") % 25 == F.col("n_nationkey")).select("event_id", "n_name"))


@query("SELECT a.event_id AS first, b.event_id AS second FROM events a JOIN events b ON a.user_id = b.user_id AND b.ts > a.ts AND b.ts <= a.ts + INTERVAL 20 MINUTE")
def st_interval_join(spark, sf):
    a = event_stream(spark, sf).select(F.col("event_id").alias("first"), "user_id", "ts").withWatermark("ts", "1 hour")
    b = event_stream(spark, sf).select(F.col("event_id").alias("second"), F.col("user_id").alias("u"), F.col("ts").alias("t")).withWatermark("t", "1 hour")
    j = a.join(b, F.expr("user_id = u AND t > ts AND t <= ts + INTERVAL 20 MINUTES"))
    return run_available(j.select("first", "second"))


@query("SELECT least(49, floor(value / 4.0))::INTEGER AS v, count(*)::BIGINT AS cnt FROM events GROUP BY v")
def st_histogram(spark, sf):
    return run_available(stream_histogram(event_stream(spark, sf)), "complete")


@query(with_caps("occ50") + brute() + "SELECT loss, true AS feasible FROM best")
def st_policy_monitor(spark, sf):
    """What the monitor of a drained stream said last: the optimum's loss, and whether the policy can be kept."""
    seen = []
    S.policy_monitor(stream_histogram(event_stream(spark, sf)), 8, lambda layout, ok: seen.append((layout.loss, bool(ok)))).awaitTermination()
    return spark.createDataFrame(seen[-1:], "loss bigint, feasible boolean")


@query("SELECT 0::BIGINT AS other_sizes, 0::BIGINT AS over_quota, true AS rows_of_the_stream, true AS once")
def st_bucket_fill(spark, sf):
    """Buckets of six rows filled by a stream: those of another size, values in a bucket more than twice, and whether each row is one of the stream's and in one bucket."""
    key, provider = "spark.sql.streaming.stateStore.providerClass", "org.apache.spark.sql.execution.streaming.state.RocksDBStateStoreProvider"
    before = spark.conf.get(key)
    spark.conf.set(key, provider)  # lists as state need it; it is a setting of the session
    try:
        filled = run_available(S.bucket_fill(event_stream(spark, sf), 6, 2))
    finally:
        spark.conf.set(key, before)
    sizes = filled.groupBy("part", "bucket").agg(F.count(F.lit(1)).alias("n")).agg(F.count_if(F.col("n") != 6).alias("other_sizes"))
    over = filled.groupBy("part", "bucket", "v").agg(F.count(F.lit(1)).alias("n")).agg(F.count_if(F.col("n") > 2).alias("over_quota"))
    ids = filled.agg((F.count(F.lit(1)) == F.count_distinct("event_id")).alias("once"))
    strange = filled.join(table(spark, sf, "events"), "event_id", "left_anti").agg((F.count(F.lit(1)) == 0).alias("rows_of_the_stream"))
    return sizes.crossJoin(over).crossJoin(strange).crossJoin(ids)
