"""Streaming queries and their batch twins."""

from __future__ import annotations

from pyspark.sql import functions as F

from dupflow.registry import query, table
from dupflow.shared import shared_path
from dupflow.streaming import jobs


def _events(spark, sf):
    return table(spark, sf, "events").withColumn("ts", F.col("ts").cast("timestamp")).withColumn("cents", F.expr("cast(round(value * 100) as bigint)"))


_S = lambda c: F.date_format(c, "yyyy-MM-dd HH:mm:ss")
_HOUR = "SELECT strftime(time_bucket(INTERVAL 6 HOUR, ts), '%Y-%m-%d %H:%M:%S') AS start, event_type, count(*) AS n, sum(round(value * 100)::BIGINT)::BIGINT AS cents FROM events GROUP BY 1, 2"


@query(_HOUR)
def sw_tumbling(spark, sf):
    return _events(spark, sf).groupBy(F.window("ts", "6 hours").alias("w"), "event_type").agg(F.count("*").alias("n"), F.sum("cents").alias("cents")).select(_S(F.col("w.start")).alias("start"), "event_type", "n", "cents")


@query(_HOUR)
def st_tumbling(spark, sf):
    """The same windows by a stream in complete mode."""
    s = jobs.event_stream(spark, sf).withColumn("cents", F.expr("cast(round(value * 100) as bigint)"))
    agg = s.groupBy(F.window("ts", "6 hours").alias("w"), "event_type").agg(F.count("*").alias("n"), F.sum("cents").alias("cents"))
    return jobs.drain(agg.select(F.col("w.start").alias("start"), "event_type", "n", "cents"), "complete").select(_S(F.col("start")).alias("start"), "event_type", "n", "cents")


@query("SELECT strftime(s, '%Y-%m-%d %H:%M:%S') AS start, count(*) AS n FROM (SELECT unnest([time_bucket(INTERVAL 6 HOUR, ts), time_bucket(INTERVAL 6 HOUR, ts) - INTERVAL 6 HOUR]) AS s FROM events) GROUP BY 1")
def sw_sliding(spark, sf):
    return _events(spark, sf).groupBy(F.window("ts", "12 hours", "6 hours").alias("w")).agg(F.count("*").alias("n")).select(_S(F.col("w.start")).alias("start"), "n")


@query("""WITH g AS (SELECT user_id, ts, CASE WHEN ts < lag(ts) OVER (PARTITION BY user_id ORDER BY ts) + INTERVAL 2 HOUR THEN 0 ELSE 1 END AS new FROM events),
s AS (SELECT *, sum(new) OVER (PARTITION BY user_id ORDER BY ts ROWS UNBOUNDED PRECEDING) AS k FROM g)
SELECT user_id, strftime(min(ts), '%Y-%m-%d %H:%M:%S') AS start, count(*) AS n FROM s GROUP BY user_id, k""")
def sw_session(spark, sf):
    return _events(spark, sf).groupBy("user_id", F.session_window("ts", "2 hours").alias("w")).agg(F.count("*").alias("n")).select("user_id", _S(F.col("w.start")).alias("start"), "n")


@query("SELECT count(DISTINCT (user_id, event_type)) AS n FROM events")
def st_dedup(spark, sf):
    return jobs.drain(jobs.event_stream(spark, sf).select("user_id", "event_type").dropDuplicates(["user_id", "event_type"])).agg(F.count("*").alias("n"))


@query()
def st_first_seen(spark, sf):
    """First of each key within the watermark."""
    return jobs.drain(jobs.first_seen(jobs.event_stream(spark, sf).select("ts", "event_id", "user_id", "event_type"), ["user_id", "event_type"])).select("event_id", "user_id", "event_type")


@query("SELECT strftime(start, '%Y-%m-%d %H:%M:%S') AS start, n FROM (SELECT time_bucket(INTERVAL 6 HOUR, ts, TIMESTAMP '1970-01-01') AS start, count(*) AS n FROM events GROUP BY 1) WHERE start + INTERVAL 6 HOUR <= (SELECT max(ts) - INTERVAL 1 HOUR FROM events)")
def st_watermark(spark, sf):
    """Windows that the watermark has closed."""
    s = jobs.event_stream(spark, sf).withWatermark("ts", "1 hour")
    agg = s.groupBy(F.window("ts", "6 hours").alias("w")).agg(F.count("*").alias("n"))
    return jobs.drain(agg.select(F.col("w.start").alias("start"), "n")).select(_S(F.col("start")).alias("start"), "n")


@query()
def st_state_mark(spark, sf):
    """Best of each key by a stateful processor with timers; keys still open at the end are not yet told."""
    conf = "spark.sql.streaming.stateStore.providerClass"
    before = spark.conf.get(conf)
    spark.conf.set(conf, "org.apache.spark.sql.execution.streaming.state.RocksDBStateStoreProvider")
    try:
        return jobs.drain(jobs.best_of_set(jobs.event_stream(spark, sf)))
    finally:
        spark.conf.set(conf, before)


@query("SELECT c.event_id AS click_id, p.event_id AS purchase_id FROM events c JOIN events p ON c.user_id = p.user_id AND c.event_type = 'click' AND p.event_type = 'purchase' AND p.ts BETWEEN c.ts AND c.ts + INTERVAL 1 HOUR")
def st_ss_join(spark, sf):
    """Click to purchase within an hour: an inner interval join of two streams."""
    s = jobs.event_stream(spark, sf)
    c = s.where("event_type = 'click'").select(F.col("event_id").alias("click_id"), F.col("user_id").alias("cu"), F.col("ts").alias("cts")).withWatermark("cts", "1 hour")
    p = s.where("event_type = 'purchase'").select(F.col("event_id").alias("purchase_id"), F.col("user_id").alias("pu"), F.col("ts").alias("pts")).withWatermark("pts", "1 hour")
    return jobs.drain(c.join(p, F.expr("cu = pu AND pts >= cts AND pts <= cts + INTERVAL 1 HOUR")).select("click_id", "purchase_id"))


@query("SELECT event_id, user_id, event_type FROM events WHERE event_type = 'click' AND value > 50")
def st_filter(spark, sf):
    """Filter-only streaming conversion: no pool, no shuffle."""
    return jobs.drain(jobs.event_stream(spark, sf).where("event_type = 'click' and value > 50").select("event_id", "user_id", "event_type"))


@query("SELECT user_id, event_type, min(event_id) AS first_id FROM events GROUP BY 1, 2")
def batch_dedup(spark, sf):
    """Batch twin of the streaming first-seen rule."""
    return table(spark, sf, "events").groupBy("user_id", "event_type").agg(F.min("event_id").alias("first_id"))


@query("SELECT CASE WHEN l_returnflag = 'A' THEN 1 ELSE 0 END AS is_a, count(*) AS n FROM lineitem GROUP BY 1")
def st_filter_to_baf(spark, sf):
    """A text stream of alignment lines filtered into block files batch by batch, counted from the files."""
    from dupflow.fixtures import alignments
    from dupflow.sources import baf, taf

    src, out = shared_path(spark, "taf-stream"), shared_path(spark, "baf-stream")
    a = alignments(spark, sf).where("flag & 64 <> 0 and flag & 256 = 0")
    a.select(F.concat_ws("\x01", F.col("seq").cast("string"), "lib", taf.render_line()).alias("value")).write.text(src)
    s = spark.readStream.text(src).select(F.split("value", "\x01", 3).alias("p"))
    made: list[str] = []

    def sink(batch, number):
        lines = batch.select(F.col("seq"), "lib", "value")
        records = taf.parse_taf(lines, keep=["seq", "lib"]).drop("_corrupt")
        made.append(f"{out}/batch-{number}")
        baf.write_baf(records, made[-1])

    jobs.drain(s.select(F.col("p")[0].cast("decimal(38,0)").alias("seq"), F.col("p")[1].alias("lib"), F.col("p")[2].alias("value")), sink=sink)
    total = None
    for path in made:
        r = baf.read_baf(spark, path).select("lib")
        total = r if total is None else total.unionAll(r)
    return total.groupBy(F.when(F.col("lib") == "A", 1).otherwise(0).alias("is_a")).agg(F.count("*").alias("n"))
