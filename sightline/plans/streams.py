"""Streaming queries, each run over what is there and returned as rows."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..catalog import query
from ..sources.scenes import detections
from ..stream import windows as w

_STAMP = "strftime({}, '%Y-%m-%d %H')"
_LAST = "(SELECT max(ts) - INTERVAL 1 HOUR AS bound FROM events)"


def _start(column: str) -> F.Column:
    return F.date_format(F.col(column), "yyyy-MM-dd HH")


@query(f"SELECT {_STAMP.format('day')} AS start, n FROM (SELECT date_trunc('day', ts) AS day, count(*) AS n FROM events GROUP BY 1), {_LAST} WHERE day + INTERVAL 1 DAY <= bound")
def stream_tumbling(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Daily counts of closed windows; the open last one is not emitted."""
    return w.drained(w.tumbling(w.events(spark, sf_dir))).select(_start("window.start").alias("start"), "n")


@query(f"""WITH h AS (SELECT date_trunc('hour', ts) AS h FROM events), s AS (SELECT h - k * INTERVAL 1 HOUR AS start FROM h, range(0, 6) r(k))
    SELECT {_STAMP.format('start')} AS start, count(*) AS n FROM s, {_LAST} WHERE start + INTERVAL 6 HOUR <= bound GROUP BY 1""")
def stream_sliding(spark: SparkSession, sf_dir: str) -> DataFrame:
    return w.drained(w.sliding(w.events(spark, sf_dir))).select(_start("window.start").alias("start"), "n")


@query(f"""WITH g AS (SELECT *, CASE WHEN ts - lag(ts) OVER (PARTITION BY user_id ORDER BY ts) < INTERVAL 12 HOUR THEN 0 ELSE 1 END AS fresh FROM events),
    k AS (SELECT *, sum(fresh) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS s FROM g)
    SELECT user_id, {_STAMP.format('min(ts)')} AS start, count(*) AS n FROM k, {_LAST} GROUP BY user_id, s, bound HAVING max(ts) + INTERVAL 12 HOUR <= bound""")
def stream_session(spark: SparkSession, sf_dir: str) -> DataFrame:
    """An object's stays, apart by twelve hours; closed ones only."""
    return w.drained(w.sessions(w.events(spark, sf_dir))).select("user_id", _start("session_window.start").alias("start"), "n")


@query("SELECT event_id, user_id FROM events WHERE event_id % 4 = 0")
def stream_gap(spark: SparkSession, sf_dir: str) -> DataFrame:
    return w.drained(w.events(spark, sf_dir).where("event_id % 4 = 0").select("event_id", "user_id"))


@query("SELECT DISTINCT event_id FROM events")
def stream_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    e = w.events(spark, sf_dir)
    return w.drained(w.deduplicated(e)).select("event_id")


@query("SELECT event_id, weight FROM events JOIN (VALUES ('view', 1), ('purchase', 5), ('click', 2)) v(event_type, weight) USING (event_type)")
def stream_static(spark: SparkSession, sf_dir: str) -> DataFrame:
    weights = spark.createDataFrame([("view", 1), ("purchase", 5), ("click", 2)], "event_type string, weight int")
    return w.drained(w.events(spark, sf_dir).join(F.broadcast(weights), "event_type").select("event_id", "weight"))


@query("SELECT v.event_id AS seen, p.event_id AS bought FROM events v JOIN events p ON v.user_id = p.user_id AND v.event_type = 'view' AND p.event_type = 'purchase' AND p.ts BETWEEN v.ts AND v.ts + INTERVAL 1 HOUR")
def stream_join(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Purchases within an hour after a view by the same user: an interval join of two streams."""
    seen = w.events(spark, sf_dir).where("event_type = 'view'").select(F.col("event_id").alias("seen"), F.col("user_id").alias("u"), F.col("ts").alias("seen_at"))
    bought = w.events(spark, sf_dir).where("event_type = 'purchase'").select(F.col("event_id").alias("bought"), "user_id", "ts")
    return w.drained(bought.join(seen, F.expr("user_id = u AND ts BETWEEN seen_at AND seen_at + INTERVAL 1 HOUR"))).select("seen", "bought")


@query(f"""WITH mid AS (SELECT min(ts) + (max(ts) - min(ts)) / 2 AS m FROM events), kept AS (SELECT ts FROM events, mid WHERE NOT (ts < m AND user_id % 10 = 0))
    SELECT {_STAMP.format('day')} AS start, n FROM (SELECT date_trunc('day', ts) AS day, count(*) AS n FROM kept GROUP BY 1), {_LAST} WHERE day + INTERVAL 1 DAY <= bound""")
def stream_late(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Daily counts when a tenth of the users' early events come after all others: the watermark has passed their days, they are dropped."""
    rows = w.table(spark, sf_dir)
    low, high = rows.agg(F.min("ts"), F.max("ts")).first()
    early, middle = (F.col("ts") < F.lit(low + (high - low) * part) for part in (0.5, 0.75))
    late = early & (F.col("user_id") % 10 == 0)
    # rows are held against the watermark that the batch before began with, so the later half comes in two
    stream = w.in_order([rows.where(early & ~late), rows.where(~early & middle), rows.where(~middle), rows.where(late)]).withWatermark("ts", "1 hour")
    return w.drained(w.tumbling(stream)).select(_start("window.start").alias("start"), "n")


@query()
def stream_tracks(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The tracker as a stateful stream over the test clips, in batches of a quarter of a minute: boxes and span of each track."""
    boxes = detections(spark, sf_dir, "test").select("scene", "clip", "t", "obj", "category", "x", "y", "w", "h", F.timestamp_seconds(F.col("t") / 8.0).alias("ts"))
    stream = w.in_order([boxes.where(F.col("t").between(120 * k, 120 * k + 119)) for k in range(4)]).withWatermark("ts", "1 minute")
    return w.drained(w.tracker(stream)).groupBy("scene", "clip", "track_id").agg(F.count("*").alias("n"), F.min("t").alias("t_first"), F.max("t").alias("t_last"))
