"""Queries on the true tracks: preparation, labels, and the exploratory questions answered from tracks."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..catalog import query
from ..sources.scenes import detections, frame_cells, frames_of, objects, simulated, table, visible
from .sql import CELLS, SIM, with_scene


@query(with_scene("SELECT scene, count(*) AS n, count(DISTINCT obj) AS objects, round(sum(x), 3) AS sum_x, round(sum(y), 3) AS sum_y FROM det GROUP BY scene"))
def scene_profile(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Size and coordinate sums of every scene: the regression test of the source."""
    return detections(spark, sf_dir).groupBy("scene").agg(F.count("*").alias("n"), F.countDistinct("obj").alias("objects"), F.round(F.sum("x"), 3).alias("sum_x"), F.round(F.sum("y"), 3).alias("sum_y"))


@query(with_scene("SELECT DISTINCT scene, clip, CASE clip % 3 WHEN 0 THEN 'train' WHEN 1 THEN 'val' ELSE 'test' END AS split, ((clip * 7919 + scene * 104729) % 1000003) % 1000 AS draw FROM obj"))
def clips_split(spark: SparkSession, sf_dir: str) -> DataFrame:
    """One-minute clips dealt to train, validation and test sets, with the hash that orders a sample."""
    return objects(spark, sf_dir).select("scene", "clip").distinct().selectExpr(
        "scene", "clip", "CASE clip % 3 WHEN 0 THEN 'train' WHEN 1 THEN 'val' ELSE 'test' END AS split", "((clip * 7919 + scene * 104729) % 1000003) % 1000 AS draw"
    )


@query(with_scene("SELECT scene, clip, pat, count(*) AS n FROM obj GROUP BY ALL"))
def truth_counts(spark: SparkSession, sf_dir: str) -> DataFrame:
    return objects(spark, sf_dir).groupBy("scene", "clip", "pat").agg(F.count("*").alias("n"))


@query(with_scene("SELECT scene, g AS gap, count(*) AS n, count(DISTINCT (clip, t)) AS frames FROM det, (VALUES (1), (2), (4), (8), (16), (32)) v(g) WHERE t % g = 0 GROUP BY ALL"))
def gap_scan(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Boxes and frames that remain at each sampling gap."""
    gaps = spark.createDataFrame([(g,) for g in (1, 2, 4, 8, 16, 32)], "gap int")
    return detections(spark, sf_dir).crossJoin(F.broadcast(gaps)).where("t % gap = 0").groupBy("scene", "gap").agg(F.count("*").alias("n"), F.countDistinct("clip", "t").alias("frames"))


@query(with_scene("SELECT scene, cx, cy, count(*) AS frames FROM cells GROUP BY ALL", CELLS))
def cell_labels(spark: SparkSession, sf_dir: str) -> DataFrame:
    """How many frames label each cell positive."""
    return frame_cells(detections(spark, sf_dir)).groupBy("scene", "cx", "cy").agg(F.count("*").alias("frames"))


@query(with_scene("SELECT scene, count(*) AS frames FROM (SELECT DISTINCT scene, clip, t FROM det WHERE clip % 3 = 0) GROUP BY scene"))
def training_frames(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Frames of the training split with a detection: the only ones that train a proxy."""
    frames = frames_of(spark, sf_dir).where("clip % 3 = 0")
    return frames.join(detections(spark, sf_dir, "train"), ["scene", "clip", "t"], "left_semi").groupBy("scene").agg(F.count("*").alias("frames"))


@query(with_scene("SELECT scene, count(*) AS frames FROM (SELECT DISTINCT scene, clip FROM obj) c CROSS JOIN range(0, 480) r(t) WHERE NOT EXISTS (SELECT 1 FROM cells d WHERE d.scene = c.scene AND d.clip = c.clip AND d.t = r.t) GROUP BY scene", CELLS))
def skipped_frames(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Frames without a positive cell: no detector run at all."""
    return frames_of(spark, sf_dir).join(visible(detections(spark, sf_dir)).select("scene", "clip", "t"), ["scene", "clip", "t"], "left_anti").groupBy("scene").agg(F.count("*").alias("frames"))


@query(with_scene("SELECT scene, category, count(*) AS n, round(sum(x), 3) AS sum_x, sum((2000e0 - round(2000e0 * score))::BIGINT)::BIGINT AS sum_noise, count(*) FILTER (obj < 0) AS spurious FROM sim GROUP BY ALL", SIM))
def sim_detect(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The simulated detector at full resolution."""
    return simulated(detections(spark, sf_dir)).groupBy("scene", "category").agg(
        F.count("*").alias("n"), F.round(F.sum("x"), 3).alias("sum_x"), F.sum(F.expr("bigint(2000e0 - round(2000e0 * score))")).alias("sum_noise"), F.count_if(F.col("obj") < 0).alias("spurious")
    )


@query(with_scene("SELECT scene, c AS conf, count(*) AS n FROM sim, (VALUES (0.25e0), (0.5e0), (0.75e0)) v(c) WHERE score >= c GROUP BY ALL", SIM))
def conf_filter(spark: SparkSession, sf_dir: str) -> DataFrame:
    levels = spark.createDataFrame([(0.25,), (0.5,), (0.75,)], "conf double")
    return simulated(detections(spark, sf_dir), conf=0.0).crossJoin(F.broadcast(levels)).where("score >= conf").groupBy("scene", "conf").agg(F.count("*").alias("n"))


@query(with_scene("SELECT scene, clip, pat, count(*) AS n FROM obj WHERE clip % 3 = 2 GROUP BY ALL"))
def turning_counts(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Turning counts of the test clips from true tracks: pattern by first and last point, nearest start and end."""
    ends = detections(spark, sf_dir, "test").groupBy("scene", "clip", "obj").agg(F.max("pat").alias("pat"))
    return ends.groupBy("scene", "clip", "pat").agg(F.count("*").alias("n"))


@query(with_scene("SELECT scene, clip, category, count(DISTINCT obj) AS n FROM det GROUP BY ALL"))
def unique_counts(spark: SparkSession, sf_dir: str) -> DataFrame:
    return detections(spark, sf_dir).groupBy("scene", "clip", "category").agg(F.countDistinct("obj").alias("n"))


_BRAKE = """, speeds AS (SELECT *, sqrt((x - lag(x) OVER w) ** 2 + (y - lag(y) OVER w) ** 2) * 0.1e0 * 8e0 AS v FROM det WHERE category = 'car' WINDOW w AS (PARTITION BY scene, clip, obj ORDER BY t)),
    drops AS (SELECT scene, clip, obj, (lag(v) OVER (PARTITION BY scene, clip, obj ORDER BY t) - v) * 8e0 AS d FROM speeds)
    SELECT scene, clip, obj, round(max(d), 3) AS hardest FROM drops GROUP BY ALL HAVING max(d) >= 5e0"""


@query(with_scene("SELECT 1")[: -len(" SELECT 1")] + _BRAKE)
def hard_braking(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Cars that lose at least 5 m/s in a second between two frames (0.1 m per px, 8 fps)."""
    w = Window.partitionBy("scene", "clip", "obj").orderBy("t")
    step = F.sqrt(F.pow(F.col("x") - F.lag("x").over(w), 2) + F.pow(F.col("y") - F.lag("y").over(w), 2))
    speeds = detections(spark, sf_dir).where("category = 'car'").withColumn("v", step * 0.1 * 8.0)
    drops = speeds.withColumn("d", (F.lag("v").over(w) - F.col("v")) * 8.0)
    return drops.groupBy("scene", "clip", "obj").agg(F.round(F.max("d"), 3).alias("hardest"), F.max("d").alias("m")).where("m >= 5e0").drop("m")


@query(with_scene("SELECT scene, clip, t, count(*) FILTER (category = 'bus') AS buses, count(*) FILTER (category = 'car') AS cars FROM det GROUP BY ALL HAVING count(*) FILTER (category = 'bus') >= 3 AND count(*) FILTER (category = 'car') >= 3"))
def cooccur_frames(spark: SparkSession, sf_dir: str) -> DataFrame:
    count = lambda c: F.count_if(F.col("category") == c)
    return detections(spark, sf_dir).groupBy("scene", "clip", "t").agg(count("bus").alias("buses"), count("car").alias("cars")).where("buses >= 3 and cars >= 3")


@query(with_scene("SELECT scene, clip, count(*) FILTER (category = 'car') / 480e0 AS mean_cars FROM det GROUP BY ALL"))
def visible_avg(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Mean number of visible cars per frame of each clip, empty frames included."""
    return detections(spark, sf_dir).groupBy("scene", "clip").agg((F.count_if(F.col("category") == "car") / 480.0).alias("mean_cars"))


@query(with_scene("SELECT scene, clip, first // 80 AS bucket, count(*) AS n FROM (SELECT scene, clip, obj, min(t) AS first FROM det WHERE category = 'car' GROUP BY ALL) GROUP BY ALL"))
def traffic_volume(spark: SparkSession, sf_dir: str) -> DataFrame:
    """New cars per ten seconds, by first sight."""
    first = detections(spark, sf_dir).where("category = 'car'").groupBy("scene", "clip", "obj").agg(F.min("t").alias("first"))
    return first.groupBy("scene", "clip", F.expr("first div 80").alias("bucket")).agg(F.count("*").alias("n"))


@query(with_scene("SELECT scene, clip, obj, min(t) AS t_first, max(t) AS t_last FROM det WHERE pat = 2 GROUP BY ALL"))
def north_south(spark: SparkSession, sf_dir: str) -> DataFrame:
    return detections(spark, sf_dir).where("pat = 2").groupBy("scene", "clip", "obj").agg(F.min("t").alias("t_first"), F.max("t").alias("t_last"))


LIMIT_SQL = """, good AS (
        SELECT clip * 480 + t AS spot, count(*) AS cars, min(len) AS shortest FROM (
            SELECT d.*, count(*) OVER (PARTITION BY obj) AS len FROM det d WHERE scene = 0 AND category = 'car') WHERE y >= 192e0 AND len >= 2 GROUP BY ALL HAVING count(*) >= 4
    ), ranked AS (SELECT *, row_number() OVER (ORDER BY shortest DESC, spot) AS r FROM good),
    pick AS (
        SELECT 1 AS n, r, [spot] AS chosen, spot FROM ranked WHERE r = 1
        UNION ALL
        SELECT n + 1, nx.r, list_append(chosen, nx.spot), nx.spot FROM pick p, LATERAL (
            SELECT k.r, k.spot FROM ranked k WHERE k.r > p.r AND len(list_filter(p.chosen, lambda c: abs(c - k.spot) < 40)) = 0 ORDER BY k.r LIMIT 1) nx WHERE n < 20
    ) SELECT n AS pick, spot // 480 AS clip, spot % 480 AS t FROM pick"""


@query(with_scene("SELECT 1", recursive=True)[: -len(" SELECT 1")] + LIMIT_SQL)
def limit_tracks(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Twenty frames with four cars in the lower half, five seconds apart, longest shortest track first, from tracks alone."""
    from ..measure.limits import spaced

    cars = detections(spark, sf_dir).where("scene = 0 and category = 'car'")
    long = cars.withColumn("len", F.count("*").over(Window.partitionBy("obj"))).where("y >= 192e0 and len >= 2")
    frames = long.groupBy("clip", "t").agg(F.count("*").alias("cars"), F.min("len").alias("shortest")).where("cars >= 4")
    ranked = frames.selectExpr("clip * 480 + t AS at", "shortest").orderBy(F.desc("shortest"), "at")
    got = spaced(ranked, 20, 40)
    return spark.createDataFrame([(i + 1, at // 480, at % 480) for i, at in enumerate(got)], "pick int, clip bigint, t bigint")


@query("""WITH d AS (SELECT date_diff('hour', TIMESTAMP '2024-01-01', ts) AS hour, user_id, event_type FROM events)
    SELECT hour, count(DISTINCT user_id) FILTER (event_type = 'purchase') AS buyers, count(DISTINCT user_id) FILTER (event_type = 'view') AS viewers FROM d GROUP BY hour
    HAVING count(DISTINCT user_id) FILTER (event_type = 'purchase') >= 3 AND count(DISTINCT user_id) FILTER (event_type = 'view') >= 3""")
def events_cooccur(spark: SparkSession, sf_dir: str) -> DataFrame:
    hours = table(spark, sf_dir, "events").selectExpr("timestampdiff(HOUR, TIMESTAMP_NTZ '2024-01-01', ts) AS hour", "user_id", "event_type")
    who = lambda c: F.countDistinct(F.when(F.col("event_type") == c, F.col("user_id")))
    return hours.groupBy("hour").agg(who("purchase").alias("buyers"), who("view").alias("viewers")).where("buyers >= 3 and viewers >= 3")


@query("SELECT strftime(ts, '%Y-%m-%d') AS day, count(*) / 24e0 AS mean_seen, count(DISTINCT user_id) AS users FROM events GROUP BY 1")
def events_visible(spark: SparkSession, sf_dir: str) -> DataFrame:
    return table(spark, sf_dir, "events").groupBy(F.date_format("ts", "yyyy-MM-dd").alias("day")).agg((F.count("*") / 24.0).alias("mean_seen"), F.countDistinct("user_id").alias("users"))


@query("""WITH seen AS (SELECT strftime(l_shipdate, '%Y-%m-%d') AS day, (floor(l_quantity) - 1)::INT AS cx, least(31, floor(l_extendedprice / 3300e0))::INT AS cy FROM lineitem)
    SELECT day, count(*) AS boxes, count(DISTINCT cx * 32 + cy) AS cells FROM seen GROUP BY day""")
def lin_cells(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The grid scene: boxes and positive cells per frame (day)."""
    seen = table(spark, sf_dir, "lineitem").selectExpr("date_format(l_shipdate, 'yyyy-MM-dd') AS day", "int(floor(l_quantity) - 1) AS cx", "int(least(31, floor(l_extendedprice / 3300e0))) AS cy")
    return seen.groupBy("day").agg(F.count("*").alias("boxes"), F.countDistinct(F.col("cx") * 32 + F.col("cy")).alias("cells"))


@query("""SELECT r_name AS region, n_name AS nation, count(*) AS cameras, sum(seen)::BIGINT AS boxes FROM
    (SELECT s_suppkey, s_nationkey, (SELECT count(*) FROM lineitem WHERE l_suppkey = s_suppkey) AS seen FROM supplier) s JOIN nation ON s_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey
    GROUP BY ROLLUP (r_name, n_name)""")
def fleet_rollup(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Cameras and boxes by nation and region."""
    seen = table(spark, sf_dir, "lineitem").groupBy(F.col("l_suppkey").alias("s_suppkey")).agg(F.count("*").alias("seen"))
    named = table(spark, sf_dir, "supplier").join(seen, "s_suppkey", "left").join(F.broadcast(table(spark, sf_dir, "nation")), F.expr("s_nationkey = n_nationkey")).join(F.broadcast(table(spark, sf_dir, "region")), F.expr("n_regionkey = r_regionkey"))
    return named.rollup(F.col("r_name").alias("region"), F.col("n_name").alias("nation")).agg(F.count("*").alias("cameras"), F.sum(F.coalesce("seen", F.lit(0))).alias("boxes"))


@query("""WITH s AS (SELECT doc_id, n_chars, toxic, CASE WHEN n_chars < b THEN 0 ELSE 1 END AS asked, b FROM documents JOIN labels USING (doc_id), (VALUES (200), (500), (1000), (2000)) v(b))
    SELECT b AS bound, count(*) AS docs, sum(asked)::BIGINT AS checked, sum(asked * n_chars)::BIGINT AS cost, sum(asked * toxic)::BIGINT AS found, sum(toxic)::BIGINT AS positives FROM s GROUP BY b""")
def doc_cascade(spark: SparkSession, sf_dir: str) -> DataFrame:
    """A cheap score (length) decides which documents get the costly check: cost and recall by bound."""
    bounds = spark.createDataFrame([(200,), (500,), (1000,), (2000,)], "bound int")
    both = table(spark, sf_dir, "documents").select("doc_id", "n_chars").join(table(spark, sf_dir, "labels").select("doc_id", "toxic"), "doc_id").crossJoin(F.broadcast(bounds))
    asked = F.when(F.col("n_chars") < F.col("bound"), 0).otherwise(1)
    return both.groupBy("bound").agg(F.count("*").alias("docs"), F.sum(asked).alias("checked"), F.sum(asked * F.col("n_chars")).alias("cost"), F.sum(asked * F.col("toxic")).alias("found"), F.sum("toxic").cast("long").alias("positives"))


@query("""WITH t AS (SELECT conv_id, turn, g FROM conversations, (VALUES (1), (2), (4), (8)) v(g) WHERE turn % g = 0)
    SELECT g AS gap, count(*) AS turns, sum(e)::BIGINT AS elapsed FROM (SELECT g, coalesce(turn - lag(turn) OVER (PARTITION BY conv_id, g ORDER BY turn), 0) AS e FROM t) GROUP BY g""")
def conv_gaps(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Sub-sampled conversations: turns kept and elapsed turns at each gap."""
    gaps = spark.createDataFrame([(g,) for g in (1, 2, 4, 8)], "gap int")
    kept = table(spark, sf_dir, "conversations").select("conv_id", "turn").crossJoin(F.broadcast(gaps)).where("turn % gap = 0")
    e = F.coalesce(F.col("turn") - F.lag("turn").over(Window.partitionBy("conv_id", "gap").orderBy("turn")), F.lit(0))
    return kept.withColumn("e", e).groupBy("gap").agg(F.count("*").alias("turns"), F.sum("e").alias("elapsed"))
