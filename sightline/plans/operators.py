"""Queries on the relational operators around the methods, over scenes and given tables."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..catalog import query
from ..sources.scenes import detections, objects, table
from .sql import with_scene


@query("SELECT l_returnflag, sum(l_quantity)::BIGINT AS quantity FROM lineitem WHERE l_quantity > 45 GROUP BY l_returnflag")
def scan_projection(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Two columns and a filter that reach the Parquet scan."""
    return table(spark, sf_dir, "lineitem").where("l_quantity > 45").groupBy("l_returnflag").agg(F.sum("l_quantity").cast("long").alias("quantity"))


@query(with_scene("SELECT scene, count(*) AS n FROM det WHERE y >= 192e0 AND category IN ('car', 'bus') AND t BETWEEN 100 AND 300 GROUP BY scene"))
def filter_bottom_half(spark: SparkSession, sf_dir: str) -> DataFrame:
    return detections(spark, sf_dir).where("y >= 192e0 AND category IN ('car', 'bus') AND t BETWEEN 100 AND 300").groupBy("scene").agg(F.count("*").alias("n"))


@query(with_scene("SELECT d.scene, d.clip, count(*) AS n, count(DISTINCT d.obj) AS objs FROM det d JOIN obj o ON d.scene = o.scene AND d.clip = o.clip AND d.obj = o.obj WHERE d.t < o.t_in + 10 GROUP BY ALL"))
def det_track_join(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Boxes joined with their tracks by key: the first ten frames of each."""
    o = objects(spark, sf_dir).select("scene", "clip", "obj", "t_in")
    return detections(spark, sf_dir).join(o, ["scene", "clip", "obj"]).where("t < t_in + 10").groupBy("scene", "clip").agg(F.count("*").alias("n"), F.countDistinct("obj").alias("objs"))


@query(with_scene("SELECT scene, zone, count(*) AS n FROM det, (VALUES (0, 0e0, 0e0), (1, 320e0, 0e0), (2, 0e0, 192e0), (3, 320e0, 192e0)) z(zone, zx, zy) WHERE x BETWEEN zx AND zx + 320e0 AND y BETWEEN zy AND zy + 192e0 GROUP BY ALL"))
def box_in_window(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Range join of box centres with four zones, the zones broadcast."""
    zones = spark.createDataFrame([(0, 0.0, 0.0), (1, 320.0, 0.0), (2, 0.0, 192.0), (3, 320.0, 192.0)], "zone int, zx double, zy double")
    return detections(spark, sf_dir).join(F.broadcast(zones), F.expr("x BETWEEN zx AND zx + 320e0 AND y BETWEEN zy AND zy + 192e0")).groupBy("scene", "zone").agg(F.count("*").alias("n"))


@query("""WITH frames AS (SELECT event_id, user_id, ts FROM events WHERE event_id % 4 = 0), asked AS (SELECT event_id, user_id, ts FROM events WHERE event_id % 4 = 1)
    SELECT a.event_id, f.event_id AS before FROM asked a ASOF LEFT JOIN frames f ON a.user_id = f.user_id AND a.ts >= f.ts""")
def asof_prev_frame(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Nearest earlier processed frame of the same object: one union, one window, no inequality join."""
    e = table(spark, sf_dir, "events").select("event_id", "user_id", "ts").where("event_id % 4 < 2").withColumn("frame", F.when(F.expr("event_id % 4 = 0"), F.col("event_id")))
    w = Window.partitionBy("user_id").orderBy("ts", F.desc("frame")).rowsBetween(Window.unboundedPreceding, 0)
    return e.withColumn("before", F.last("frame", ignorenulls=True).over(w)).where("frame is null").select("event_id", "before")


@query(with_scene("SELECT scene, clip, moment, count(*) AS alive FROM obj, (SELECT unnest(range(0, 480, 60)) AS moment) WHERE moment BETWEEN t_in AND least(479, t_in + dur) GROUP BY ALL"))
def interval_alive(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Tracks alive at each moment: intervals exploded to the moments they hold."""
    at = F.expr("explode(filter(sequence(0L, 479L, 60L), s -> s BETWEEN t_in AND least(479, t_in + dur)))")
    return objects(spark, sf_dir).select("scene", "clip", at.alias("moment")).groupBy("scene", "clip", "moment").agg(F.count("*").alias("alive"))


@query(with_scene("SELECT scene, clip, category, count(*) AS n FROM obj GROUP BY CUBE (scene, clip, category)"))
def cube_counts(spark: SparkSession, sf_dir: str) -> DataFrame:
    return objects(spark, sf_dir).cube("scene", "clip", "category").agg(F.count("*").alias("n"))


@query(with_scene("SELECT scene, pat, count(*) AS n FROM obj GROUP BY ROLLUP (scene, pat)"))
def rollup_counts(spark: SparkSession, sf_dir: str) -> DataFrame:
    return objects(spark, sf_dir).rollup("scene", "pat").agg(F.count("*").alias("n"))


@query(with_scene("SELECT scene, category, pat, count(*) AS n FROM obj GROUP BY GROUPING SETS ((scene, category), (pat), ())"))
def gsets_counts(spark: SparkSession, sf_dir: str) -> DataFrame:
    return objects(spark, sf_dir).groupingSets([["scene", "category"], ["pat"], []], "scene", "category", "pat").agg(F.count("*").alias("n"))


@query(with_scene("SELECT scene, clip, " + ", ".join(f"count(*) FILTER (pat = {p}) AS pat{p}" for p in range(5)) + " FROM obj GROUP BY scene, clip"))
def pivot_patterns(spark: SparkSession, sf_dir: str) -> DataFrame:
    wide = objects(spark, sf_dir).groupBy("scene", "clip").pivot("pat", list(range(5))).agg(F.count(F.lit(1)))
    return wide.select("scene", "clip", *(F.coalesce(F.col(str(p)), F.lit(0)).alias(f"pat{p}") for p in range(5)))


@query(with_scene("SELECT scene, count(*) AS n, min(dur) AS lo, max(dur) AS hi, round(avg(dur), 6) AS mean, round(stddev(dur), 6) AS sd, count(DISTINCT clip) AS clips, bool_or(braking) AS any_braking, arg_max(obj, dur * 1000000 + obj) AS longest FROM obj GROUP BY scene"))
def agg_basic(spark: SparkSession, sf_dir: str) -> DataFrame:
    return objects(spark, sf_dir).groupBy("scene").agg(
        F.count("*").alias("n"), F.min("dur").alias("lo"), F.max("dur").alias("hi"), F.round(F.avg("dur"), 6).alias("mean"), F.round(F.stddev("dur"), 6).alias("sd"),
        F.countDistinct("clip").alias("clips"), F.bool_or("braking").alias("any_braking"), F.max_by("obj", F.expr("dur * 1000000 + obj")).alias("longest"),
    )


@query(with_scene("SELECT scene, quantile_cont(dur, 0.5) AS median, quantile_cont(dur, 0.9) AS p90 FROM obj GROUP BY scene"))
def agg_percentile(spark: SparkSession, sf_dir: str) -> DataFrame:
    return objects(spark, sf_dir).groupBy("scene").agg(F.percentile("dur", F.lit(0.5)).alias("median"), F.percentile("dur", F.lit(0.9)).alias("p90"))


@query(with_scene("SELECT obj, rank() OVER w AS rk, dense_rank() OVER w AS dr, row_number() OVER v AS rn, ntile(4) OVER v AS quarter FROM obj WINDOW w AS (PARTITION BY scene, clip ORDER BY dur), v AS (PARTITION BY scene, clip ORDER BY dur, obj)"))
def win_rank(spark: SparkSession, sf_dir: str) -> DataFrame:
    w, v = Window.partitionBy("scene", "clip").orderBy("dur"), Window.partitionBy("scene", "clip").orderBy("dur", "obj")
    return objects(spark, sf_dir).select("obj", F.rank().over(w).alias("rk"), F.dense_rank().over(w).alias("dr"), F.row_number().over(v).alias("rn"), F.ntile(4).over(v).alias("quarter"))


@query("SELECT event_id, lag(event_id) OVER w AS before, lead(event_id) OVER w AS after, first_value(event_id) OVER w AS first_id, nth_value(event_id, 2) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN UNBOUNDED PRECEDING AND UNBOUNDED FOLLOWING) AS second_id FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id)")
def win_lag(spark: SparkSession, sf_dir: str) -> DataFrame:
    w = Window.partitionBy("user_id").orderBy("ts", "event_id")
    whole = w.rowsBetween(Window.unboundedPreceding, Window.unboundedFollowing)
    return table(spark, sf_dir, "events").select("event_id", F.lag("event_id").over(w).alias("before"), F.lead("event_id").over(w).alias("after"), F.first("event_id").over(w).alias("first_id"), F.nth_value("event_id", 2).over(whole).alias("second_id"))


@query(with_scene("SELECT scene, clip, t, n, sum(n) OVER (PARTITION BY scene, clip ORDER BY t ROWS BETWEEN 7 PRECEDING AND CURRENT ROW)::BIGINT AS smooth, sum(n) OVER (PARTITION BY scene, clip ORDER BY t RANGE BETWEEN 16 PRECEDING AND CURRENT ROW)::BIGINT AS recent FROM (SELECT scene, clip, t, count(*) AS n FROM det WHERE scene = 4 GROUP BY ALL)"))
def win_rows(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Smoothing over rows and over a range of frames."""
    n = detections(spark, sf_dir).where("scene = 4").groupBy("scene", "clip", "t").agg(F.count("*").alias("n"))
    w = Window.partitionBy("scene", "clip").orderBy("t")
    return n.select("*", F.sum("n").over(w.rowsBetween(-7, 0)).alias("smooth"), F.sum("n").over(w.rangeBetween(-16, 0)).alias("recent"))


@query(with_scene("SELECT obj, dur FROM obj ORDER BY dur DESC, obj LIMIT 25"))
def topk(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The 25 longest tracks: a top-k report."""
    return objects(spark, sf_dir).select("obj", "dur").orderBy(F.desc("dur"), "obj").limit(25)


@query(with_scene("SELECT scene, obj, dur FROM obj QUALIFY row_number() OVER (PARTITION BY scene ORDER BY dur DESC, obj) <= 3"))
def topk_group(spark: SparkSession, sf_dir: str) -> DataFrame:
    w = Window.partitionBy("scene").orderBy(F.desc("dur"), "obj")
    return objects(spark, sf_dir).select("scene", "obj", "dur").withColumn("r", F.row_number().over(w)).where("r <= 3").drop("r")


_CARS = "(SELECT DISTINCT scene, clip, t FROM det WHERE category = 'car')"
_BUS = "(SELECT DISTINCT scene, clip, t FROM det WHERE category = 'bus')"
for _name, _op, _f in (("set_union", "UNION", lambda a, b: a.union(b).distinct()), ("set_intersect", "INTERSECT", lambda a, b: a.intersect(b)), ("set_except", "EXCEPT", lambda a, b: a.subtract(b))):

    def _set(spark: SparkSession, sf_dir: str, f=_f) -> DataFrame:
        d = detections(spark, sf_dir)
        one, two = (d.where(F.col("category") == c).select("scene", "clip", "t") for c in ("car", "bus"))
        return f(one, two).groupBy("scene", "clip").agg(F.count("*").alias("frames"))

    query(with_scene(f"SELECT scene, clip, count(*) AS frames FROM ({_CARS} {_op} {_BUS}) GROUP BY ALL"), _name)(_set)


@query(with_scene("SELECT scene, round(sum(sqrt(x * x + y * y)), 4) AS r, round(sum(atan2(y, x)), 6) AS a, sum(floor(x / 32e0))::BIGINT AS cells, round(sum(greatest(x, y) - least(x, y)), 4) AS d FROM det GROUP BY scene"))
def fn_geometry(spark: SparkSession, sf_dir: str) -> DataFrame:
    return detections(spark, sf_dir).groupBy("scene").agg(
        F.round(F.sum(F.sqrt(F.expr("x * x + y * y"))), 4).alias("r"), F.round(F.sum(F.atan2("y", "x")), 6).alias("a"), F.sum(F.floor(F.expr("x / 32e0"))).alias("cells"), F.round(F.sum(F.expr("greatest(x, y) - least(x, y)")), 4).alias("d")
    )


@query("SELECT c_custkey, lower(c_mktsegment) AS kind, length(c_name) AS n, regexp_extract(c_name, '[0-9]+', 0) AS digits, concat_ws('/', c_mktsegment, c_nationkey::VARCHAR) AS id FROM customer")
def fn_string(spark: SparkSession, sf_dir: str) -> DataFrame:
    return table(spark, sf_dir, "customer").select("c_custkey", F.lower("c_mktsegment").alias("kind"), F.length("c_name").cast("long").alias("n"), F.regexp_extract("c_name", "[0-9]+", 0).alias("digits"), F.concat_ws("/", "c_mktsegment", F.col("c_nationkey").cast("string")).alias("id"))


@query("SELECT strftime(date_trunc('hour', ts), '%Y-%m-%d %H') AS hour, count(*) AS n, sum(extract(minute FROM ts))::BIGINT AS minutes FROM events GROUP BY 1")
def fn_time(spark: SparkSession, sf_dir: str) -> DataFrame:
    return table(spark, sf_dir, "events").groupBy(F.date_format(F.date_trunc("hour", "ts"), "yyyy-MM-dd HH").alias("hour")).agg(F.count("*").alias("n"), F.sum(F.minute("ts")).alias("minutes"))


@query("SELECT (json_extract(props, '$.k')::INT // 10)::INT AS bin, count(*) AS n FROM events GROUP BY 1")
def fn_json(spark: SparkSession, sf_dir: str) -> DataFrame:
    return table(spark, sf_dir, "events").select(F.from_json("props", "k int").alias("p")).groupBy(F.expr("int(p.k div 10)").alias("bin")).agg(F.count("*").alias("n"))


@query(with_scene("SELECT scene, clip, obj, min(t) AS first, max(t) AS last, count(*) FILTER (x > 320e0) AS right_half FROM det WHERE scene = 4 GROUP BY ALL"))
def fn_array(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Tracks at rest as arrays of points, asked with array functions."""
    tracks = detections(spark, sf_dir).where("scene = 4").groupBy("scene", "clip", "obj").agg(F.sort_array(F.collect_list(F.struct("t", "x"))).alias("dets"))
    return tracks.select("scene", "clip", "obj", F.element_at("dets", 1)["t"].alias("first"), F.element_at("dets", -1)["t"].alias("last"), F.size(F.filter("dets", lambda d: d["x"] > 320.0)).cast("long").alias("right_half"))


@query(with_scene("SELECT scene, category AS k, count(*) AS v FROM obj GROUP BY ALL"))
def fn_map(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Counts kept as a map of category to number, exploded again."""
    n = objects(spark, sf_dir).groupBy("scene", "category").agg(F.count("*").alias("n"))
    maps = n.groupBy("scene").agg(F.map_from_entries(F.collect_list(F.struct("category", "n"))).alias("m"))
    return maps.select("scene", F.explode("m").alias("k", "v"))


@query("SELECT a.vec_id, b.vec_id AS other, round(list_cosine_similarity(a.embedding::DOUBLE[], b.embedding::DOUBLE[]), 6) AS cosine FROM embeddings a, embeddings b WHERE b.vec_id < 12")
def vec_cosine(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Cosine of each vector with the twelve appearance vectors."""
    e = table(spark, sf_dir, "embeddings").select("vec_id", F.transform("embedding", lambda x: x.cast("double")).alias("v"))
    few = e.where("vec_id < 12").select(F.col("vec_id").alias("other"), F.col("v").alias("w"))
    dot = lambda a, b: F.aggregate(F.zip_with(a, b, lambda x, y: x * y), F.lit(0.0), lambda s, x: s + x)
    return e.crossJoin(F.broadcast(few)).select("vec_id", "other", F.round(dot("v", "w") / F.sqrt(dot("v", "v")) / F.sqrt(dot("w", "w")), 6).alias("cosine"))


@query(with_scene("SELECT scene, count(*) AS n FROM obj WHERE ((obj * 7919 + 13) % 1000003) % 10 < 3 GROUP BY scene"))
def hash_sample(spark: SparkSession, sf_dir: str) -> DataFrame:
    """A repeatable sample by hash: a sampling operator."""
    return objects(spark, sf_dir).where("((obj * 7919 + 13) % 1000003) % 10 < 3").groupBy("scene").agg(F.count("*").alias("n"))


@query("SELECT l_orderkey, l_linenumber, min(l_partkey) AS part, count(*) AS copies FROM lineitem GROUP BY ALL HAVING count(*) > 1")
def dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return table(spark, sf_dir, "lineitem").groupBy("l_orderkey", "l_linenumber").agg(F.min("l_partkey").alias("part"), F.count("*").alias("copies")).where("copies > 1")


@query(with_scene("SELECT category, count(*) AS n FROM obj WHERE dur > 100 GROUP BY category"))
def sql_surface(spark: SparkSession, sf_dir: str) -> DataFrame:
    """A view of tracks asked in SQL with a parameter marker."""
    return spark.sql("SELECT category, count(*) AS n FROM {tracks} WHERE dur > :least GROUP BY category", args={"least": 100}, tracks=objects(spark, sf_dir))


@query(with_scene("SELECT scene, count(*) AS frames FROM (SELECT DISTINCT scene, clip, t FROM det d WHERE EXISTS (SELECT 1 FROM obj o WHERE o.scene = d.scene AND o.clip = d.clip AND o.t_in = d.t)) GROUP BY scene"))
def semi_frames(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Frames at which some object enters."""
    entries = objects(spark, sf_dir).select("scene", "clip", F.col("t_in").alias("t"))
    return detections(spark, sf_dir).select("scene", "clip", "t").distinct().join(entries, ["scene", "clip", "t"], "left_semi").groupBy("scene").agg(F.count("*").alias("frames"))


@query(with_scene("SELECT scene, count(*) AS frames FROM (SELECT DISTINCT scene, clip, t FROM det d WHERE NOT EXISTS (SELECT 1 FROM obj o WHERE o.scene = d.scene AND o.clip = d.clip AND o.t_in = d.t)) GROUP BY scene"))
def anti_frames(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Frames with objects at which none enters."""
    entries = objects(spark, sf_dir).select("scene", "clip", F.col("t_in").alias("t"))
    return detections(spark, sf_dir).select("scene", "clip", "t").distinct().join(entries, ["scene", "clip", "t"], "left_anti").groupBy("scene").agg(F.count("*").alias("frames"))


@query("SELECT event_type, count(DISTINCT user_id) AS users, count(DISTINCT (user_id, ts::DATE)) AS visits FROM events GROUP BY event_type")
def agg_distinct(spark: SparkSession, sf_dir: str) -> DataFrame:
    return table(spark, sf_dir, "events").groupBy("event_type").agg(F.countDistinct("user_id").alias("users"), F.expr("count(DISTINCT struct(user_id, date(ts))) AS visits"))


@query("SELECT strftime(ts, '%Y-%m-%d') AS day, count(DISTINCT user_id) AS users FROM (SELECT user_id, min(ts) AS ts FROM events GROUP BY user_id) GROUP BY 1")
def events_unique(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Objects by the day they are first seen."""
    first = table(spark, sf_dir, "events").groupBy("user_id").agg(F.min("ts").alias("ts"))
    return first.groupBy(F.date_format("ts", "yyyy-MM-dd").alias("day")).agg(F.countDistinct("user_id").alias("users"))


@query(with_scene("SELECT scene, clip, t, sum(n) OVER (PARTITION BY scene, clip ORDER BY t RANGE BETWEEN 8 PRECEDING AND CURRENT ROW)::BIGINT AS lately FROM (SELECT scene, clip, t, count(*) AS n FROM det WHERE scene >= 3 GROUP BY ALL)"))
def win_range(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Boxes of the last second, by frames of time and not by rows."""
    n = detections(spark, sf_dir).where("scene >= 3").groupBy("scene", "clip", "t").agg(F.count("*").alias("n"))
    return n.select("scene", "clip", "t", F.sum("n").over(Window.partitionBy("scene", "clip").orderBy("t").rangeBetween(-8, 0)).alias("lately"))


@query("SELECT l_orderkey, max(l_extendedprice) AS price, arg_max(l_linenumber, (l_extendedprice, -l_linenumber)) AS line FROM lineitem GROUP BY l_orderkey")
def fn_struct(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Largest row of a group as a struct, ordered by its fields."""
    best = F.max(F.struct(F.col("l_extendedprice").alias("price"), (-F.col("l_linenumber")).alias("back"))).alias("best")
    return table(spark, sf_dir, "lineitem").groupBy("l_orderkey").agg(best).select("l_orderkey", F.col("best").withField("line", -F.col("best.back")).alias("best")).select("l_orderkey", "best.price", "best.line")


@query(with_scene("SELECT scene, category, round(sum(sec), 6) AS sec FROM det JOIN (VALUES ('car', 0.004e0), ('bus', 0.006e0), ('walker', 0.003e0)) c(category, sec) USING (category) GROUP BY ALL"))
def bcast_cost(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Seconds by category from a literal cost table, which is broadcast."""
    costs = spark.createDataFrame([("car", 0.004), ("bus", 0.006), ("walker", 0.003)], "category string, sec double")
    n = detections(spark, sf_dir).groupBy("scene", "category").agg(F.count("*").alias("n"))  # counted before the join: far fewer rows meet the table
    return n.join(F.broadcast(costs), "category").select("scene", "category", F.round(F.col("n") * F.col("sec"), 6).alias("sec"))


@query(with_scene("SELECT scene, clip, obj, t, cx, cy, round(w / 640e0, 9) AS bw, round(h / 384e0, 9) AS bh, coalesce(t - lag(t) OVER (PARTITION BY scene, clip, obj ORDER BY t), 0) AS elapsed FROM (SELECT *, round(x / 640e0, 9) AS cx, round(y / 384e0, 9) AS cy FROM det WHERE scene = 4 AND t % 4 = 0)"))
def det_features(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Inputs of the scorer for each box: position and size in parts of the frame, and frames since the box before."""
    e = F.coalesce(F.col("t") - F.lag("t").over(Window.partitionBy("scene", "clip", "obj").orderBy("t")), F.lit(0))
    return detections(spark, sf_dir, gap=4).where("scene = 4").select("scene", "clip", "obj", "t", F.expr("round(x / 640e0, 9) AS cx"), F.expr("round(y / 384e0, 9) AS cy"), F.expr("round(w / 640e0, 9) AS bw"), F.expr("round(h / 384e0, 9) AS bh"), e.alias("elapsed"))


@query(with_scene("SELECT scene, cx, cy, count(*) AS boxes FROM (SELECT scene, clip, t, obj, cx, unnest(range(floor(y0 / 32e0)::BIGINT, ceil(y1 / 32e0)::BIGINT))::INT AS cy FROM (SELECT *, unnest(range(floor(x0 / 32e0)::BIGINT, ceil(x1 / 32e0)::BIGINT))::INT AS cx FROM (SELECT *, greatest(x - w / 2e0, 0e0) AS x0, least(x + w / 2e0, 640e0) AS x1, greatest(y - h / 2e0, 0e0) AS y0, least(y + h / 2e0, 384e0) AS y1 FROM det WHERE scene = 4 AND t % 16 = 0) WHERE x0 < x1 AND y0 < y1)) GROUP BY ALL"))
def udtf_cells(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The cells of a box as a table function joined laterally; cell_labels is the built-in form for large inputs."""
    from pyspark.sql.functions import udtf

    @udtf(returnType="cx int, cy int")
    class CellsOfBox:
        def eval(self, x: float, y: float, w: float, h: float):
            x0, x1, y0, y1 = max(x - w / 2, 0.0), min(x + w / 2, 640.0), max(y - h / 2, 0.0), min(y + h / 2, 384.0)
            if x0 < x1 and y0 < y1:
                for cx in range(int(x0 // 32), int(-(-x1 // 32))):
                    for cy in range(int(y0 // 32), int(-(-y1 // 32))):
                        yield cx, cy

    boxes = detections(spark, sf_dir, gap=16).where("scene = 4").select("scene", "x", "y", "w", "h")
    cells = boxes.lateralJoin(CellsOfBox(F.col("x").outer(), F.col("y").outer(), F.col("w").outer(), F.col("h").outer()))
    return cells.groupBy("scene", "cx", "cy").agg(F.count("*").alias("boxes"))
