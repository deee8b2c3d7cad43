"""Queries on resampled paths and the repair of track ends, all in built-in expressions."""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..catalog import query
from ..sources.scenes import detections
from .sql import with_scene

#: The reference set is the training split of one scene: a fixed set, whatever is repaired with it.
_SET = "scene = 4 and t % 4 = 0"
_SQL_PATHS = """pts AS (SELECT clip, category, pat, obj, t, x, y, lag(x) OVER o AS x0, lag(y) OVER o AS y0 FROM det WHERE scene = 4 AND t % 4 = 0 WINDOW o AS (PARTITION BY obj ORDER BY t)),
    walk AS (SELECT *, sum(coalesce(sqrt((x - x0) * (x - x0) + (y - y0) * (y - y0)), 0e0)) OVER (PARTITION BY obj ORDER BY t) AS s FROM pts),
    seg AS (SELECT *, lag(s) OVER (PARTITION BY obj ORDER BY t) AS s0, max(s) OVER (PARTITION BY obj) AS len FROM walk),
    path AS (SELECT clip, category, pat, obj, i, CASE WHEN i = 0 THEN x ELSE x0 + (x - x0) * (goal - s0) / (s - s0) END AS px, CASE WHEN i = 0 THEN y ELSE y0 + (y - y0) * (goal - s0) / (s - s0) END AS py
        FROM (SELECT *, CASE WHEN i = 19 THEN len ELSE len * i / 19e0 END AS goal FROM seg, (SELECT unnest(range(0, 20))::INT AS i) WHERE len > 0e0) WHERE i = 0 AND s0 IS NULL OR i > 0 AND s0 < goal AND goal <= s),
    ref AS (SELECT * FROM path WHERE clip % 3 = 0), own AS (SELECT * FROM path WHERE clip % 3 = 2),
    centre AS (SELECT category, pat, i, round(avg(px), 6) AS cx, round(avg(py), 6) AS cy, count(*) AS size FROM ref GROUP BY ALL)"""
_NEAR = """far AS (SELECT o.obj, r.obj AS other, round(avg(sqrt((o.px - r.px) * (o.px - r.px) + (o.py - r.py) * (o.py - r.py))), 6) AS d FROM own o JOIN ref r ON o.category = r.category AND o.i = r.i WHERE {} GROUP BY ALL),
    best AS (SELECT * FROM far QUALIFY row_number() OVER (PARTITION BY obj ORDER BY d, other) <= 10)"""
_ENDS = """SELECT b.obj, round(median(s.px), 4) AS sx, round(median(s.py), 4) AS sy, round(median(e.px), 4) AS ex, round(median(e.py), 4) AS ey
    FROM best b JOIN ref s ON s.obj = b.other AND s.i = 0 JOIN ref e ON e.obj = b.other AND e.i = 19 GROUP BY b.obj"""


def paths(spark: SparkSession, sf_dir: str, split: str) -> DataFrame:
    """Twenty points evenly spaced by arc length for every track with some length: clip, category, pat, obj, i, px, py.

    Each step of a track emits the points whose goal falls in it, so a track needs one sort and no join.
    """
    o = Window.partitionBy("obj").orderBy("t")
    step = detections(spark, sf_dir, split).where(_SET).select("clip", "category", "pat", "obj", "t", "x", "y", F.lag("x").over(o).alias("x0"), F.lag("y").over(o).alias("y0"))
    walk = step.withColumn("s", F.sum(F.coalesce(F.expr("sqrt((x - x0) * (x - x0) + (y - y0) * (y - y0))"), F.lit(0.0))).over(o))
    seg = walk.withColumns({"s0": F.lag("s").over(o), "len": F.max("s").over(Window.partitionBy("obj"))}).where("len > 0e0")
    goal = "CASE WHEN i = 19 THEN len ELSE len * i / 19e0 END"
    at = seg.withColumn("i", F.expr(f"explode(filter(sequence(0, 19), i -> (i = 0 AND s0 IS NULL) OR (i > 0 AND s0 < {goal} AND {goal} <= s)))"))
    at = at.withColumn("f", F.expr(f"CASE WHEN i > 0 THEN ({goal} - s0) / (s - s0) END"))
    return at.selectExpr("clip", "category", "pat", "obj", "i", "CASE WHEN i = 0 THEN x ELSE x0 + (x - x0) * f END AS px", "CASE WHEN i = 0 THEN y ELSE y0 + (y - y0) * f END AS py")


@query(with_scene("SELECT category, pat, i, cx, cy, size FROM centre", _SQL_PATHS))
def path_centers(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Point-wise mean of the reference paths of each category and pattern."""
    return paths(spark, sf_dir, "train").groupBy("category", "pat", "i").agg(F.round(F.avg("px"), 6).alias("cx"), F.round(F.avg("py"), 6).alias("cy"), F.count("*").alias("size"))


_INDEX = "idx AS (SELECT DISTINCT category, pat, floor(cx / 64e0)::INT AS gx, floor(cy / 64e0)::INT AS gy FROM centre)"


@query(with_scene("SELECT category, pat, gx, gy FROM idx", _SQL_PATHS, _INDEX))
def path_index(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Grid cells that each centre passes."""
    return path_centers(spark, sf_dir).selectExpr("category", "pat", "int(floor(cx / 64e0)) AS gx", "int(floor(cy / 64e0)) AS gy").distinct()


_CAND = """tip AS (SELECT obj, category, i, floor(round(px, 6) / 64e0)::INT AS gx, floor(round(py, 6) / 64e0)::INT AS gy FROM own WHERE i IN (0, 19)),
    hits AS (SELECT DISTINCT obj, i, x.category, pat FROM tip p JOIN idx x ON p.category = x.category AND abs(p.gx - x.gx) <= 1 AND abs(p.gy - x.gy) <= 1),
    cand AS (SELECT obj, category, pat FROM hits GROUP BY ALL HAVING count(*) = 2)"""


@query(with_scene("SELECT obj, category, pat FROM cand", _SQL_PATHS, _INDEX, _CAND))
def path_candidates(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Centres that pass near both ends of a track: an equi-join on the nine cells around each end; the index is a fixed small table."""
    around = F.expr("explode(flatten(transform(sequence(-1, 1), dx -> transform(sequence(-1, 1), dy -> struct(int(floor(round(px, 6) / 64e0)) + dx AS gx, int(floor(round(py, 6) / 64e0)) + dy AS gy)))))")
    tips = paths(spark, sf_dir, "test").where("i in (0, 19)").select("obj", "category", "i", around.alias("c")).select("obj", "category", "i", "c.gx", "c.gy")
    hits = tips.join(path_index(spark, sf_dir), ["category", "gx", "gy"]).select("obj", "category", "pat", "i").distinct()
    return hits.groupBy("obj", "category", "pat").agg(F.count("*").alias("ends")).where("ends = 2").drop("ends")


@query(with_scene("""SELECT obj, pat, d, least(size, 10 - before)::BIGINT AS weight FROM (SELECT *, (sum(size) OVER (PARTITION BY obj ORDER BY d, pat) - size)::BIGINT AS before FROM
    (SELECT o.obj, c.pat, round(avg(sqrt((o.px - c.cx) * (o.px - c.cx) + (o.py - c.cy) * (o.py - c.cy))), 6) AS d, min(c.size) AS size FROM cand k JOIN own o ON o.obj = k.obj JOIN centre c ON c.category = k.category AND c.pat = k.pat AND c.i = o.i GROUP BY ALL)) WHERE before < 10""", _SQL_PATHS, _INDEX, _CAND))
def path_knn(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Nearest candidate centres of each track until their sizes make ten."""
    own = paths(spark, sf_dir, "test").select("obj", "i", "px", "py")
    far = path_candidates(spark, sf_dir).join(own, "obj").join(path_centers(spark, sf_dir), ["category", "pat", "i"])
    far = far.groupBy("obj", "pat").agg(F.round(F.avg(F.expr("sqrt((px - cx) * (px - cx) + (py - cy) * (py - cy))")), 6).alias("d"), F.min("size").alias("size"))
    before = F.sum("size").over(Window.partitionBy("obj").orderBy("d", "pat")) - F.col("size")
    return far.withColumn("before", before).where("before < 10").selectExpr("obj", "pat", "d", "least(size, 10 - before) AS weight")


def packed(points: DataFrame) -> DataFrame:
    """A row for each path: category, obj, xs and ys in order."""
    xy = points.groupBy("category", "obj").agg(F.sort_array(F.collect_list(F.struct("i", "px", "py"))).alias("p"))  # twenty points
    return xy.select("category", "obj", F.col("p.px").alias("xs"), F.col("p.py").alias("ys"))


def nearest_paths(own: np.ndarray, ref: np.ndarray, n: int = 10, seeds: int = 40) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Places in ``own`` and ``ref`` and mean point distances of every path's ``n`` nearest, and of those that may tie with the last after rounding.

    Paths are (paths, 2, points). The distance of two paths' centres of gravity is never more than their mean point distance, so only paths whose centres
    are as near as the n-th of some near ones are looked at; none that counts is left out. Points are summed in order, as the SQL forms do.
    """

    def far(i: int, some) -> np.ndarray:
        off = own[i] - ref[some]
        off *= off
        return np.sqrt(off[:, 0] + off[:, 1]).cumsum(1)[:, -1] / ref.shape[2]

    middles, at, to, ds = ref.mean(2), [], [], []
    for i, middle in enumerate(own.mean(2)):
        low = np.hypot(middles[:, 0] - middle[0], middles[:, 1] - middle[1])
        some = np.arange(len(ref))
        if len(ref) > seeds:
            first = np.argpartition(low, seeds)[:seeds]
            some = np.flatnonzero(low <= np.partition(far(i, first), n - 1)[n - 1] + 1e-5)
        d = far(i, some)
        if len(d) > n:
            fine = d <= np.partition(d, n - 1)[n - 1] + 2e-6
            some, d = some[fine], d[fine]
        at.append(np.full(len(some), i))
        to.append(some)
        ds.append(d)
    return tuple(np.concatenate(v) if v else np.zeros(0, k) for v, k in ((at, int), (to, int), (ds, float)))


#: Tracks and reference paths that meet in a task.
OWN_BLOCK, REF_BLOCK = 4_000, 50_000


def _by_neighbours(spark: SparkSession, sf_dir: str, some: str) -> DataFrame:
    """Plain medians of the ends of the ten nearest reference paths: every track against the whole reference set, in blocks of both.

    A block's task returns what may be among a track's ten; ranks over all blocks decide.
    """
    ref = packed(paths(spark, sf_dir, "train").where(some)).select("category", F.col("obj").alias("other"), "xs", "ys").where("size(xs) = 20").cache()
    own = packed(paths(spark, sf_dir, "test")).where("size(xs) = 20").cache()
    parts = max(spark.sparkContext.defaultParallelism, -(-own.count() // OWN_BLOCK))
    blocks = max(1, -(-ref.count() // REF_BLOCK))
    each = lambda n: F.explode(F.sequence(F.lit(0), F.lit(n - 1)))
    left = own.withColumns({"a": F.abs(F.hash("obj")) % parts, "b": each(blocks)}).groupBy("category", "a", "b")
    right = ref.withColumns({"a": each(parts), "b": F.abs(F.hash("other")) % blocks}).groupBy("category", "a", "b")
    points = lambda pdf: np.stack([np.stack(pdf["xs"].to_list()), np.stack(pdf["ys"].to_list())], 1)

    def near(mine: pd.DataFrame, known: pd.DataFrame) -> pd.DataFrame:
        if mine.empty or known.empty:
            return pd.DataFrame({c: pd.Series(dtype=k) for c, k in (("obj", int), ("other", int), *((c, float) for c in ("d", "sx", "sy", "ex", "ey")))})
        p = points(known)
        i, j, d = nearest_paths(points(mine), p)
        return pd.DataFrame({"obj": mine["obj"].to_numpy()[i], "other": known["other"].to_numpy()[j], "d": d, "sx": p[j, 0, 0], "sy": p[j, 1, 0], "ex": p[j, 0, -1], "ey": p[j, 1, -1]})

    far = left.cogroup(right).applyInPandas(near, "obj bigint, other bigint, d double, sx double, sy double, ex double, ey double").withColumn("d", F.round("d", 6))
    best = far.withColumn("place", F.row_number().over(Window.partitionBy("obj").orderBy("d", "other"))).where("place <= 10")
    return best.groupBy("obj").agg(*[F.round(F.percentile(c, 0.5), 4).alias(c) for c in ("sx", "sy", "ex", "ey")])


@query(with_scene(_ENDS, _SQL_PATHS, _NEAR.format("true")))
def refine_exact(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Repair by the nearest of all reference paths, without clusters or index."""
    return _by_neighbours(spark, sf_dir, "true")


@query(with_scene(_ENDS, _SQL_PATHS, _NEAR.format("r.obj % 3 = 0")))
def refine_sample(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Repair by the nearest paths of a third of the reference set (the variant that samples)."""
    return _by_neighbours(spark, sf_dir, "obj % 3 = 0")


@query(with_scene("""SELECT obj, round(x + vx * n, 4) AS ex, round(y + vy * n, 4) AS ey FROM (SELECT *, greatest(0e0, least(CASE WHEN vx > 0e0 THEN (640e0 - x) / vx WHEN vx < 0e0 THEN -x / vx ELSE 1e9 END, CASE WHEN vy > 0e0 THEN (384e0 - y) / vy WHEN vy < 0e0 THEN -y / vy ELSE 1e9 END)) AS n
    FROM (SELECT obj, x, y, (x - x0) / 4e0 AS vx, (y - y0) / 4e0 AS vy FROM pts WHERE clip % 3 = 2 AND x0 IS NOT NULL QUALIFY row_number() OVER (PARTITION BY obj ORDER BY t DESC) = 1) WHERE vx <> 0e0 OR vy <> 0e0)""", _SQL_PATHS))
def refine_border(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The last step of each track run on to the frame's border."""
    o = Window.partitionBy("obj").orderBy("t")
    boxes = detections(spark, sf_dir, "test").where(_SET).withColumns({"vx": (F.col("x") - F.lag("x").over(o)) / 4.0, "vy": (F.col("y") - F.lag("y").over(o)) / 4.0}).where("vx is not null")
    last = boxes.groupBy("obj").agg(F.max_by(F.struct("x", "y", "vx", "vy"), "t").alias("p")).select("obj", "p.*").where("vx <> 0e0 or vy <> 0e0")
    run = lambda v, p, top: f"CASE WHEN {v} > 0e0 THEN ({top} - {p}) / {v} WHEN {v} < 0e0 THEN -{p} / {v} ELSE 1e9 END"
    return last.withColumn("n", F.expr(f"greatest(0e0, least({run('vx', 'x', '640e0')}, {run('vy', 'y', '384e0')}))")).selectExpr("obj", "round(x + vx * n, 4) AS ex", "round(y + vy * n, 4) AS ey")


@query(with_scene("""SELECT clip, t, min(x) AS mid FROM (SELECT clip, t, x, sum(w) OVER (PARTITION BY clip, t ORDER BY x, obj) AS upto, sum(w) OVER (PARTITION BY clip, t) AS total FROM det WHERE scene = 4 AND t % 4 = 0 AND clip % 3 = 2) WHERE upto >= total / 2e0 GROUP BY clip, t"""))
def udaf_wmedian(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Weighted median as an aggregate function: the middle of each frame's boxes by width; a frame's boxes are few."""
    from ..refine.paths import weighted_median

    @F.pandas_udf("double")
    def wmedian(values: pd.Series, weights: pd.Series) -> float:
        return weighted_median(values.to_numpy(), weights.to_numpy())

    return detections(spark, sf_dir, "test").where(_SET).groupBy("clip", "t").agg(wmedian("x", "w").alias("mid"))
