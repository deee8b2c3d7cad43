"""Queries on linking, tracking and path repair."""

from __future__ import annotations


import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..catalog import query
from ..model.schemas import FRAMES
from ..refine.paths import Reference, dbscan, resample
from ..sources.scenes import detections, simulated
from ..track import loop
from ..tune.trial import Clip, changed, run_clip
from .sql import SIM, with_scene
from .tuning import BASE, CLIPS, models
from .windows import iou

_TRACKED = "scene int, clip bigint, t bigint, track_id bigint"


def tracked(spark: SparkSession, sf_dir: str, tracker: str, gap: int) -> DataFrame:
    """Boxes of all test clips with the ids that a tracker gives them; a clip is one group, frames in order inside it."""
    net = spark.sparkContext.broadcast(models(spark, sf_dir).net if tracker == "recurrent" else None)
    cfg = changed(BASE, conf=0.25, gap=gap, tracker=tracker)

    def run(key, pdf: pd.DataFrame) -> pd.DataFrame:
        return run_clip(Clip(pdf), cfg, net.value)[0].assign(scene=int(key[0]), clip=int(key[1]))[["scene", "clip", "t", "track_id"]]

    return detections(spark, sf_dir, "test", gap, True).groupBy("scene", "clip").applyInPandas(run, _TRACKED)


@query()
def tracks_overlap(spark: SparkSession, sf_dir: str) -> DataFrame:
    return tracked(spark, sf_dir, "overlap", 1).groupBy("scene", "clip", "track_id").agg(F.count("*").alias("n"), F.min("t").alias("t_first"), F.max("t").alias("t_last"))


@query()
def tracks_recurrent(spark: SparkSession, sf_dir: str) -> DataFrame:
    return tracked(spark, sf_dir, "recurrent", 4).groupBy("scene", "clip", "track_id").agg(F.count("*").alias("n"), F.min("t").alias("t_first"), F.max("t").alias("t_last"))


_LINK = f"""near AS (SELECT a.scene, a.clip, a.t, a.obj AS a, b.obj AS b, {iou('a', 'b')} AS v FROM det a JOIN det b ON a.scene = b.scene AND a.clip = b.clip AND b.t = a.t + 4 AND a.category = b.category WHERE a.scene = 4 AND a.t % 4 = 0 AND a.clip % 3 = 2),
    ranked AS (SELECT *, row_number() OVER (PARTITION BY scene, clip, t, a ORDER BY v DESC, b) AS ra, row_number() OVER (PARTITION BY scene, clip, t, b ORDER BY v DESC, a) AS rb FROM near WHERE v >= 0.3e0),
    links AS (SELECT clip, t, a, b FROM ranked WHERE ra = 1 AND rb = 1)"""


def links(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Mutual-best overlaps of frames t and t + 4 in the test clips of one scene."""
    some = detections(spark, sf_dir, "test", 4).where("scene = 4")
    near = some.alias("a").join(some.alias("b"), F.expr("a.clip = b.clip AND b.t = a.t + 4 AND a.category = b.category")).selectExpr("a.clip", "a.t", "a.obj AS a", "b.obj AS b", f"{iou('a', 'b')} AS v").where("v >= 0.3e0")
    rank = lambda one, two: F.row_number().over(Window.partitionBy("clip", "t", one).orderBy(F.desc("v"), two))
    return near.withColumns({"ra": rank("a", "b"), "rb": rank("b", "a")}).where("ra = 1 and rb = 1").select("clip", "t", "a", "b")


@query(with_scene("SELECT clip, count(*) AS links, count(*) FILTER (a = b) AS correct FROM links GROUP BY clip", _LINK))
def pair_links(spark: SparkSession, sf_dir: str) -> DataFrame:
    return links(spark, sf_dir).groupBy("clip").agg(F.count("*").alias("links"), F.count_if(F.expr("a = b")).alias("correct"))


@query(with_scene("SELECT clip, start_t, start_obj, max(n) AS n FROM chain GROUP BY ALL", _LINK, """chain AS (
    SELECT clip, t AS start_t, a AS start_obj, t + 4 AS t, b AS obj, 2 AS n FROM links l WHERE NOT EXISTS (SELECT 1 FROM links p WHERE p.clip = l.clip AND p.t + 4 = l.t AND p.b = l.a)
    UNION ALL SELECT c.clip, start_t, start_obj, l.t + 4, l.b, n + 1 FROM chain c JOIN links l ON l.clip = c.clip AND l.t = c.t AND l.a = c.obj)""", recursive=True))
def chain_tracks(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Chains of mutual-best links: start and number of boxes. Links of a clip are followed in time order inside one group."""

    def run(pdf: pd.DataFrame) -> pd.DataFrame:
        at: dict[tuple[int, int], tuple[int, int]] = {}
        n: dict[tuple[int, int], int] = {}
        for t, a, b in pdf.sort_values("t")[["t", "a", "b"]].itertuples(index=False):
            start = at.pop((t, a), (t, a))
            at[t + 4, b] = start
            n[start] = n.get(start, 1) + 1
        return pd.DataFrame([(pdf["clip"].iloc[0], *k, v) for k, v in n.items()], columns=["clip", "start_t", "start_obj", "n"])

    return links(spark, sf_dir).groupBy("clip").applyInPandas(run, "clip bigint, start_t bigint, start_obj bigint, n int")


@query(with_scene("SELECT g AS gap, scene, count(*) AS kept FROM keep GROUP BY ALL", """few AS (SELECT scene, obj, t FROM sim WHERE obj >= 0 AND scene = 4 AND clip < 12), keep AS (
    SELECT g, scene, obj, min(t) AS t FROM few, (VALUES (2), (4), (8)) v(g) GROUP BY ALL
    UNION ALL SELECT g, k.scene, k.obj, n.t FROM keep k, LATERAL (SELECT min(t) AS t FROM few f WHERE f.obj = k.obj AND f.t >= k.t + g) n WHERE n.t IS NOT NULL)""".replace("few AS", "few AS MATERIALIZED"), recursive=True).replace("few AS MATERIALIZED", SIM + ", few AS MATERIALIZED"))
def subsample_tracks(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Boxes kept when each is at least a gap after the last kept one: a fold over each track; twelve clips of scene 4, as the SQL has it."""
    return _subsampled(spark, sf_dir, "scene = 4 and clip < 12")


@query()
def subsample_tracks_all(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The same for all clips of all scenes."""
    return _subsampled(spark, sf_dir)


def _subsampled(spark: SparkSession, sf_dir: str, some: str = "true") -> DataFrame:
    gaps = spark.createDataFrame([(2,), (4,), (8,)], "gap int")
    tracks = simulated(detections(spark, sf_dir)).where("obj >= 0").where(some).groupBy("scene", "obj").agg(F.sort_array(F.collect_list("t")).alias("ts"))
    kept = F.aggregate("ts", F.struct(F.lit(-(10**6)).cast("long").alias("last"), F.lit(0).cast("long").alias("n")), lambda acc, t: F.when(t >= acc["last"] + F.col("gap"), F.struct(t.alias("last"), (acc["n"] + 1).alias("n"))).otherwise(acc))
    return tracks.crossJoin(F.broadcast(gaps)).withColumn("kept", kept["n"]).groupBy("gap", "scene").agg(F.sum("kept").alias("kept"))


@query(with_scene("SELECT scene, sum(e)::BIGINT AS elapsed, sum((e = 0)::INT)::BIGINT AS firsts FROM (SELECT scene, coalesce(t - lag(t) OVER (PARTITION BY scene, clip, obj ORDER BY t), 0) AS e FROM sim WHERE obj >= 0) GROUP BY scene", SIM))
def t_elapsed(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Elapsed frames between the boxes of a prefix; 0 for the first."""
    e = F.coalesce(F.col("t") - F.lag("t").over(Window.partitionBy("scene", "clip", "obj").orderBy("t")), F.lit(0))
    return simulated(detections(spark, sf_dir)).where("obj >= 0").withColumn("e", e).groupBy("scene").agg(F.sum("e").alias("elapsed"), F.count_if(F.col("e") == 0).alias("firsts"))


@query(with_scene("SELECT scene, count(*) AS tracks FROM (SELECT scene, clip, obj, count(*) AS n FROM sim GROUP BY ALL) WHERE n > 1 GROUP BY scene", SIM))
def drop_singletons(spark: SparkSession, sf_dir: str) -> DataFrame:
    return simulated(detections(spark, sf_dir)).groupBy("scene", "clip", "obj").agg(F.count("*").alias("n")).where("n > 1").groupBy("scene").agg(F.count("*").alias("tracks"))


@query()
def variable_gap_frames(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Frames that the variable-gap tracker processes, by tolerance. A clip's boxes go to one task once, and the tolerances share what is known of two frames."""
    levels = (0.1, 0.3, 0.5)

    def run(key, pdf: pd.DataFrame) -> pd.DataFrame:
        t, boxes = pdf["t"].to_numpy(), pdf[["x", "y", "w", "h"]].to_numpy(float)
        order = np.argsort(t, kind="stable")
        cuts, boxes = np.searchsorted(t[order], np.arange(FRAMES + 1)).tolist(), boxes[order]
        at = lambda f: boxes[cuts[f] : cuts[f + 1]]
        least = loop.Confidence(at)
        return pd.DataFrame([(b, *key, len(loop.variable_frames(at, b, least=least))) for b in levels], columns=["tolerance", "scene", "clip", "frames"])

    boxes = simulated(detections(spark, sf_dir, "test", by_clip=True)).select("scene", "clip", "t", "x", "y", "w", "h")
    return boxes.groupBy("scene", "clip").applyInPandas(run, "tolerance double, scene int, clip bigint, frames bigint")


def reference_paths(spark: SparkSession, sf_dir: str, split: str = "train", scenes: str = "scene = 4", clips: int | None = None) -> DataFrame:
    """Resampled path of every true track: scene, category, obj, xs, ys."""

    def run(pdf: pd.DataFrame) -> pd.DataFrame:
        p = resample(pdf.sort_values("t")[["x", "y"]].to_numpy())
        return pd.DataFrame({"scene": [pdf["scene"].iloc[0]], "category": [pdf["category"].iloc[0]], "obj": [pdf["obj"].iloc[0]], "pat": [pdf["pat"].iloc[0]], "xs": [p[:, 0]], "ys": [p[:, 1]]})

    rows = detections(spark, sf_dir, split, clips=clips).where(scenes).select("scene", "category", "obj", "pat", "t", "x", "y")
    return rows.groupBy("scene", "category", "obj").applyInPandas(run, "scene int, category string, obj bigint, pat int, xs array<double>, ys array<double>")


@query()
def resample_paths(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Twenty evenly spaced points of each training track of one scene."""
    return reference_paths(spark, sf_dir)


def _distance() -> F.Column:
    d = F.transform(F.sequence(F.lit(0), F.lit(19)), lambda i: F.sqrt(F.pow(F.get("xs", i) - F.get("oxs", i), 2) + F.pow(F.get("ys", i) - F.get("oys", i), 2)))
    return F.aggregate(d, F.lit(0.0), lambda a, e: a + e) / 20.0


@query()
def path_distance(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Pairs of training tracks nearer than 40 px, blocked by the cells of their mean points, which loses none."""
    mid = lambda c: F.floor(F.aggregate(c, F.lit(0.0), lambda a, e: a + e) / 20.0 / 40.0)
    paths = reference_paths(spark, sf_dir).withColumns({"cx": mid("xs"), "cy": mid("ys")})
    near = F.expr("explode(flatten(transform(sequence(-1, 1), dx -> transform(sequence(-1, 1), dy -> struct(cx + dx AS cx, cy + dy AS cy)))))")
    probe = paths.select("scene", "category", F.col("obj").alias("other"), F.col("xs").alias("oxs"), F.col("ys").alias("oys"), near.alias("c")).select("*", "c.cx", "c.cy").drop("c")
    return paths.join(probe, ["scene", "category", "cx", "cy"]).where("obj < other").withColumn("d", _distance()).where("d <= 40e0").select("scene", "category", "obj", "other", F.round("d", 6).alias("d"))


@query()
def dbscan_clusters(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Clusters of the paths in the sampled training clips, sixty of each scene, by scene and category: a set of fixed size, so a group is one task."""

    def run(pdf: pd.DataFrame) -> pd.DataFrame:
        pdf = pdf.sort_values("obj")
        paths = np.stack([np.stack(pdf["xs"].to_list()), np.stack(pdf["ys"].to_list())], 2)
        return pd.DataFrame({"scene": pdf["scene"], "category": pdf["category"], "obj": pdf["obj"], "pat": pdf["pat"], "cluster_id": dbscan(paths)})

    return reference_paths(spark, sf_dir, scenes="true", clips=CLIPS).groupBy("scene", "category").applyInPandas(run, "scene int, category string, obj bigint, pat int, cluster_id bigint")


@query()
def extended_tracks(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Ends of reduced-rate tracks before and after repair, and their mean distance from the true ends."""
    own = spark.sparkContext.broadcast(models(spark, sf_dir).references)
    boxes = detections(spark, sf_dir, "test")

    def run(pdf: pd.DataFrame) -> pd.DataFrame:
        pdf = pdf.sort_values("t")
        some = pdf[pdf["t"] % 16 == 0]
        if len(some) < 2:
            return pd.DataFrame(columns=["scene", "obj", "before", "after"])
        true, xy = pdf[["x", "y"]].to_numpy()[[0, -1]], some[["x", "y"]].to_numpy()
        ref: Reference | None = own.value.get(int(pdf["scene"].iloc[0]))
        ends = ref.ends(resample(xy)) if ref else None
        got = np.array(ends) if ends is not None else xy[[0, -1]]
        miss = lambda p: float(np.hypot(*(p - true).T).mean())
        return pd.DataFrame([(pdf["scene"].iloc[0], pdf["obj"].iloc[0], miss(xy[[0, -1]]), miss(got))], columns=["scene", "obj", "before", "after"])

    return boxes.groupBy("scene", "clip", "obj").applyInPandas(run, "scene int, obj bigint, before double, after double")


@query()
def end_error(spark: SparkSession, sf_dir: str) -> DataFrame:
    return extended_tracks(spark, sf_dir).groupBy("scene").agg(F.avg("before").alias("before"), F.avg("after").alias("after"), F.count("*").alias("tracks"))


