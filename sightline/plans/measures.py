"""Queries on accuracy, cost and published figures."""

from __future__ import annotations

import pandas as pd
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..catalog import query
from ..measure.mota import mota, mota_terms
from ..model.schemas import COST, FRAMES, MISSES
from ..sources.scenes import detections, noise, objects, simulated
from ..tune.trial import Clip, changed, percent, run_clip
from .sql import SIM, with_scene
from .sql import noise as sql_noise
from .tuning import BASE, OURS, clips, models
from .windows import iou

_GAPS = (1, 2, 4, 8, 16, 32)
_ARCHS = ", ".join(f"('{a}', {MISSES[a]}e0, {COST[a][0]!r}::DOUBLE, {COST[a][1]!r}::DOUBLE)" for a in COST)
_POINTS = f"""archs(arch, miss, base, unit) AS (VALUES {_ARCHS}), gaps(gap) AS (VALUES {", ".join(f"({g})" for g in _GAPS)}),
    held AS (SELECT scene, count(*) AS every, count(DISTINCT clip) AS n FROM obj GROUP BY scene),
    looks AS (SELECT scene, clip, obj, t, {sql_noise(17)} / CASE category WHEN 'walker' THEN 1.5e0 ELSE 1e0 END AS z FROM det WHERE NOT (obj % 11 = 0 AND k >= dur // 2 AND k < dur // 2 + 6)),
    seen AS (SELECT scene, clip, obj, arch, gap, count(*) FILTER (z >= miss AND t % gap = 0) AS boxes FROM looks, archs, gaps GROUP BY ALL),
    points AS (SELECT scene, arch || CASE WHEN gap = 1 THEN '_native' ELSE '_reduced' END AS method, count(*) FILTER (boxes >= 2)::DOUBLE / min(every)::DOUBLE AS accuracy,
        round((min(n) * (480 // gap))::DOUBLE * (min(base) + min(unit) * 245760e0), 6) AS sec FROM seen JOIN held USING (scene) JOIN archs USING (arch) GROUP BY scene, arch, gap),
    fine AS (SELECT scene, method, min(sec) AS sec FROM (SELECT *, max(accuracy) OVER (PARTITION BY scene) AS best FROM points) WHERE accuracy >= best - 0.05e0 GROUP BY ALL)"""


def _within5(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Seconds of each method's fastest point within five points of the best share of objects found, by scene: detectors at the native or a reduced rate.

    An object is found when two of its boxes are seen; one pass counts them for all detectors and gaps.
    """
    held = objects(spark, sf_dir).groupBy("scene").agg(F.count("*").alias("every"), F.countDistinct("clip").alias("n"))
    boxes = detections(spark, sf_dir, by_clip=True).where("NOT (obj % 11 = 0 AND k >= dur div 2 AND k < dur div 2 + 6)")
    looks = boxes.selectExpr("scene", "clip", "obj", "t", f"({noise(17)}) / CASE category WHEN 'walker' THEN 1.5e0 ELSE 1e0 END AS z")
    trials = [(a, g) for a in COST for g in _GAPS]
    seen = looks.groupBy("scene", "clip", "obj").agg(*[F.count_if(F.expr(f"z >= {MISSES[a]}e0 AND t % {g} = 0")).alias(f"{a}_{g}") for a, g in trials])
    found = seen.groupBy("scene").agg(*[F.count_if(F.col(f"{a}_{g}") >= 2).alias(f"{a}_{g}") for a, g in trials]).join(F.broadcast(held), "scene")
    points = F.array(*[
        F.struct(
            F.lit(f"{a}_{'native' if g == 1 else 'reduced'}").alias("method"), (F.col(f"{a}_{g}").cast("double") / F.col("every").cast("double")).alias("accuracy"),
            F.round(F.expr(f"double(n * ({FRAMES} div {g})) * ({COST[a][0]!r}D + {COST[a][1]!r}D * 245760e0)"), 6).alias("sec"),
        ) for a, g in trials
    ])
    best = found.select("scene", F.inline(points)).withColumn("best", F.max("accuracy").over(Window.partitionBy("scene")))
    return best.where("accuracy >= best - 0.05e0").groupBy("scene", "method").agg(F.min("sec").alias("sec"))


@query(with_scene("""SELECT round(avg(rest / ours), 3) AS mean_gain, count(*) AS scenes FROM (SELECT scene, min(sec) FILTER (method = 'one_stage_reduced') AS ours, min(sec) FILTER (method <> 'one_stage_reduced') AS rest FROM fine GROUP BY scene)""", _POINTS))
def published_speedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    own = F.col("method") == "one_stage_reduced"
    both = _within5(spark, sf_dir).groupBy("scene").agg(F.min(F.when(own, F.col("sec"))).alias("ours"), F.min(F.when(~own, F.col("sec"))).alias("rest"))
    return both.agg(F.round(F.avg(F.col("rest") / F.col("ours")), 3).alias("mean_gain"), F.count("*").alias("scenes"))


@query(with_scene("SELECT scene, arg_min(method, sec) AS fastest, min(sec) AS sec, max(sec) / min(sec) AS spread FROM fine GROUP BY scene", _POINTS))
def pick_within5(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The fastest method of each scene at matched accuracy."""
    return _within5(spark, sf_dir).groupBy("scene").agg(F.min_by("method", "sec").alias("fastest"), F.min("sec").alias("sec"), (F.max("sec") / F.min("sec")).alias("spread"))


_EST = """est AS (SELECT scene, clip, pat, count(DISTINCT s.obj) AS n FROM (SELECT DISTINCT scene, clip, obj FROM sim WHERE obj >= 0 AND t % 16 = 0) s JOIN obj USING (scene, clip, obj) GROUP BY ALL),
    tru AS (SELECT scene, clip, pat, count(*) AS n FROM obj GROUP BY ALL),
    grid AS (SELECT * FROM (SELECT DISTINCT scene, clip FROM obj), (SELECT unnest(range(0, 5))::INT AS pat)),
    both_ AS (SELECT scene, clip, pat, coalesce(e.n, 0) AS e, coalesce(t.n, 0) AS t FROM grid LEFT JOIN est e USING (scene, clip, pat) LEFT JOIN tru t USING (scene, clip, pat)),
    acc AS (SELECT *, CASE WHEN t > 0 THEN greatest(0e0, 1e0 - abs(e - t)::DOUBLE / t::DOUBLE) WHEN e = 0 THEN 1e0 ELSE 0e0 END AS a FROM both_)"""


def _accuracies(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Counts of objects that the simulated detector sees at gap 16, beside the truth, patterns without any included."""
    objs = objects(spark, sf_dir)
    seen = simulated(detections(spark, sf_dir, gap=16)).where("obj >= 0").select("scene", "clip", "obj").distinct()
    est = seen.join(objs.select("scene", "clip", "obj", "pat"), ["scene", "clip", "obj"]).groupBy("scene", "clip", "pat").agg(F.count("*").alias("e"))
    tru = objs.groupBy("scene", "clip", "pat").agg(F.count("*").alias("t"))
    grid = objs.select("scene", "clip").distinct().withColumn("pat", F.explode(F.expr("sequence(0, 4)")))
    both = grid.join(est, ["scene", "clip", "pat"], "left").join(tru, ["scene", "clip", "pat"], "left").fillna(0, ["e", "t"])
    a = F.when(F.col("t") > 0, F.greatest(F.lit(0.0), 1.0 - F.abs(F.col("e") - F.col("t")).cast("double") / F.col("t").cast("double"))).otherwise((F.col("e") == 0).cast("double"))
    return both.withColumn("a", a)


@query(with_scene("SELECT scene, round(avg(a), 9) AS accuracy, count(*) AS clips FROM (SELECT scene, clip, avg(a) AS a FROM acc GROUP BY scene, clip) GROUP BY scene", SIM, _EST))
def count_accuracy(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Mean percent accuracy over patterns, then clips."""
    return _accuracies(spark, sf_dir).groupBy("scene", "clip").agg(F.avg("a").alias("a")).groupBy("scene").agg(F.round(F.avg("a"), 9).alias("accuracy"), F.count("*").alias("clips"))


@query(with_scene("SELECT scene, round(stddev(a) / sqrt(count(*)), 9) AS stderr FROM (SELECT scene, clip, avg(a) AS a FROM acc GROUP BY scene, clip) GROUP BY scene", SIM, _EST))
def clip_stderr(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Sampling error of the mean over clips."""
    return _accuracies(spark, sf_dir).groupBy("scene", "clip").agg(F.avg("a").alias("a")).groupBy("scene").agg(F.round(F.stddev("a") / F.sqrt(F.count("*")), 9).alias("stderr"))


@query(with_scene("SELECT scene, sum(e - t)::BIGINT AS over, sum(t)::BIGINT AS truth FROM both_ GROUP BY scene", SIM, _EST))
def overcount(spark: SparkSession, sf_dir: str) -> DataFrame:
    return _accuracies(spark, sf_dir).groupBy("scene").agg(F.sum(F.col("e") - F.col("t")).alias("over"), F.sum("t").alias("truth"))


@query(with_scene("SELECT scene, arch, round(sum(sec), 6) AS sec FROM (SELECT DISTINCT scene, clip FROM obj), (VALUES ('one_stage', 480e0 * (0.002e0 + 3.2e-8 * 245760e0)), ('two_stage', 480e0 * (0.01e0 + 1.2e-7 * 245760e0))) c(arch, sec) GROUP BY ALL"))
def naive_cost(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Modelled seconds of the detector at full resolution on every frame."""
    from ..model.schemas import seconds

    costs = spark.createDataFrame([(a, 480 * seconds(a, 640, 384)) for a in ("one_stage", "two_stage")], "arch string, sec double")
    return objects(spark, sf_dir).select("scene", "clip").distinct().crossJoin(F.broadcast(costs)).groupBy("scene", "arch").agg(F.round(F.sum("sec"), 6).alias("sec"))


_PAIRS = f"""near AS (SELECT d.scene, d.clip, d.t, d.obj AS tobj, s.obj AS sobj, {iou('d', 's')} AS v FROM det d JOIN sim s USING (scene, clip, t) WHERE d.clip IN (2, 5, 8, 11) AND scene = 0 AND d.t % 8 = 0),
    best AS (SELECT *, row_number() OVER (PARTITION BY clip, t, tobj ORDER BY v DESC, sobj) AS ra, row_number() OVER (PARTITION BY clip, t, sobj ORDER BY v DESC, tobj) AS rb FROM near WHERE v >= 0.5e0),
    hit AS (SELECT clip, t, tobj, sobj, lag(sobj) OVER (PARTITION BY clip, tobj ORDER BY t) AS prev FROM best WHERE ra = 1 AND rb = 1)"""


@query(with_scene("""SELECT clip, truth, truth - hits AS misses, boxes - hits AS spurious, switches FROM (SELECT clip, count(*) AS truth FROM det WHERE scene = 0 AND clip IN (2, 5, 8, 11) AND t % 8 = 0 GROUP BY clip)
    JOIN (SELECT clip, count(*) AS boxes FROM sim WHERE scene = 0 AND clip IN (2, 5, 8, 11) AND t % 8 = 0 GROUP BY clip) USING (clip)
    JOIN (SELECT clip, count(*) AS hits, count(*) FILTER (prev IS NOT NULL AND prev <> sobj) AS switches FROM hit GROUP BY clip) USING (clip)""", SIM, _PAIRS))
def mota_mutual(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Terms of tracking accuracy by mutual-best matching, identities as the detector carries them; four clips of scene 0, as the SQL has it."""
    return _mutual(spark, sf_dir, "scene = 0 and clip in (2, 5, 8, 11)").drop("scene")


@query()
def mota_mutual_all(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The same terms for every test clip of every scene, clips without a hit too."""
    return _mutual(spark, sf_dir, "clip % 3 = 2", "left")


def _mutual(spark: SparkSession, sf_dir: str, some: str, how: str = "inner") -> DataFrame:
    truth = detections(spark, sf_dir)
    boxes = simulated(truth).where(some).where("t % 8 = 0")
    truth = truth.where(some).where("t % 8 = 0")
    near = truth.alias("d").join(boxes.alias("s"), F.expr("d.scene = s.scene AND d.clip = s.clip AND d.t = s.t")).selectExpr("d.scene", "d.clip", "d.t", "d.obj AS tobj", "s.obj AS sobj", f"{iou('d', 's')} AS v").where("v >= 0.5e0")
    rank = lambda a, b: F.row_number().over(Window.partitionBy("scene", "clip", "t", a).orderBy(F.desc("v"), b))
    hits = near.withColumns({"ra": rank("tobj", "sobj"), "rb": rank("sobj", "tobj")}).where("ra = 1 and rb = 1").withColumn("prev", F.lag("sobj").over(Window.partitionBy("scene", "clip", "tobj").orderBy("t")))
    n = hits.groupBy("scene", "clip").agg(F.count("*").alias("hits"), F.count_if(F.expr("prev is not null and prev <> sobj")).alias("switches"))
    clips_ = truth.groupBy("scene", "clip").agg(F.count("*").alias("truth")).join(boxes.groupBy("scene", "clip").agg(F.count("*").alias("boxes")), ["scene", "clip"], how).join(n, ["scene", "clip"], how)
    return clips_.fillna(0, ["boxes", "hits", "switches"]).selectExpr("scene", "clip", "truth", "truth - hits AS misses", "boxes - hits AS spurious", "switches")


@query()
def mota_study(spark: SparkSession, sf_dir: str) -> DataFrame:
    """MOTA (optimal matching) beside count accuracy for several configurations, on the sampled test clips at one frame a second."""
    truth = clips(spark, sf_dir, "test")
    own = spark.sparkContext.broadcast(models(spark, sf_dir))
    configs = list({c.id: c for c in (changed(b, gap=g, tracker=t) for b in (BASE, OURS) for g in (1, 2, 4, 8) for t in ("overlap", "motion", "recurrent"))}.values())

    def run(key, pdf: pd.DataFrame) -> pd.DataFrame:
        m, scene, out = own.value, int(key[0]), []
        clip = Clip(pdf, (m.sizes or {}).get(scene))
        true = pdf.drop_duplicates("obj")["pat"].value_counts()
        for cfg in configs:
            tracks, got = run_clip(clip, cfg, m.net, (m.references or {}).get(scene))
            terms = mota_terms(pdf[pdf["t"] % 8 == 0], tracks[tracks["t"] % 8 == 0])
            acc = sum(percent(got["counts"][p], float(true.get(p, 0))) for p in range(5)) / 5
            out.append((cfg.id, *key, mota(terms), acc))
        return pd.DataFrame(out, columns=["cfg", "scene", "clip", "mota", "accuracy"])

    return truth.groupBy("scene", "clip").applyInPandas(run, "cfg string, scene int, clip bigint, mota double, accuracy double").groupBy("cfg").agg(F.avg("mota").alias("mota"), F.avg("accuracy").alias("accuracy"))


@query()
def corr_mota(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Correlation of MOTA and count accuracy over the configurations."""
    return mota_study(spark, sf_dir).agg(F.corr("mota", "accuracy").alias("corr"), F.count("*").alias("configs"))
