"""Further queries of the inventory: trained proxies, gates on real features, limit reports, costs of single knobs, page runs."""

from __future__ import annotations

import pandas as pd
from pyspark.ml.classification import LogisticRegression
from pyspark.ml.functions import array_to_vector, vector_to_array
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..catalog import ORACLES, QUERIES, query
from ..detect.proxy import fit_many, tally
from ..measure.limits import ranked_pages
from ..model.schemas import COST, FRAMES, PROXY_COST, PROXY_SIZES, seconds
from ..sources.scenes import detections, frame_cells, noise, objects, simulated, table
from ..tune.trial import changed, outcomes
from ..windows.group import components, grouped
from .gates import walk
from .sql import CELLS, SIM, with_scene
from .sql import noise as sql_noise
from .tuning import BASE, CLIPS, FULL, PAIR_CLIPS, frame, judge, models
from .windows import _S, SIZES

_GAPPED = "gapped AS (SELECT scene, clip, obj, g AS gap, calls, count(*) AS n FROM sim, (VALUES (4, 4), (8, 6), (16, 8)) v(g, calls) WHERE obj >= 0 AND t % g = 0 GROUP BY ALL)"


def _seen(spark: SparkSession, sf_dir: str, gaps: str) -> DataFrame:
    """Boxes of each object by sampling gap: a box goes to every gap that samples its frame, so the boxes are made once."""
    boxes = simulated(detections(spark, sf_dir)).where("obj >= 0")
    return boxes.withColumn("gap", F.explode(F.expr(f"filter(array({gaps}), g -> t % g = 0)"))).groupBy("scene", "clip", "obj", "gap").agg(F.count("*").alias("n"))


@query(with_scene("SELECT scene, gap, count(*) AS tracks, sum(calls)::BIGINT AS calls FROM gapped WHERE n > 1 GROUP BY scene, gap", SIM, _GAPPED))
def refine_frames_cost(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Extra detector calls when both ends of every track are found by bisection inside the skipped frames."""
    tracks = _seen(spark, sf_dir, "4, 8, 16").where("n > 1").groupBy("scene", "gap").agg(F.count("*").alias("tracks"))
    return tracks.withColumn("calls", F.expr("tracks * 2 * bigint(ceil(log2(gap)))"))


@query(with_scene(f"""SELECT scene, gap, seen, round(every // gap * ({COST['one_stage'][0]!r}::DOUBLE + {COST['one_stage'][1]!r}::DOUBLE * 245760e0), 6) AS sec
    FROM (SELECT scene, g AS gap, count(*) AS seen FROM (SELECT scene, clip, obj, g FROM sim, (VALUES (1), (2), (4), (8), (16), (32)) v(g) WHERE obj >= 0 AND t % g = 0 GROUP BY ALL HAVING count(*) > 1) GROUP BY ALL)
    JOIN (SELECT scene, count(DISTINCT clip) * 480 AS every FROM obj GROUP BY scene) USING (scene)""", SIM))
def sweep_gap_cost(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Single-knob curve of the gap: objects seen twice or more, and modelled detector seconds."""
    base, unit = COST["one_stage"]
    every = objects(spark, sf_dir).groupBy("scene").agg((F.countDistinct("clip") * FRAMES).alias("every"))
    seen = _seen(spark, sf_dir, "1, 2, 4, 8, 16, 32").where("n > 1").groupBy("scene", "gap").agg(F.count("*").alias("seen"))
    return seen.join(F.broadcast(every), "scene").select("scene", "gap", "seen", F.round(F.expr("every div gap") * (base + unit * 245760.0), 6).alias("sec"))


_SCORED = f"""scored AS (SELECT b AS threshold, clip, t, cx, cy FROM (SELECT *, 1e0 - {sql_noise(59, 'cx * 100 + cy', 'clip * 480 + t')} / 1000e0 AS score FROM cells WHERE scene = 4 AND clip % 3 = 2), (VALUES (0.2e0), (0.5e0), (0.8e0)) v(b) WHERE score > b),
    reach AS (SELECT *, cx * 100 + cy AS root FROM scored
        UNION SELECT n.*, r.root FROM reach r JOIN scored n ON n.threshold = r.threshold AND n.clip = r.clip AND n.t = r.t AND abs(n.cx - r.cx) <= 1 AND abs(n.cy - r.cy) <= 1),
    box AS (SELECT threshold, clip, t, root, (max(cx) - min(cx) + 1) * 32 AS bw, (max(cy) - min(cy) + 1) * 32 AS bh FROM (SELECT threshold, clip, t, cx, cy, min(root) AS root FROM reach GROUP BY ALL) GROUP BY ALL)"""


@query(with_scene(f"""SELECT threshold, count(*) AS windows, count(DISTINCT clip * 480 + t) AS frames, round(sum((SELECT arg_min(sec, s.w * s.h) FROM sizes s WHERE s.w >= bw AND s.h >= bh)) + count(DISTINCT clip * 480 + t) * {PROXY_COST[0]!r}::DOUBLE, 6) AS sec
    FROM box GROUP BY threshold""", CELLS, _SCORED, _S, recursive=True))
def proxy_grid_nomerge(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Proxy and window seconds by threshold when no components are merged; scores are made once for all thresholds."""
    cells = frame_cells(detections(spark, sf_dir, "test").where("scene = 4")).withColumn("score", F.expr(f"1e0 - ({noise(59, 'cx * 100 + cy', 'clip * 480 + t')}) / 1000e0"))
    passed = cells.withColumn("threshold", F.explode(F.expr("filter(array(0.2e0, 0.5e0, 0.8e0), b -> score > b)")))
    wins = grouped(passed, SIZES, "none", "threshold", "clip", "t").groupBy("threshold", "clip", "t").agg(F.count("*").alias("n"), F.sum("sec").alias("sec"))
    return wins.groupBy("threshold").agg(F.sum("n").alias("windows"), F.count("*").alias("frames"), F.round(F.sum("sec") + F.count("*") * PROXY_COST[0], 6).alias("sec"))


@query("""WITH RECURSIVE seen AS (SELECT DISTINCT strftime(l_shipdate, '%Y-%m-%d') AS day, (floor(l_quantity) - 1)::INT AS cx, least(31, floor(l_extendedprice / 3300e0))::INT AS cy FROM lineitem),
    reach AS (SELECT day, cx, cy, cx * 32 + cy AS root FROM seen UNION SELECT n.day, n.cx, n.cy, r.root FROM reach r JOIN seen n ON n.day = r.day AND abs(n.cx - r.cx) <= 1 AND abs(n.cy - r.cy) <= 1)
    SELECT day, count(DISTINCT root) AS components, count(*) AS cells FROM (SELECT day, cx, cy, min(root) AS root FROM reach GROUP BY ALL) GROUP BY day""")
def lin_components(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Components of the positive cells of each frame of the grid scene; a frame has at most 1,600 cells."""

    @F.pandas_udf("long")
    def count(frames: pd.Series) -> pd.Series:
        return pd.Series([len(components([(c // 32, c % 32) for c in f.tolist()])) for f in frames])

    seen = table(spark, sf_dir, "lineitem").selectExpr("date_format(l_shipdate, 'yyyy-MM-dd') AS day", "int(floor(l_quantity) - 1) AS cx", "int(least(31, floor(l_extendedprice / 3300e0))) AS cy")
    frames = seen.groupBy("day").agg(F.collect_set(F.col("cx") * 32 + F.col("cy")).alias("c"))
    return frames.select("day", count("c").alias("components"), F.size("c").cast("long").alias("cells"))


@query("""WITH part AS (SELECT page_id, unnest(string_split(html, '<')) AS s, generate_subscripts(string_split(html, '<'), 1) AS i FROM pages),
    cell AS (SELECT page_id, i, strpos(s, '>') > 0 AND length(s) - strpos(s, '>') >= 20 AS hit FROM part),
    run AS (SELECT page_id, i - row_number() OVER (PARTITION BY page_id ORDER BY i) AS island FROM cell WHERE hit),
    long AS (SELECT page_id, count(*) AS runs, max(n) AS longest FROM (SELECT page_id, island, count(*) AS n FROM run GROUP BY ALL) GROUP BY page_id)
    SELECT page_id, count(*) AS cells, count(*) FILTER (hit) AS positive, coalesce(any_value(runs), 0) AS runs, coalesce(any_value(longest), 0) AS longest FROM cell LEFT JOIN long USING (page_id) GROUP BY page_id""")
def page_islands(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Pages cut at their tags as rows of cells; runs of cells with 20 characters or more are the windows. One fold over each page, no shuffle."""
    hit = "transform(split(html, '<', -1), s -> locate('>', s) > 0 AND length(s) - locate('>', s) >= 20)"
    zero = "named_struct('run', 0L, 'runs', 0L, 'longest', 0L, 'positive', 0L)"
    step = "CASE WHEN h THEN named_struct('run', a.run + 1, 'runs', a.runs + if(a.run = 0, 1L, 0L), 'longest', greatest(a.longest, a.run + 1), 'positive', a.positive + 1) ELSE named_struct('run', 0L, 'runs', a.runs, 'longest', a.longest, 'positive', a.positive) END"
    pages = table(spark, sf_dir, "pages").where("html is not null").select("page_id", F.expr(hit).alias("hits"))
    return pages.select("page_id", F.size("hits").cast("long").alias("cells"), F.expr(f"aggregate(hits, {zero}, (a, h) -> {step})").alias("f")).select("page_id", "cells", "f.positive", "f.runs", "f.longest")


@query(f"SELECT clip, round(1e0 - (misses + spurious + switches)::DOUBLE / truth::DOUBLE, 9) AS mota FROM ({ORACLES['mota_mutual']})")
def mota(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Tracking accuracy of each clip from the terms of mutual-best matching."""
    return QUERIES["mota_mutual"](spark, sf_dir).select("clip", F.round(1.0 - F.expr("double(misses + spurious + switches) / double(truth)"), 9).alias("mota"))


@query(f"SELECT sum(truth)::BIGINT AS truth, sum(misses)::BIGINT AS misses, sum(spurious)::BIGINT AS spurious, sum(switches)::BIGINT AS switches FROM ({ORACLES['mota_mutual']})")
def mota_terms(spark: SparkSession, sf_dir: str) -> DataFrame:
    return QUERIES["mota_mutual"](spark, sf_dir).agg(*[F.sum(c).alias(c) for c in ("truth", "misses", "spurious", "switches")])


@query()
def limit_proxy_calls(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Detector calls of the proxy-ranked limit query, and their modelled seconds."""
    return QUERIES["limit_proxy"](spark, sf_dir).agg(F.count("*").alias("found"), F.max("calls").alias("calls")).withColumn("sec", F.col("calls") * seconds("one_stage", 640, 384))


@query()
def limit_accuracy(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Both limit queries against the truth: frames found, right ones among them, detector calls of the query phase."""
    right = detections(spark, sf_dir).where("scene = 0 and category = 'car' and y >= 192e0").groupBy("clip", "t").agg(F.count("*").alias("cars")).where("cars >= 4")
    picks = QUERIES["limit_tracks"](spark, sf_dir).selectExpr("'tracks' AS method", "clip", "t", "0L AS calls").unionByName(QUERIES["limit_proxy"](spark, sf_dir).selectExpr("'proxy' AS method", "clip", "t", "calls"))
    # at most forty picks
    return right.join(F.broadcast(picks), ["clip", "t"], "right").groupBy("method").agg(F.count("*").alias("found"), F.count("cars").alias("right"), F.max("calls").alias("calls"))


def vector_scores(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Vectors as frames: vec_id, label and the trained score of 'label is 4 or more'; half of the vectors (by hash) train, the others are scored.

    Vectors that are null, of another length than most, or hold null or non-finite components are left out.
    """
    rows = table(spark, sf_dir, "embeddings").where("label is not null and embedding is not null and forall(embedding, x -> coalesce(abs(x) < float('Infinity'), false))")
    length = rows.groupBy(F.size("embedding").alias("n")).count().agg(F.max_by("n", "count")).first()[0]
    rows = rows.where(F.size("embedding") == (length or 0)).select("vec_id", "label", array_to_vector("embedding").alias("features"), (F.col("label") >= 4).cast("double").alias("y"), F.expr("pmod(xxhash64(vec_id), 2) = 0").alias("learn"))
    model = LogisticRegression(labelCol="y", maxIter=10, regParam=0.01).fit(rows.where("learn"))
    return model.transform(rows.where("not learn")).select("vec_id", "label", vector_to_array("probability")[1].alias("score"))


@query()
def frame_gate_ml(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The frame gate with a trained classifier on real features: frames and positive frames that stay, by threshold."""
    levels = spark.createDataFrame([(b / 10,) for b in range(1, 10)], "threshold double")
    scored = vector_scores(spark, sf_dir).crossJoin(F.broadcast(levels))
    return scored.groupBy("threshold").agg(F.count("*").alias("frames"), F.count_if(F.col("label") >= 4).alias("positive"), F.count_if(F.expr("score >= threshold")).alias("kept"), F.count_if(F.expr("score >= threshold and label >= 4")).alias("kept_positive"))


@query()
def limit_vec(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Limit query over the vectors: by trained score, twenty frames of label 4 or more at distance 5, and the calls made."""
    ranked = vector_scores(spark, sf_dir).select("vec_id", "score", (F.col("label") >= 4).alias("holds"))
    found, calls = walk(((r["vec_id"], r["holds"]) for r in ranked_pages(ranked, "score", "vec_id")), 20, 5)
    return spark.createDataFrame([(i + 1, at, calls) for i, at in enumerate(found)], "pick int, vec_id bigint, calls bigint")


def _proxies(spark: SparkSession, sf_dir: str):
    """Trained on every eighth frame of a sample of training clips of each scene: a set of fixed size."""
    rows = detections(spark, sf_dir, "train", 8, clips=PAIR_CLIPS).selectExpr("clip * 5 + scene AS clip", "t", "x", "y", "w", "h").toPandas()
    return fit_many(rows)


@query()
def proxy_scores_by_res(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Recall and false alarms of trained proxies on test clips, by input size and threshold."""
    sums = tally(detections(spark, sf_dir, "test", 4, clips=CLIPS), _proxies(spark, sf_dir)).groupBy("res", "threshold").agg(*[F.sum(c).alias(c) for c in ("hits", "misses", "alarms", "cells")])
    return sums.withColumns({"recall": F.expr("hits / (hits + misses)"), "alarm_rate": F.expr("alarms / (cells - hits - misses)")})


@query()
def var_rate_predicate(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The variable-rate baseline with and without the predicate north to south: extra frames only for tracks that may satisfy it."""
    configs = [changed(BASE, gap=16, tolerance=b, refine="frames", only=p) for b in (0.1, 0.3, 0.5, 0.7) for p in (None, 2)]
    return frame(spark, [r | {"pattern": r["config"].only} for r in judge(spark, sf_dir)(configs)], pattern="int")


@query()
def limit_phases(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The limit query by phases, in modelled seconds: proxies over all frames and then the detector by rank, against tracks made once and no detector after."""
    own = models(spark, sf_dir)
    ours = outcomes(detections(spark, sf_dir, None, FULL.gap, True).where("scene = 0"), [FULL], own).where("pat = 0").agg(F.sum("sec")).first()[0] or 0.0
    frames = objects(spark, sf_dir).where("scene = 0").select("clip").distinct().count() * FRAMES
    cols, rows = PROXY_SIZES[-1]
    found = {r.method: r for r in QUERIES["limit_accuracy"](spark, sf_dir).collect()}
    prep = {"proxy": frames * (PROXY_COST[0] + PROXY_COST[1] * cols * rows), "tracks": float(ours)}
    out = [(m, prep[m], r.calls * seconds("one_stage", 640, 384), prep[m] + r.calls * seconds("one_stage", 640, 384), r.found, r.right) for m, r in found.items()]
    return spark.createDataFrame(out, "method string, prep_sec double, query_sec double, total_sec double, found bigint, right bigint")
