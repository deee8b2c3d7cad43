"""Queries on cells, windows, cover costs and the detector inside windows."""

from __future__ import annotations

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..catalog import query
from ..model.schemas import HEIGHT, WIDTH, window_sizes
from ..sources.scenes import detections, frame_cells, frame_masks, noise, simulated, visible
from ..windows.group import choose_sizes as pick_sizes
from ..windows.group import grouped, signatures
from .sql import CELLS, SIM, with_scene
from .sql import noise as sql_noise

#: The size set of the registered queries; choose_sizes shows how such a set is found.
SIZES = window_sizes([(128, 96), (256, 128)])
_SIZE_ROWS = ", ".join(f"({w}, {h}, {s!r}::DOUBLE)" for w, h, s in SIZES)
_S = f"sizes(w, h, sec) AS (VALUES {_SIZE_ROWS})"
_TEST = "tc AS (SELECT * FROM cells WHERE scene = 4 AND clip % 3 = 2)"
_COMP = """reach AS (
    SELECT clip, t, cx, cy, cx * 100 + cy AS root FROM tc
    UNION SELECT n.clip, n.t, n.cx, n.cy, r.root FROM reach r JOIN tc n ON n.clip = r.clip AND n.t = r.t AND abs(n.cx - r.cx) <= 1 AND abs(n.cy - r.cy) <= 1
), comp AS (SELECT clip, t, cx, cy, min(root) AS root FROM reach GROUP BY ALL)"""
_FIT = "(SELECT arg_min(sec, s.w * s.h) FROM sizes s WHERE s.w >= {w} AND s.h >= {h})"


def _cells(spark: SparkSession, sf_dir: str) -> DataFrame:
    return frame_cells(detections(spark, sf_dir, "test").where("scene = 4"))


@query(with_scene(f"SELECT scene, cx, cy, count(*) AS frames FROM (SELECT *, {sql_noise(53, 'cx * 100 + cy', 'clip * 480 + t')} AS z FROM cells) WHERE z >= 30 GROUP BY ALL", CELLS))
def proxy_noisy_cells(spark: SparkSession, sf_dir: str) -> DataFrame:
    """A proxy that misses three per cent of the positive cells, by hash."""
    return frame_cells(detections(spark, sf_dir)).where(f"({noise(53, 'cx * 100 + cy', 'clip * 480 + t')}) >= 30").groupBy("scene", "cx", "cy").agg(F.count("*").alias("frames"))


@query(with_scene(f"SELECT scene, b AS threshold, count(*) AS cells FROM (SELECT *, 1e0 - {sql_noise(59, 'cx * 100 + cy', 'clip * 480 + t')} / 1000e0 AS score FROM cells), (VALUES (0.1e0), (0.5e0), (0.9e0)) v(b) WHERE score > b GROUP BY ALL", CELLS))
def positive_cells(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Cells that stay above each threshold for hashed scores."""
    scored = frame_cells(detections(spark, sf_dir)).withColumn("score", F.expr(f"1e0 - ({noise(59, 'cx * 100 + cy', 'clip * 480 + t')}) / 1000e0"))
    levels = spark.createDataFrame([(0.1,), (0.5,), (0.9,)], "threshold double")
    return scored.crossJoin(F.broadcast(levels)).where("score > threshold").groupBy("scene", "threshold").agg(F.count("*").alias("cells"))


@query(with_scene("SELECT clip, t, count(DISTINCT root) AS components, count(*) AS cells FROM comp GROUP BY clip, t", CELLS, _TEST, _COMP, recursive=True))
def cell_components(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Connected components of the positive cells of each test frame of one scene."""
    from ..windows.group import components

    @F.pandas_udf("long")
    def count(frames: pd.Series) -> pd.Series:
        return pd.Series([len(components([(c % 1024, c // 1024) for c in f.tolist()])) for f in frames])

    frames = _cells(spark, sf_dir).groupBy("clip", "t").agg(F.collect_set(F.col("cx") + 1024 * F.col("cy")).alias("c"))
    return frames.select("clip", "t", count("c").alias("components"), F.size("c").cast("long").alias("cells"))


_SPANS = """spans AS (SELECT ((ceil(least(x + w / 2e0, 640e0) / 32e0) - floor(greatest(x - w / 2e0, 0e0) / 32e0)) * 32e0)::INT AS bw, ((ceil(least(y + h / 2e0, 384e0) / 32e0) - floor(greatest(y - h / 2e0, 0e0) / 32e0)) * 32e0)::INT AS bh
    FROM det WHERE x + w / 2e0 > 0e0 AND x - w / 2e0 < 640e0 AND y + h / 2e0 > 0e0 AND y - h / 2e0 < 384e0), boxes AS (SELECT bw, bh, count(*) AS n FROM spans GROUP BY ALL)"""


@query(with_scene(f"SELECT bw, bh, n, {_FIT.format(w='bw', h='bh')} AS sec FROM boxes", _SPANS, _S))
def fit_size(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Sizes of the boxes' cells, how many boxes have each, and the seconds of the smallest window that holds it."""
    sizes = F.array(*[F.struct(F.lit(w * h).alias("area"), F.lit(sec).alias("sec"), F.lit(w).alias("w"), F.lit(h).alias("h")) for w, h, sec in SIZES])
    span = lambda p, d, most: f"int(greatest(ceil(least({p} + {d} / 2e0, {most}e0) / 32e0) - floor(greatest({p} - {d} / 2e0, 0e0) / 32e0), 0)) * 32"
    boxes = detections(spark, sf_dir).selectExpr(f"{span('x', 'w', WIDTH)} AS bw", f"{span('y', 'h', HEIGHT)} AS bh")
    # boxes outside have no cell; a filter on what is grouped by would be pushed below the boxes' making
    some = boxes.groupBy("bw", "bh").agg(F.count("*").alias("n"), F.max("bw").alias("w0"), F.max("bh").alias("h0")).where("w0 > 0 and h0 > 0")
    return some.select("bw", "bh", "n", F.array_min(F.filter(sizes, lambda s: (s["w"] >= F.col("bw")) & (s["h"] >= F.col("bh"))))["sec"].alias("sec"))


def _mode(mode: str):
    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        wins = grouped(_cells(spark, sf_dir), SIZES, mode)
        return wins.groupBy("clip").agg(F.count("*").alias("windows"), F.round(F.sum("sec"), 6).alias("sec"))

    return run


_BOXES = "boxes AS (SELECT clip, t, root, (max(cx) - min(cx) + 1) * 32 AS bw, (max(cy) - min(cy) + 1) * 32 AS bh, min(cx) * 32 AS x0, min(cy) * 32 AS y0 FROM comp GROUP BY clip, t, root)"
_SUM = "SELECT clip, count(*) AS windows, round(sum(sec), 6) AS sec FROM ({}) GROUP BY clip"
query(with_scene(_SUM.format(f"SELECT clip, {_FIT.format(w='bw', h='bh')} AS sec FROM boxes"), CELLS, _TEST, _COMP, _BOXES, _S, recursive=True), "windows_nomerge")(_mode("none"))
query(with_scene(_SUM.format(f"SELECT clip, {_FIT.format(w='32', h='32')} AS sec FROM tc"), CELLS, _TEST, _S), "windows_percell")(_mode("cell"))
query(with_scene(_SUM.format(f"SELECT DISTINCT clip, t, {_FIT.format(w='640', h='384')} AS sec FROM tc"), CELLS, _TEST, _S), "windows_frame")(_mode("frame"))
query(with_scene(_SUM.format(f"SELECT clip, {_FIT.format(w='bw', h='bh')} AS sec FROM (SELECT clip, t, (max(cx) - min(cx) + 1) * 32 AS bw, (max(cy) - min(cy) + 1) * 32 AS bh FROM tc GROUP BY clip, t)"), CELLS, _TEST, _S), "windows_bbox")(_mode("bbox"))
query(None, "windows_cost_total")(_mode("merge"))


@query()
def windows(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Windows of every test frame of one scene by greedy merging."""
    return grouped(_cells(spark, sf_dir), SIZES)


@query()
def windows_all(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Windows and seconds of the test frames of every scene by greedy merging, busy scenes too."""
    wins = grouped(frame_cells(detections(spark, sf_dir, "test")), SIZES)
    return wins.groupBy("scene").agg(F.countDistinct("clip", "t").alias("frames"), F.count("*").alias("windows"), F.sum("sec").alias("sec"))


@query(with_scene(f"SELECT pw, ph, count(*) AS n, round(sum(sec), 6) AS sec FROM (SELECT s.w AS pw, s.h AS ph, s.sec FROM boxes, LATERAL (SELECT * FROM sizes z WHERE z.w >= bw AND z.h >= bh ORDER BY z.w * z.h LIMIT 1) s) GROUP BY ALL", CELLS, _TEST, _COMP, _BOXES, _S, recursive=True))
def cover_cost(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Cost of the windows by size: window counts joined with the cost table."""
    costs = spark.createDataFrame(SIZES, "pw int, ph int, cost double")
    wins = grouped(_cells(spark, sf_dir), SIZES, "none").join(F.broadcast(costs), ["pw", "ph"])
    return wins.groupBy("pw", "ph").agg(F.count("*").alias("n"), F.round(F.sum("cost"), 6).alias("sec"))


@query()
def frame_time(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Detector seconds of each test frame under the perfect proxy, merged and unmerged."""
    cells = _cells(spark, sf_dir)
    one = grouped(cells, SIZES).groupBy("clip", "t").agg(F.sum("sec").alias("merged"))
    two = grouped(cells, SIZES, "none").groupBy("clip", "t").agg(F.sum("sec").alias("unmerged"))
    return one.join(two, ["clip", "t"])


@query()
def choose_sizes(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Three window sizes for each scene, chosen on the training split."""
    found = pick_sizes(frame_cells(detections(spark, sf_dir, "train", 8)), 3, sample=40)
    return spark.createDataFrame([(s, i, w, h) for s, sizes in found.items() for i, (w, h) in enumerate(sizes)], "scene int, place int, w int, h int")


_NM = "train AS (SELECT * FROM cells WHERE scene = 4 AND clip % 3 = 0 AND t % 16 = 0)"


@query(with_scene(f"""SELECT w, h, round(sum(least_sec), 6) AS total FROM (
    SELECT c.w, c.h, b.clip, b.t, b.root, CASE WHEN c.w >= bw AND c.h >= bh THEN 0.002e0 + 3.2e-8 * (c.w * c.h)::DOUBLE ELSE 0.002e0 + 3.2e-8 * 245760e0 END AS least_sec FROM boxes b,
    (SELECT (w.range * 32)::INT AS w, (h.range * 32)::INT AS h FROM range(1, 21) w, range(1, 13) h) c) GROUP BY w, h""", CELLS, _NM, _COMP.replace("tc", "train"), _BOXES, recursive=True))
def choose_sizes_nomerge(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Total seconds of one scene's training frames for each second size, without merging: the table that a round of the choice takes its minimum of."""
    from ..windows.group import total_times

    cells = frame_cells(detections(spark, sf_dir, "train", 16).where("scene = 4"))
    every = [(w * 32, h * 32) for w in range(1, 21) for h in range(1, 13)]
    return total_times(signatures(cells), [(640, 384)], every, "none").select("w", "h", F.round("total", 6).alias("total"))


_IOU = "greatest(0e0, least({a}.x + {a}.w / 2e0, {b}.x + {b}.w / 2e0) - greatest({a}.x - {a}.w / 2e0, {b}.x - {b}.w / 2e0)) * greatest(0e0, least({a}.y + {a}.h / 2e0, {b}.y + {b}.h / 2e0) - greatest({a}.y - {a}.h / 2e0, {b}.y - {b}.h / 2e0))"


def iou(a: str, b: str) -> str:
    inter = _IOU.format(a=a, b=b)
    return f"({inter}) / ({a}.w * {a}.h + {b}.w * {b}.h - ({inter}))"


@query(with_scene(f"SELECT clip, count(*) AS n FROM (SELECT * FROM sim WHERE scene = 0 AND clip % 3 = 2) a WHERE NOT EXISTS (SELECT 1 FROM sim b WHERE b.scene = 0 AND b.clip = a.clip AND b.t = a.t AND b.category = a.category AND b.obj <> a.obj AND (b.score > a.score OR b.score = a.score AND b.obj < a.obj) AND {iou('a', 'b')} > 0.6e0) GROUP BY clip", SIM))
def dedupe_boxes(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Boxes without a better box of their category over them: one pass of non-maximum suppression as self-join and anti-join."""
    boxes = simulated(detections(spark, sf_dir, "test").where("scene = 0"))
    a, b = boxes.alias("a"), boxes.alias("b")
    worse = F.expr(f"a.clip = b.clip AND a.t = b.t AND a.category = b.category AND a.obj <> b.obj AND (b.score > a.score OR b.score = a.score AND b.obj < a.obj) AND {iou('a', 'b')} > 0.6e0")
    return a.join(b, worse, "left_anti").groupBy("clip").agg(F.count("*").alias("n"))


_INSIDE = f"""wins AS (SELECT b.clip, b.t, greatest(0, least(x0, 640 - s.w)) AS px, greatest(0, least(y0, 384 - s.h)) AS py, s.w AS pw, s.h AS ph, s.sec FROM boxes b,
    LATERAL (SELECT * FROM sizes z WHERE z.w >= bw AND z.h >= bh ORDER BY z.w * z.h LIMIT 1) s)"""


def _inside(boxes: DataFrame, wins: DataFrame) -> DataFrame:
    """Boxes whose centre lies in a window of their frame: an equi-join on the frame with a range rest."""
    return boxes.alias("b").join(wins.alias("w"), F.expr("b.clip = w.clip AND b.t = w.t AND b.x BETWEEN w.px AND w.px + w.pw AND b.y BETWEEN w.py AND w.py + w.ph"), "left_semi")


@query(with_scene("SELECT clip, count(*) AS n FROM sim d WHERE scene = 4 AND clip % 3 = 2 AND EXISTS (SELECT 1 FROM wins w WHERE w.clip = d.clip AND w.t = d.t AND d.x BETWEEN px AND px + pw AND d.y BETWEEN py AND py + ph) GROUP BY clip", CELLS, SIM, _TEST, _COMP, _BOXES, _S, _INSIDE, recursive=True))
def detect_in_windows(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Boxes that a detector run in the unmerged windows would return."""
    truth = detections(spark, sf_dir, "test").where("scene = 4")
    return _inside(simulated(truth), grouped(frame_cells(truth), SIZES, "none")).groupBy("clip").agg(F.count("*").alias("n"))


@query(with_scene("SELECT clip, sum(covered::INT)::BIGINT AS covered, count(*) AS boxes FROM (SELECT d.clip, EXISTS (SELECT 1 FROM wins w WHERE w.clip = d.clip AND w.t = d.t AND greatest(0e0, d.x - d.w / 2e0) >= px AND least(640e0, d.x + d.w / 2e0) <= px + pw AND greatest(0e0, d.y - d.h / 2e0) >= py AND least(384e0, d.y + d.h / 2e0) <= py + ph) AS covered FROM det d WHERE scene = 4 AND clip % 3 = 2 AND x + d.w / 2e0 > 0e0 AND x - d.w / 2e0 < 640e0 AND y + d.h / 2e0 > 0e0 AND y - d.h / 2e0 < 384e0) GROUP BY clip", CELLS, _TEST, _COMP, _BOXES, _S, _INSIDE, recursive=True))
def proxy_recall(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Boxes that lie inside one window, of all boxes: the proxy's recall, 1 for the perfect proxy."""
    truth = visible(detections(spark, sf_dir, "test").where("scene = 4"))
    wins = grouped(frame_cells(truth), SIZES, "none")
    hit = truth.alias("b").join(wins.alias("w"), F.expr("b.clip = w.clip AND b.t = w.t AND greatest(0e0, b.x - b.w / 2e0) >= px AND least(640e0, b.x + b.w / 2e0) <= px + pw AND greatest(0e0, b.y - b.h / 2e0) >= py AND least(384e0, b.y + b.h / 2e0) <= py + ph"), "left_semi")
    return truth.groupBy("clip").agg(F.count("*").alias("boxes")).join(hit.groupBy("clip").agg(F.count("*").alias("covered")), "clip", "left").select("clip", F.coalesce("covered", F.lit(0)).alias("covered"), "boxes")


@query(with_scene("SELECT clip, sum(pw * ph)::BIGINT AS area, count(DISTINCT t) AS frames FROM wins GROUP BY clip", CELLS, _TEST, _COMP, _BOXES, _S, _INSIDE, recursive=True))
def area_fraction(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Pixels that the detector sees and frames it runs on."""
    wins = grouped(_cells(spark, sf_dir), SIZES, "none")
    return wins.groupBy("clip").agg(F.sum((F.col("pw") * F.col("ph")).cast("long")).alias("area"), F.countDistinct("t").alias("frames"))


@query(with_scene("SELECT scene, 1e0 - count(DISTINCT (clip, t)) / (480e0 * count(DISTINCT clip)) AS frames_idle, 1e0 - count(*) / (240e0 * 480e0 * count(DISTINCT clip)) AS area_idle FROM cells GROUP BY scene", CELLS))
def skippable(spark: SparkSession, sf_dir: str) -> DataFrame:
    """What frame gating and what cells can skip, from busy to sparse scenes."""
    cells = F.expr("bit_count(m0) + bit_count(m1) + bit_count(m2) + bit_count(m3)")
    frames = frame_masks(detections(spark, sf_dir)).withColumn("n", cells).groupBy("scene", "clip").agg(F.count("*").alias("frames"), F.sum("n").alias("n"))
    return frames.groupBy("scene").agg((1.0 - F.sum("frames") / (480.0 * F.count("*"))).alias("frames_idle"), (1.0 - F.sum("n") / (240.0 * 480.0 * F.count("*"))).alias("area_idle"))


@query()
def lin_windows_cost(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Grouping on the dense grid scene: windows and cost per frame."""
    from ..sources.scenes import table

    seen = table(spark, sf_dir, "lineitem").selectExpr("datediff(date(l_shipdate), date'1990-01-01') AS t", "int((l_quantity - 1) * 20 / 50) AS cx", "int(least(11, floor(l_extendedprice / 9000e0))) AS cy")
    return grouped(seen.distinct(), SIZES, "merge", "t").groupBy("t").agg(F.count("*").alias("windows"), F.sum("sec").alias("sec"))
