"""Scenes on the given tables, as column expressions: objects, true detections and a simulated detector."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..model.schemas import FRAMES, HEIGHT, MISSES, SPURIOUS, WIDTH

#: Control points of the five paths: start, bend, end.
PATHS = [
    ((0, 192), (320, 192), (640, 192)),
    ((640, 240), (320, 240), (0, 240)),
    ((280, 0), (280, 192), (280, 384)),
    ((360, 384), (360, 212), (640, 212)),
    ((0, 160), (300, 160), (300, 0)),
]


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def objects(spark: SparkSession, sf_dir: str, split: str | None = None) -> DataFrame:
    """One row per object of the orders scene. Nations are a fixed small table and broadcast; customers join by key."""
    orders = table(spark, sf_dir, "orders").select("o_orderkey", "o_custkey", "o_totalprice", "o_orderstatus")
    customers = table(spark, sf_dir, "customer").select("c_custkey", "c_nationkey", "c_mktsegment")
    nations = table(spark, sf_dir, "nation").select("n_nationkey", "n_regionkey")
    cents = F.round(F.col("o_totalprice") * 100e0).cast("long")
    kind = F.when(F.col("c_mktsegment") == "MACHINERY", "bus").when(F.col("c_mktsegment") == "BUILDING", "walker").otherwise("car")
    out = (
        orders.join(customers, F.col("o_custkey") == F.col("c_custkey")).join(F.broadcast(nations), F.col("c_nationkey") == F.col("n_nationkey"))
        .where(F.expr("o_orderkey % (2 * (1 + n_regionkey)) = 0"))
        .withColumns({"cents": cents, "category": kind})
        .select(
            F.col("n_regionkey").cast("int").alias("scene"), F.expr("o_orderkey div 250").alias("clip"), F.col("o_orderkey").alias("obj"),
            F.expr("int(n_nationkey div 5)").alias("pat"), "category",
            F.expr("CASE category WHEN 'bus' THEN 96e0 WHEN 'car' THEN 64e0 ELSE 32e0 END").alias("w"),
            F.expr("CASE category WHEN 'bus' THEN 64e0 WHEN 'car' THEN 40e0 ELSE 48e0 END").alias("h"),
            F.expr("cents % 480").alias("t_in"),
            F.expr("(32 + (cents div 480) % 97) * CASE category WHEN 'walker' THEN 2 ELSE 1 END").alias("dur"),
            (F.col("o_orderstatus") == "P").alias("braking"), F.expr("(c_custkey % 5 - 2) * 6e0").alias("lane"), F.expr("o_custkey % 12").alias("vec_id"),
        )
    )
    return out.where(F.expr(f"clip % 3 = {('train', 'val', 'test').index(split)}")) if split else out


def _along(axis: int) -> Column:
    """Quadratic curve of the object's path at u."""
    u = F.col("u")
    out = None
    for pat, points in enumerate(PATHS):
        a, b, c = (float(p[axis]) for p in points)
        at = (1e0 - u) * (1e0 - u) * F.lit(a) + 2e0 * u * (1e0 - u) * F.lit(b) + u * u * F.lit(c)
        out = F.when(F.col("pat") == pat, at) if out is None else out.when(F.col("pat") == pat, at)
    return out


def sampled(spark: SparkSession, sf_dir: str, split: str, clips: int = 60) -> DataFrame:
    """At most ``clips`` clips of each scene's split, those with the smallest hash: the sample that the method trains and tunes on."""
    draw = F.expr("((clip * 7919 + scene * 104729) % 1000003) % 1000")
    every = objects(spark, sf_dir, split).select("scene", "clip").distinct().withColumn("draw", draw)
    place = F.row_number().over(Window.partitionBy("scene").orderBy("draw", "clip"))
    return every.withColumn("place", place).where(F.col("place") <= clips).select("scene", "clip", "place")


def detections(spark: SparkSession, sf_dir: str, split: str | None = None, gap: int = 1, first: bool = False, clips: int | None = None, by_clip: bool = False) -> DataFrame:
    """True boxes at every ``gap``-th frame: scene, clip, t, obj, category, x, y, w, h, k, dur, pat.

    Only these frames are made. ``first``: each object's first box too; ``clips``: of so many sampled clips a scene. ``by_clip``: a
    clip's objects are brought together before their boxes are made, so that what groups by clip or frame moves no boxes.
    """
    rows = objects(spark, sf_dir, split)
    if by_clip:
        rows = rows.repartition(max(64, 4 * spark.sparkContext.defaultParallelism), "scene", "clip")
    if clips is not None and split:
        rows = rows.join(F.broadcast(sampled(spark, sf_dir, split, clips).select("scene", "clip")), ["scene", "clip"], "left_semi")  # that many rows a scene
    last, start = "least(dur, 479L - t_in)", f"(({gap}L - t_in % {gap}L) % {gap}L)"
    some = f"sequence({start}, {last}, {gap}L)"
    if gap > 1:
        some = f"CASE WHEN {start} > {last} THEN {'array(0L)' if first else 'array()'} " + (f"WHEN {start} > 0L THEN concat(array(0L), {some}) " if first else "") + f"ELSE {some} END"
    step = rows.withColumn("k", F.explode(F.expr(some))).withColumn("t", F.col("t_in") + F.col("k"))
    v = F.col("k").cast("double") / F.col("dur").cast("double")
    moved = step.withColumn("u", F.when(F.col("braking"), v * (2e0 - v)).otherwise(v))
    return moved.withColumns({"x": _along(0) + F.col("lane"), "y": _along(1) + F.col("lane")}).select(
        "scene", "clip", "t", "obj", "category", "x", "y", "w", "h", "k", "dur", "pat", "vec_id"
    )


def noise(salt: int, obj: str = "obj", t: str = "t") -> str:
    return f"((({obj}) * 1000003L + ({t}) * 7919L + {salt * 104729}L) % 1000003L) % 1000L"


def simulated(truth: DataFrame, arch: str = "one_stage", res: int = WIDTH, conf: float = 0.25) -> DataFrame:
    """Boxes of the simulated detector over ``truth``: misses, scores, jitter, the split defect and spurious boxes.

    A spurious box belongs to a frame, so frames come from ``truth`` (those with an object).
    """
    miss = f"{MISSES[arch]}e0 * ({WIDTH}e0 / {res}e0) * CASE category WHEN 'walker' THEN 1.5e0 ELSE 1e0 END"
    span = 1000e0 / res
    jitter = lambda salt: f"(({noise(salt)}) / 500e0 - 1e0) * {span!r}"
    seen = truth.where(f"({noise(17)}) >= {miss} AND NOT (obj % 11 = 0 AND k >= dur div 2 AND k < dur div 2 + 6)").selectExpr(
        "scene", "clip", "t", "obj", "category", f"x + {jitter(29)} AS x", f"y + {jitter(31)} AS y", "w", "h", f"1e0 - ({noise(23)}) / 2000e0 AS score"
    )
    frame = "clip * 5 + scene"
    ghosts = truth.select("scene", "clip", "t").distinct().where(f"({noise(41, frame)}) < {SPURIOUS[arch]}").selectExpr(
        "scene", "clip", "t", "-1 - t AS obj", "'car' AS category", f"16e0 + 32e0 * (({noise(43, frame)}) % 20)  AS x", f"16e0 + 32e0 * (({noise(47, frame)}) % 12) AS y", "64e0 AS w", "40e0 AS h", "0.6e0 AS score"
    )
    return seen.unionByName(ghosts).where(F.col("score") >= conf)


def visible(boxes: DataFrame) -> DataFrame:
    """Boxes with some area on the canvas."""
    return boxes.where(f"x + w / 2e0 > 0e0 AND x - w / 2e0 < {WIDTH}e0 AND y + h / 2e0 > 0e0 AND y - h / 2e0 < {HEIGHT}e0")


def frame_masks(boxes: DataFrame) -> DataFrame:
    """The cells that the boxes of a frame touch, as bits: scene, clip, t, m0 to m3, three rows of twenty cells each.

    A box's bits follow from its corners, and the boxes of a frame are combined by a bit-wise or, so no row is made for a cell. The rows that a
    box has among three are a sum of powers of 2 ** 20 in closed form: code that is small enough for the JVM to compile.
    """
    left, right = "floor(greatest(x - w / 2e0, 0e0) / 32e0)", f"ceil(least(x + w / 2e0, {WIDTH}e0) / 32e0)"
    top, bottom = "floor(greatest(y - h / 2e0, 0e0) / 32e0)", f"ceil(least(y + h / 2e0, {HEIGHT}e0) / 32e0)"
    # boxes outside get no cell here: a filter on them would be pushed below the boxes' making, with their curves again in every part of it
    cut = boxes.selectExpr("scene", "clip", "t", f"int({left}) AS x0", f"int({right}) AS x1", f"int({top}) AS y0", f"int({bottom}) AS y1")
    power = lambda y, k: f"shiftleft(1L, 20 * least(greatest({y} - {3 * k}, 0), 3))"
    rows = cut.selectExpr("scene", "clip", "t", "shiftleft(1L, greatest(x0, x1)) - shiftleft(1L, x0) AS across", *[f"({power('greatest(y0, y1)', k)} - {power('y0', k)}) div 1048575L AS r{k}" for k in range(4)])
    return rows.groupBy("scene", "clip", "t").agg(*[F.bit_or(F.expr(f"across * r{k}")).alias(f"m{k}") for k in range(4)]).where("(m0 | m1 | m2 | m3) != 0")


def frame_cells(boxes: DataFrame) -> DataFrame:
    """The perfect proxy: distinct cells of every frame that some box touches."""
    lit = "explode(filter(sequence(0, 239), i -> getbit(CASE int(i / 60) WHEN 0 THEN m0 WHEN 1 THEN m1 WHEN 2 THEN m2 ELSE m3 END, i % 60) = 1))"
    return frame_masks(boxes).selectExpr("scene", "clip", "t", f"{lit} AS i").selectExpr("scene", "clip", "t", "i % 20 AS cx", "int(i / 20) AS cy")


def frames_of(spark: SparkSession, sf_dir: str, gap: int = 1) -> DataFrame:
    """All frames of the clips that have objects, empty frames too."""
    clips = objects(spark, sf_dir).select("scene", "clip").distinct()
    return clips.select("scene", "clip", F.explode(F.expr(f"sequence(0L, {FRAMES - 1}L, {gap}L)")).alias("t"))
