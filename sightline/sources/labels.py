"""Counts that people made by hand, from text files, and the sinks of what the engine finds."""

from __future__ import annotations

import json

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

COUNTS = "scene int, clip bigint, pat int, n bigint"


def read_counts(spark: SparkSession, path: str, kind: str = "csv") -> DataFrame:
    """Hand counts (scene, clip, pat, n) from CSV with a header or JSON lines. The schema is fixed; broken lines, and rows without a clip or a count of 0
    or more, are left out; of several counts of one pattern in a clip the mean, rounded, stands."""
    reader = spark.read.schema(COUNTS).option("mode", "DROPMALFORMED")
    rows = reader.option("header", True).csv(path) if kind == "csv" else reader.json(path)
    return rows.where("scene is not null and clip is not null and pat is not null and n >= 0").groupBy("scene", "clip", "pat").agg(F.round(F.avg("n")).cast("long").alias("n"))


def write_counts(counts: DataFrame, path: str, kind: str = "csv") -> None:
    rows = counts.select("scene", "clip", "pat", "n").write.mode("overwrite")
    rows.option("header", True).csv(path) if kind == "csv" else rows.json(path)


def write_tracks(tracks: DataFrame, path: str) -> None:
    """Track points as Parquet, one folder for each scene; a row group holds clips in order, so questions about some clips skip the others."""
    tracks.repartition("scene", "clip").sortWithinPartitions("scene", "clip", "track_id", "t").write.mode("overwrite").partitionBy("scene").parquet(path)


def write_curve(spark: SparkSession, curve: list[dict], path: str) -> None:
    """The points of a curve (some dozens) as JSON lines, their settings as one string."""
    rows = [(i, r["config"].id, float(r["sec"]), float(r["accuracy"])) for i, r in enumerate(curve)]
    spark.createDataFrame(rows, "place int, config string, sec double, accuracy double").coalesce(1).write.mode("overwrite").json(path)


def read_curve(spark: SparkSession, path: str) -> list[dict]:
    from ..tune.trial import Config

    rows = spark.read.schema("place int, config string, sec double, accuracy double").json(path).orderBy("place").collect()
    return [{"config": Config(**json.loads(r.config)), "sec": r.sec, "accuracy": r.accuracy} for r in rows]
