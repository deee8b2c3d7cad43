"""Streams of boxes: watermarked windows, sessions, dedup, joins, and the tracker as a stateful operator."""

from __future__ import annotations

import uuid
from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..session import shared_dir
from ..track.assign import assign
from ..track.scorers import iou


def events(spark: SparkSession, sf_dir: str, delay: str = "1 hour") -> DataFrame:
    """The event table as a file stream, its time zone fixed and watermarked."""
    path = f"{sf_dir}/events.parquet"
    schema = spark.read.parquet(path).schema
    stream = spark.readStream.schema(schema).option("pathGlobFilter", "*.parquet").parquet(path if _is_dir(spark, path) else f"{sf_dir}/event[s].parquet")
    return stream.withColumn("ts", F.col("ts").cast("timestamp")).withWatermark("ts", delay)


def table(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The event table, its time zone fixed."""
    return spark.read.parquet(f"{sf_dir}/events.parquet").withColumn("ts", F.col("ts").cast("timestamp"))


def _is_dir(spark: SparkSession, path: str) -> bool:
    p = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(path)
    return p.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).getFileStatus(p).isDirectory()


def drained(stream: DataFrame, mode: str = "append") -> DataFrame:
    """Everything that a stream emits when run over what is there now, written to the shared folder batch by batch and read back.

    A batch overwrites the folder of its own number, so one that runs twice after a failure counts once.
    """
    spark = stream.sparkSession
    base = f"{shared_dir(spark)}/stream-{uuid.uuid4().hex}"

    def put(batch: DataFrame, number: int) -> None:
        batch.write.mode("overwrite").parquet(f"{base}/rows/batch={0 if mode == 'complete' else number}")

    spark.createDataFrame([], stream.schema).write.parquet(f"{base}/rows/batch=-1")
    stream.writeStream.foreachBatch(put).outputMode(mode).option("checkpointLocation", f"{base}/state").trigger(availableNow=True).start().awaitTermination()
    return spark.read.schema(stream.schema).parquet(f"{base}/rows").select(*stream.columns)


def in_order(parts: list[DataFrame]) -> DataFrame:
    """A file stream that delivers the given tables one after another, a batch each. A table is made by many tasks and written as one file."""
    spark = parts[0].sparkSession
    base = f"{shared_dir(spark)}/parts-{uuid.uuid4().hex}"
    for part in parts:
        part.repartition(1).write.mode("append").parquet(base)
    return spark.readStream.schema(parts[0].schema).option("maxFilesPerTrigger", 1).parquet(base)


def tumbling(stream: DataFrame, width: str = "1 day") -> DataFrame:
    return stream.groupBy(F.window("ts", width)).agg(F.count("*").alias("n"), F.approx_count_distinct("user_id").alias("users"))


def sliding(stream: DataFrame) -> DataFrame:
    return stream.groupBy(F.window("ts", "6 hours", "1 hour")).agg(F.count("*").alias("n"))


def sessions(stream: DataFrame) -> DataFrame:
    return stream.groupBy(F.session_window("ts", "12 hours"), "user_id").agg(F.count("*").alias("n"))


def deduplicated(stream: DataFrame) -> DataFrame:
    return stream.dropDuplicatesWithinWatermark(["event_id"])


def tracker(stream: DataFrame, least: float = 0.3, max_lost: int = 3, idle: str = "10 minutes") -> DataFrame:
    """The overlap tracker over a stream of boxes (scene, clip, t, obj, category, x, y, w, h): prefixes are the state of a
    clip and frames must come in order from batch to batch; a box goes on only with a prefix of its category. Prefixes expire by frame count, the
    state of a clip that no box has come for since ``idle`` goes, by the watermark on the column ``ts``; streams without it keep their states. Emits the boxes with their track_id."""
    names = ["bus", "car", "walker"]
    timed = "ts" in stream.columns
    millis = int(idle.split()[0]) * {"seconds": 1000, "minutes": 60_000, "hours": 3_600_000}[idle.split()[1]]

    def step(key, batches: Iterator[pd.DataFrame], state) -> Iterator[pd.DataFrame]:
        if state.hasTimedOut:
            state.remove()
            return
        fresh, alive = 0, []
        if state.exists:
            fresh, flat = state.get
            alive = [list(flat[i : i + 7]) for i in range(0, len(flat), 7)]
        pdf = pd.concat(list(batches)).sort_values(["t", "obj"], kind="stable")
        t_all, every = pdf["t"].to_numpy(), pdf[["x", "y", "w", "h"]].to_numpy(float)
        kinds_all = pdf["category"].map(lambda c: names.index(c) if c in names else len(names)).to_numpy(float)
        cuts = np.flatnonzero(np.diff(t_all, prepend=t_all[0] - 1)).tolist()
        found = np.full(len(pdf), -1, np.int64)
        for lo, hi in zip(cuts, [*cuts[1:], len(pdf)]):
            t, boxes, kinds, ids = int(t_all[lo]), every[lo:hi], kinds_all[lo:hi], found[lo:hi]
            alive = [p for p in alive if t - p[1] <= max_lost + 1]
            if alive:
                last = np.array(alive)
                score = iou(last[:, 3:7], boxes)
                for i, j in assign(np.where(last[:, 2][:, None] == kinds[None], score, -1.0), least):
                    ids[j] = int(alive[i][0])
                    alive[i][1:] = [float(t), float(kinds[j]), *boxes[j].tolist()]
            for j in np.flatnonzero(ids < 0).tolist():
                ids[j] = fresh
                alive.append([float(fresh), float(t), float(kinds[j]), *boxes[j].tolist()])
                fresh += 1
        yield pdf[["scene", "clip", "t", "obj"]].assign(track_id=found)
        state.update((int(fresh), [float(v) for p in alive for v in p]))
        if timed:
            state.setTimeoutTimestamp(max(int(pdf["ts"].max().timestamp() * 1000), state.getCurrentWatermarkMs()) + millis)

    return stream.groupBy("scene", "clip").applyInPandasWithState(
        step, "scene int, clip bigint, t bigint, obj bigint, track_id bigint", "fresh bigint, alive array<double>", "append", "EventTimeTimeout" if timed else "NoTimeout"
    )
