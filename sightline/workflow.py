"""The whole method as one object: sample clips, find the best configuration, learn from its output, tune, pick a point, extract all tracks."""

from __future__ import annotations

import time

import pandas as pd
from pyspark.sql import DataFrame, SparkSession

from .sources.labels import write_curve, write_tracks
from .sources.scenes import detections
from .tune import greedy
from .tune.trial import Clip, Config, Models, changed, run_clip

TRACKS = "scene int, clip bigint, t bigint, obj bigint, category string, x double, y double, w double, h double, track_id bigint"


class Preprocessor:
    """``fit`` leaves the best configuration, the learnt models and the speed-accuracy curve; ``pick`` chooses a point of it; ``run`` extracts tracks.

    ``seconds`` holds the wall seconds of each phase of ``fit`` and of ``run``.
    """

    def __init__(self, spark: SparkSession, sf_dir: str):
        self.spark, self.sf_dir = spark, sf_dir
        self.best: Config | None = None
        self.models: Models | None = None
        self.curve: list[dict] = []
        self.seconds: dict[str, float] = {}

    def _timed(self, phase: str, work):
        began = time.time()
        out = work()
        self.seconds[phase] = self.seconds.get(phase, 0.0) + time.time() - began
        return out

    def fit(self, points: int = 8, start: Config | None = None, modules: list | None = None) -> Preprocessor:
        from . import catalog  # noqa: F401  the plans are loaded by it
        from .plans import tuning

        spark, sf_dir = self.spark, self.sf_dir
        self.best = self._timed("best configuration", lambda: greedy.find_best(tuning.judge(spark, sf_dir), start or tuning.BASE)[0])
        self.models = self._timed("training", lambda: tuning.models(spark, sf_dir, self.best))
        first = changed(self.best, tracker="recurrent", refine="clusters")
        parts = modules if modules is not None else [greedy.DetectionModule(), greedy.ProxyModule(), greedy.TrackingModule()]
        self.curve = self._timed("tuning", lambda: greedy.tune(tuning.judge(spark, sf_dir, own=self.models), first, parts, points=points)[0])
        return self

    def pick(self, within: float = 0.05, least: float | None = None) -> Config:
        """The fastest point within some accuracy points of the best one, or of a least accuracy."""
        found = greedy.pick(self.curve, within, least)
        if found is None:
            raise ValueError("no point of the curve is accurate enough")
        return found["config"]

    def run(self, cfg: Config, split: str | None = "test", out: str | None = None) -> DataFrame:
        """Track points of all clips of a split (None: of all) under a configuration; with ``out``, written there as Parquet, the curve beside them as JSON, and read back."""
        gap = 1 if cfg.tolerance is not None or cfg.refine == "frames" else cfg.gap
        truth = detections(self.spark, self.sf_dir, split, gap)
        held = self.spark.sparkContext.broadcast(self.models or Models())

        def extract(key, pdf: pd.DataFrame) -> pd.DataFrame:
            own, scene = held.value, int(key[0])
            tracks, _ = run_clip(Clip(pdf, (own.sizes or {}).get(scene)), cfg, own.net, (own.references or {}).get(scene))
            return tracks.assign(scene=scene, clip=int(key[1]))[[c.split()[0] for c in TRACKS.split(", ")]]

        tracks = truth.groupBy("scene", "clip").applyInPandas(extract, TRACKS)
        if out is None:
            return tracks
        self._timed("extraction", lambda: write_tracks(tracks, f"{out}/tracks"))
        if self.curve:
            write_curve(self.spark, self.curve, f"{out}/curve")
        return self.spark.read.schema(TRACKS).parquet(f"{out}/tracks")
