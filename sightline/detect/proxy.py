"""Trained segmentation proxies: one small model for each input size, over the neighbourhood of a coarse cell."""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame

from ..model.schemas import CELL, HEIGHT, PROXY_SIZES, WIDTH


def brightness(boxes: np.ndarray, t: int, res: int) -> tuple[np.ndarray, np.ndarray]:
    """A frame at proxy size ``res``: noisy intensity of every coarse cell, and whether some box touches it.

    No pixels are at hand, so the share of a cell that boxes cover stands for them; noise grows as the input shrinks.
    """
    cols, rows = PROXY_SIZES[res][0] // CELL, PROXY_SIZES[res][1] // CELL
    wide, high = WIDTH / cols, HEIGHT / rows
    cover = np.zeros((rows, cols))
    for x, y, w, h in boxes:
        across = np.clip(np.minimum(x + w / 2, (np.arange(cols) + 1) * wide) - np.maximum(x - w / 2, np.arange(cols) * wide), 0, None)
        down = np.clip(np.minimum(y + h / 2, (np.arange(rows) + 1) * high) - np.maximum(y - h / 2, np.arange(rows) * high), 0, None)
        cover += np.outer(down, across) / (wide * high)
    noise = np.random.default_rng((t, res)).normal(0, 0.05 + 0.02 * res, cover.shape)
    return np.minimum(cover, 1) + noise, cover > 0


def patches(image: np.ndarray) -> np.ndarray:
    """Rows of a cell's 3 x 3 neighbourhood, the border repeated, and a constant."""
    edge = np.pad(image, 1, mode="edge")
    rows, cols = image.shape
    near = [edge[i : i + rows, j : j + cols].ravel() for i in range(3) for j in range(3)]
    return np.stack([*near, near[4] ** 2, np.ones(image.size)], 1)


@dataclass
class SegmentProxy:
    """Logistic model over cell patches; ``fit`` takes a training set of fixed size, ``score`` runs on every frame."""

    res: int
    weights: np.ndarray | None = None

    def fit(self, frames: list[tuple[int, np.ndarray]], steps: int = 25, ridge: float = 1e-3) -> SegmentProxy:
        """Newton steps on the cells of ``frames``, (t, boxes) each."""
        seen = [brightness(boxes, t, self.res) for t, boxes in frames]
        x, y = np.concatenate([patches(i) for i, _ in seen]), np.concatenate([m.ravel() for _, m in seen]).astype(float)
        w = np.zeros(x.shape[1])
        for _ in range(steps):
            p = 1 / (1 + np.exp(-np.clip(x @ w, -30, 30)))
            slope = (x * (p * (1 - p))[:, None]).T @ x + ridge * len(x) * np.eye(len(w))
            step = np.linalg.solve(slope, x.T @ (y - p) - ridge * len(x) * w)
            w += step
            if np.abs(step).max() < 1e-6:
                break
        self.weights = w
        return self

    def score(self, boxes: np.ndarray, t: int) -> tuple[np.ndarray, np.ndarray]:
        """Scores of all coarse cells and their labels."""
        image, label = brightness(boxes, t, self.res)
        return 1 / (1 + np.exp(-np.clip(patches(image) @ self.weights, -30, 30))), label.ravel()


def fit_many(rows: pd.DataFrame) -> list[SegmentProxy]:
    """A model for each input size, from frames with a box or more."""
    frames = [(int(t), g[["x", "y", "w", "h"]].to_numpy(float)) for (_, t), g in rows.groupby(["clip", "t"])]
    return [SegmentProxy(res).fit(frames) for res in range(len(PROXY_SIZES))]


def tally(boxes: DataFrame, proxies: list[SegmentProxy], thresholds: tuple[float, ...] = (0.1, 0.3, 0.5, 0.7)) -> DataFrame:
    """Hits, misses and false alarms of cells by clip, size and threshold: all models score a frame that is read once."""
    held = boxes.sparkSession.sparkContext.broadcast(proxies)  # a dozen weights each

    def run(key, pdf: pd.DataFrame) -> pd.DataFrame:
        sums: dict[tuple[int, float], np.ndarray] = {}
        for t, g in pdf.groupby("t"):
            for proxy in held.value:
                score, label = proxy.score(g[["x", "y", "w", "h"]].to_numpy(float), int(t))
                for b in thresholds:
                    hit = score > b
                    sums[proxy.res, b] = sums.get((proxy.res, b), 0) + np.array([(hit & label).sum(), (~hit & label).sum(), (hit & ~label).sum(), label.size])
        return pd.DataFrame([(*key, *k, *v.tolist()) for k, v in sums.items()], columns=["scene", "clip", "res", "threshold", "hits", "misses", "alarms", "cells"])

    return boxes.groupBy("scene", "clip").applyInPandas(run, "scene int, clip bigint, res int, threshold double, hits bigint, misses bigint, alarms bigint, cells bigint")
