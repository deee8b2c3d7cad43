"""Grouping of positive cells into windows of a few fixed sizes, and the choice of these sizes."""

from __future__ import annotations

from collections.abc import Iterable, Iterator
from itertools import combinations

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F
from pyspark.sql.types import IntegerType, StructField, StructType

from ..model.schemas import CELL, COLUMNS, HEIGHT, ROWS, WIDTH, seconds

Size = tuple[int, int, float]
Cell = tuple[int, int]
Box = tuple[int, int, int, int]


def components(cells: Iterable[Cell], connect: int = 8) -> list[list[Cell]]:
    """Connected groups of cells, ordered by their smallest cell."""
    left = set(cells)
    steps = [(dx, dy) for dx in (-1, 0, 1) for dy in (-1, 0, 1) if (dx or dy) and (connect == 8 or not dx or not dy)]
    out = []
    for start in sorted(left):
        if start not in left:
            continue
        left.discard(start)
        group, work = [], [start]
        while work:
            x, y = work.pop()
            group.append((x, y))
            for dx, dy in steps:
                near = (x + dx, y + dy)
                if near in left:
                    left.discard(near)
                    work.append(near)
        out.append(sorted(group))
    return out


def box_of(cells: Iterable[Cell]) -> Box:
    xs, ys = zip(*cells)
    return min(xs), min(ys), max(xs) + 1, max(ys) + 1


def union(a: Box, b: Box) -> Box:
    return min(a[0], b[0]), min(a[1], b[1]), max(a[2], b[2]), max(a[3], b[3])


def fit_size(box: Box, sizes: list[Size]) -> Size | None:
    """The smallest size that holds a box of cells: least area, then cheaper, then narrower."""
    w, h = (box[2] - box[0]) * CELL, (box[3] - box[1]) * CELL
    return min((s for s in sizes if s[0] >= w and s[1] >= h), key=lambda s: (s[0] * s[1], s[2], s[0]), default=None)


def _apart(a: Box, b: Box) -> tuple[int, int]:
    dx, dy = max(0, a[0] - b[2], b[0] - a[2]), max(0, a[1] - b[3], b[1] - a[3])
    return max(dx, dy), dx * dx + dy * dy


def merge(boxes: list[Box], sizes: list[Size]) -> list[tuple[Box, Size]]:
    """Greedy merging of component boxes: a cluster and its nearest one, with all that the size for both also holds, become
    one where that is strictly cheaper than the windows of its own; passes go on until one merges nothing."""
    clusters = [(b, fit_size(b, sizes)) for b in boxes]
    changed = True
    while changed and len(clusters) > 1:
        changed, i = False, 0
        while i < len(clusters) and len(clusters) > 1:
            box, size = clusters[i]
            nearest = min((j for j in range(len(clusters)) if j != i), key=lambda j: (*_apart(box, clusters[j][0]), j))
            joined = union(box, clusters[nearest][0])
            wide = fit_size(joined, sizes)
            if wide is not None:
                taken = [i, nearest]
                for j in range(len(clusters)):
                    if j not in taken:
                        grown = union(joined, clusters[j][0])
                        if (grown[2] - grown[0]) * CELL <= wide[0] and (grown[3] - grown[1]) * CELL <= wide[1]:
                            joined = grown
                            taken.append(j)
                if wide[2] < sum(clusters[j][1][2] for j in taken) - 1e-12:
                    clusters[i] = (joined, wide)
                    clusters = [c for j, c in enumerate(clusters) if j == i or j not in taken]
                    changed = True
                    i = clusters.index((joined, wide))
            i += 1
    return clusters


def merged_seconds(boxes: np.ndarray, sets: np.ndarray) -> np.ndarray:
    """Seconds of the windows that :func:`merge` leaves, for many frames at once: ``boxes`` (frames, components, 4) in cells, with a size set of its own
    for each, ``sets`` (frames, sizes, 3) as (w, h, seconds). Every frame takes the steps of :func:`merge` in their order; a step is taken by all together.
    """
    n, order = boxes.shape[1], np.lexsort((sets[..., 0], sets[..., 2], sets[..., 0] * sets[..., 1]))
    sets = np.take_along_axis(sets, order[..., None], 1)
    wide, high, price = (sets[..., 0] // CELL).astype(np.int32), (sets[..., 1] // CELL).astype(np.int32), sets[..., 2]

    def fitting(w: np.ndarray, h: np.ndarray) -> np.ndarray:
        """Places of the smallest sizes that hold boxes (frames, ...); the largest, the frame, holds all."""
        more = (slice(None),) + (None,) * (w.ndim - 1)
        out = np.full(w.shape, sets.shape[1] - 1)
        for k in range(sets.shape[1] - 2, -1, -1):
            out[(wide[:, k][more] >= w) & (high[:, k][more] >= h)] = k
        return out

    x0, y0, x1, y1 = (np.ascontiguousarray(boxes[..., k], np.int32) for k in range(4))
    sec = np.take_along_axis(price, fitting(x1 - x0, y1 - y0), 1)
    lanes, alive = np.arange(len(boxes)), np.ones((len(boxes), n), bool)
    at, changed, out = np.zeros(len(boxes), int), np.zeros(len(boxes), bool), sec.sum(1)
    while len(lanes) and n > 1:
        rows = np.arange(len(lanes))
        a0, b0, a1, b1 = (v[rows, at] for v in (x0, y0, x1, y1))
        dx, dy = (np.maximum(0, np.maximum(lo[:, None] - his, los - hi[:, None])) for lo, hi, los, his in ((a0, a1, x0, x1), (b0, b1, y0, y1)))
        far = np.where(alive, np.maximum(dx, dy) * 4096 + dx * dx + dy * dy, 1 << 30)
        far[rows, at] = 1 << 30
        near = far.argmin(1)
        taken = np.zeros(alive.shape, bool)
        taken[rows, at] = taken[rows, near] = True
        a0, b0 = np.minimum(a0, x0[rows, near]), np.minimum(b0, y0[rows, near])
        a1, b1 = np.maximum(a1, x1[rows, near]), np.maximum(b1, y1[rows, near])
        size = fitting(a1 - a0, b1 - b0)
        w, h, cost = wide[rows, size], high[rows, size], price[rows, size]
        total = sec[rows, at] + sec[rows, near]
        for j in range(n):
            c0, d0, c1, d1 = np.minimum(a0, x0[:, j]), np.minimum(b0, y0[:, j]), np.maximum(a1, x1[:, j]), np.maximum(b1, y1[:, j])
            more = alive[:, j] & ~taken[:, j] & (c1 - c0 <= w) & (d1 - d0 <= h)
            a0, b0, a1, b1 = (np.where(more, new, old) for new, old in ((c0, a0), (d0, b0), (c1, a1), (d1, b1)))
            taken[:, j] |= more
            total += np.where(more, sec[:, j], 0.0)
        go = cost < total - 1e-12
        some = rows[go]
        for v, new in ((x0, a0), (y0, b0), (x1, a1), (y1, b1), (sec, cost)):
            v[some, at[some]] = new[some]
        taken[rows, at] = False
        alive &= ~(taken & go[:, None])
        changed |= go
        later = alive & (np.arange(n) > at[:, None])
        ended, alone = ~later.any(1), alive.sum(1) == 1
        again, done = ended & changed, alone | (ended & ~changed)
        at = np.where(ended, alive.argmax(1), later.argmax(1))
        changed &= ~again
        out[lanes[done]] = np.where(alive[done], sec[done], 0.0).sum(1)
        if done.any():
            x0, y0, x1, y1, sec, wide, high, price, sets, lanes, alive, at, changed = (v[~done] for v in (x0, y0, x1, y1, sec, wide, high, price, sets, lanes, alive, at, changed))
    return out


def group_cells(cells: Iterable[Cell], sizes: list[Size], mode: str = "merge", connect: int = 8) -> list[tuple[int, int, int, int, float]]:
    """Windows (px, py, pw, ph, sec) that cover all cells.

    Modes: merge (greedy), none (one window per component), cell (one per cell), bbox (one per frame), frame (the whole frame).
    Every window is shifted back into the frame. No cells give no windows.
    """
    cells = sorted(set(cells))
    if not cells:
        return []
    frame = max(sizes, key=lambda s: s[0] * s[1])
    if mode == "frame":
        return [(0, 0, frame[0], frame[1], frame[2])]
    if mode == "cell":
        boxes = [(x, y, x + 1, y + 1) for x, y in cells]
    elif mode == "bbox":
        boxes = [box_of(cells)]
    else:
        boxes = [box_of(c) for c in components(cells, connect)]
    found = merge(boxes, sizes) if mode == "merge" else [(b, fit_size(b, sizes)) for b in boxes]
    return [(max(0, min(b[0] * CELL, WIDTH - s[0])), max(0, min(b[1] * CELL, HEIGHT - s[1])), s[0], s[1], s[2]) for b, s in found]


def optimal_cover(cells: Iterable[Cell], sizes: list[Size]) -> float:
    """Least cost over all partitions of the components into windows; exponential, for small frames only."""
    boxes = [box_of(c) for c in components(cells)]
    full = (1 << len(boxes)) - 1
    price = [0.0] * (full + 1)
    for mask in range(1, full + 1):
        some = [b for i, b in enumerate(boxes) if mask >> i & 1]
        joined = some[0]
        for b in some[1:]:
            joined = union(joined, b)
        size = fit_size(joined, sizes)
        price[mask] = size[2] if size else float("inf")
    best = [0.0] + [float("inf")] * full
    for mask in range(1, full + 1):
        sub = mask
        while sub:
            best[mask] = min(best[mask], price[sub] + best[mask ^ sub])
            sub = (sub - 1) & mask
    return best[full]


def grouped(cells: DataFrame, sizes: list[Size], mode: str = "merge", *keys: str) -> DataFrame:
    """Windows of every frame of (keys..., cx, cy): one row per window; frames are independent, nothing else is shuffled."""
    keys = keys or ("scene", "clip", "t")

    @F.pandas_udf("array<struct<px int, py int, pw int, ph int, sec double>>")
    def run(frames: pd.Series) -> pd.Series:
        known: dict[tuple, list] = {}
        out = []
        for f in frames:
            key = tuple(sorted(f.tolist()))
            if key not in known:
                known[key] = [dict(zip(("px", "py", "pw", "ph", "sec"), w)) for w in group_cells([(c % 1024, c // 1024) for c in key], sizes, mode)]
            out.append(known[key])
        return pd.Series(out)

    frames = cells.groupBy(*keys).agg(F.collect_set(F.col("cx") + 1024 * F.col("cy")).alias("cells"))
    return frames.select(*keys, F.posexplode(run("cells")).alias("win_id", "win")).select(*keys, "win_id", "win.*")


def signatures(cells: DataFrame) -> DataFrame:
    """Distinct cell sets with how many frames have each: frames with the same cells cost the same for every size set."""
    return cells.groupBy("scene", "clip", "t").agg(F.sort_array(F.collect_set(F.col("cx") + 1024 * F.col("cy"))).alias("cells")).groupBy("scene", "cells").agg(F.count("*").alias("frames"))


def total_times(sets: DataFrame, chosen: list[tuple[int, int]], candidates: list[tuple[int, int]], mode: str = "merge") -> DataFrame:
    """Total seconds of the frames for the chosen sizes plus each candidate: rows (scene, w, h, total)."""

    def merged(batch: pd.DataFrame) -> Iterator[tuple[int, np.ndarray]]:
        """A scene and the seconds under each candidate, of the frames with equally many components: their boxes alone decide, so equal ones are reckoned once."""
        alike: dict[tuple, dict[tuple, int]] = {}
        for scene, codes, frames in zip(batch["scene"], batch["cells"], batch["frames"]):
            boxes = tuple(box_of(c) for c in components((int(c) % 1024, int(c) // 1024) for c in codes))
            own = alike.setdefault((scene, len(boxes)), {})
            own[boxes] = own.get(boxes, 0) + frames
        # the frame as the last one stands for all candidates that hold no component: they change nothing
        every = np.array([(w, h, seconds("one_stage", w, h)) for w, h in [*candidates, (WIDTH, HEIGHT)]])
        have = np.array([(w, h, seconds("one_stage", w, h)) for w, h in chosen])
        for (scene, n), own in alike.items():
            boxes, frames = np.array(list(own), np.int32), np.array(list(own.values()))
            few = max(1, 400_000 // (n * len(every)))
            for some, weight in ((boxes[k : k + few], frames[k : k + few]) for k in range(0, len(boxes), few)):
                w, h = (some[..., 2] - some[..., 0]) * CELL, (some[..., 3] - some[..., 1]) * CELL
                holds = ((w[..., None] <= every[:, 0]) & (h[..., None] <= every[:, 1])).any(1)
                holds[:, -1] = True
                f, c = np.nonzero(holds)
                cost = np.full(holds.shape, np.nan)
                cost[f, c] = merged_seconds(some[f], np.concatenate([np.broadcast_to(have, (len(f), *have.shape)), every[c, None]], 1))
                yield scene, (np.where(holds, cost, cost[:, -1:]) * weight[:, None]).sum(0)[:-1]

    def single(batch: pd.DataFrame) -> Iterator[tuple[int, np.ndarray]]:
        for scene, codes, frames in zip(batch["scene"], batch["cells"], batch["frames"]):
            cells = [(int(c) % 1024, int(c) // 1024) for c in codes]
            widest = [box_of(c) for c in components(cells)]
            plain, costs = None, []
            for w, h in candidates:
                if not any((b[2] - b[0]) * CELL <= w and (b[3] - b[1]) * CELL <= h for b in widest):
                    if plain is None:  # a size that holds no component changes nothing
                        plain = sum(x[4] for x in group_cells(cells, [(*s, seconds("one_stage", *s)) for s in chosen], mode))
                    costs.append(plain)
                else:
                    costs.append(sum(x[4] for x in group_cells(cells, [(*s, seconds("one_stage", *s)) for s in [*chosen, (w, h)]], mode)))
            yield scene, np.array(costs) * frames

    def run(batches: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for batch in batches:
            sums: dict[int, np.ndarray] = {}
            for scene, costs in (merged if mode == "merge" else single)(batch):
                sums[scene] = sums.get(scene, 0.0) + costs
            if sums:
                yield pd.DataFrame([(scene, w, h, v) for scene, costs in sums.items() for (w, h), v in zip(candidates, costs.tolist())], columns=["scene", "w", "h", "total"])

    return sets.mapInPandas(run, "scene int, w int, h int, total double").groupBy("scene", "w", "h").agg(F.sum("total").alias("total"))


def choose_sizes(cells: DataFrame, k: int = 3, step: int = CELL, mode: str = "merge", sample: int | None = 100, coarse: int = 1) -> dict[int, list[tuple[int, int]]]:
    """Greedy choice of ``k`` sizes for each scene, the frame first: each round adds the size with the lowest total time.

    ``sample``: distinct cell sets for each scene, by hash (a fixed training split; None: all). A round that lowers nothing ends the choice.
    """
    sets = signatures(cells)
    if sample:
        order = F.row_number().over(Window.partitionBy("scene").orderBy(F.xxhash64("cells")))
        sets = sets.withColumn("r", order).where(F.col("r") <= sample).drop("r")
    sets = sets.repartition(16).cache()
    scenes = [r.scene for r in sets.select("scene").distinct().collect()]
    chosen = {s: [(WIDTH, HEIGHT)] for s in scenes}
    every = [(w * step, h * step) for w in range(1, WIDTH // step + 1, coarse) for h in range(1, HEIGHT // step + 1, coarse) if (w * step, h * step) != (WIDTH, HEIGHT)]
    best: dict[int, float] = {}
    for _ in range(k - 1):
        todo: dict[tuple, list[int]] = {}
        for s in scenes:
            todo.setdefault(tuple(chosen[s]), []).append(s)
        for have, group in todo.items():
            totals = total_times(sets.where(F.col("scene").isin(group)), list(have), [(WIDTH, HEIGHT), *every], mode).collect()
            for s in group:
                own = [r for r in totals if r.scene == s]
                now = best.setdefault(s, next(r.total for r in own if (r.w, r.h) == (WIDTH, HEIGHT)))
                pick = min(own, key=lambda r: (round(r.total, 9), r.w * r.h, r.w))
                if pick.total < now - 1e-9:
                    best[s] = pick.total
                    chosen[s].append((pick.w, pick.h))
    sets.unpersist()
    return chosen


def best_sizes_exact(frames: list[list[Cell]], k: int, candidates: list[tuple[int, int]]) -> tuple[float, list[tuple[int, int]]]:
    """The best size set by trying all; for small grids."""
    best = (float("inf"), [])
    for extra in combinations(candidates, k - 1):
        sizes = [(*s, seconds("one_stage", *s)) for s in [(WIDTH, HEIGHT), *extra]]
        best = min(best, (sum(w[4] for f in frames for w in group_cells(f, sizes)), [(WIDTH, HEIGHT), *extra]))
    return best


def scale_sizes(sizes: list[tuple[int, int]], width: int) -> list[tuple[int, int]]:
    """Sizes at a detector resolution of ``width``, snapped outward to whole cells."""
    return [(-(-w * width // WIDTH // CELL) * CELL, -(-h * width // WIDTH // CELL) * CELL) for w, h in sizes]


def batches(windows: DataFrame, size: int = 16) -> DataFrame:
    """Windows of one size numbered into batches inside each partition: equal shapes run together without a shuffle."""

    def run(parts: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        seen: dict[tuple[int, int], int] = {}
        for part in parts:
            ids = []
            for w, h in zip(part["pw"], part["ph"]):
                n = seen[w, h] = seen.get((w, h), -1) + 1
                ids.append(n // size)
            yield part.assign(batch=ids)

    return windows.mapInPandas(run, StructType([*windows.schema.fields, StructField("batch", IntegerType())]))


assert (COLUMNS, ROWS) == (20, 12)
