"""Tracking accuracy: misses, spurious boxes and identity switches over true boxes."""

from __future__ import annotations

import numpy as np
import pandas as pd

from ..track.assign import assign
from ..track.scorers import iou


def mota_terms(truth: pd.DataFrame, tracks: pd.DataFrame, least: float = 0.5) -> dict[str, int]:
    """Terms over the frames of ``truth``: pairs of the frame before go on while they overlap enough, the rest is assigned optimally."""
    true_by, got_by = ({int(t): g for t, g in f.groupby("t")} for f in (truth, tracks))
    last: dict[int, int] = {}
    out = {"truth": 0, "misses": 0, "spurious": 0, "switches": 0}
    for t in sorted(set(true_by) | set(got_by)):
        a, b = true_by.get(t, truth.iloc[:0]), got_by.get(t, tracks.iloc[:0])
        out["truth"] += len(a)
        pairs: list[tuple[int, int]] = []
        if len(a) and len(b):
            score = iou(a[["x", "y", "w", "h"]].to_numpy(float), b[["x", "y", "w", "h"]].to_numpy(float))
            objs, ids = a["obj"].tolist(), b["track_id"].tolist()
            for i, o in enumerate(objs):
                if o in last and last[o] in ids and score[i, (j := ids.index(last[o]))] >= least:
                    pairs.append((i, j))
            free = score.copy()
            for i, j in pairs:
                free[i], free[:, j] = -1, -1
            pairs += assign(free, least)
            for i, j in pairs:
                out["switches"] += objs[i] in last and last[objs[i]] != ids[j]
                last[objs[i]] = ids[j]
        out["misses"] += len(a) - len(pairs)
        out["spurious"] += len(b) - len(pairs)
    return out


def mota(terms: dict[str, int]) -> float:
    """1 - errors / true boxes; may be negative; 1 without true boxes and errors."""
    errors = terms["misses"] + terms["spurious"] + terms["switches"]
    return 1 - errors / terms["truth"] if terms["truth"] else float(not errors)
