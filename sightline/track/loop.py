"""The frame loop of a tracker over one clip, its training examples, and variable gaps."""

from __future__ import annotations

import numpy as np
import pandas as pd

from .assign import assign
from .scorers import INPUTS, PLAIN, Motion, Overlap, Pool, Prefix, Recurrent, iou

MAX_LOST = 3


def frames_of(pdf: pd.DataFrame) -> dict[int, pd.DataFrame]:
    return {int(t): g for t, g in pdf.sort_values(["t", "obj"]).groupby("t", sort=True)}


def track(pdf: pd.DataFrame, scorer, gap: int = 1, max_lost: int = MAX_LOST, least: float | None = None) -> pd.DataFrame:
    """Adds track_id to the boxes of one clip. A prefix unmatched for more than ``max_lost`` processed frames ends; categories must agree."""
    pdf = pdf.sort_values(["t", "obj"], kind="stable")
    return pdf.assign(track_id=track_ids(pdf["t"].to_numpy(), pdf["category"].to_numpy(), pdf[["x", "y", "w", "h"]].to_numpy(float), scorer, gap, max_lost, least))


def track_ids(t_all: np.ndarray, cats: np.ndarray, boxes_all: np.ndarray, scorer, gap: int = 1, max_lost: int = MAX_LOST, least: float | None = None) -> np.ndarray:
    """Track ids of the boxes of one clip, given in the order of their frames."""
    least = scorer.least if least is None else least
    alive: list[Prefix] = []
    ids = np.full(len(t_all), -1, np.int64)
    cuts = np.flatnonzero(np.diff(t_all, prepend=-1))
    fresh = 0
    for a, b in zip(cuts, [*cuts[1:], len(t_all)]):
        t = int(t_all[a])
        alive = [p for p in alive if t - p.t <= max_lost * gap + gap]
        taken = set()
        if alive:
            score = scorer.score(alive, boxes_all[a:b], t)
            same = np.array([p.category for p in alive])[:, None] == cats[a:b][None]
            for i, j in assign(np.where(same, score, -1.0), least):
                scorer.update(alive[i], boxes_all[a + j], t)
                ids[a + j] = alive[i].id
                taken.add(j)
        for j in range(b - a):
            if j not in taken:
                p = Prefix(fresh, boxes_all[a + j], t, cats[a + j])
                if isinstance(scorer, Recurrent):
                    scorer.start(p)
                alive.append(p)
                ids[a + j] = fresh
                fresh += 1
    return ids


def track_many(runs: list[tuple[np.ndarray, np.ndarray, np.ndarray]], scorer, gap: int = 1, max_lost: int = MAX_LOST, least: float | None = None) -> list[np.ndarray]:
    """Track ids of many runs (frames, categories, boxes), each as :func:`track_ids` gives them. A frame of all runs is one step over arrays: the pairs of
    a run's running tracks and boxes are scored together, and only runs in which a feasible pair is not alone are assigned by themselves."""
    least = scorer.least if least is None else least
    sizes = [len(t) for t, _, _ in runs]
    if not sum(sizes):
        return [np.zeros(0, np.int64) for _ in runs]
    run, t_all = np.repeat(np.arange(len(runs)), sizes), np.concatenate([t for t, _, _ in runs])
    kinds, codes = np.unique(np.concatenate([c for _, c, _ in runs]).astype(str), return_inverse=True)
    boxes = np.concatenate([b for _, _, b in runs if len(b)])
    order = np.lexsort((run, t_all))  # stable: a run's boxes of a frame keep their order
    run, t_all, boxes = run[order], t_all[order], boxes[order]
    key = run * len(kinds) + codes[order]
    pool, ids = Pool(len(run), boxes.shape[1]), np.empty(len(run), np.int64)
    # a track's place in the pool is that of its first box, so the places of a run are in the order of their ids
    alive, fresh = np.zeros(0, np.int64), np.zeros(len(runs), np.int64)
    cuts = np.flatnonzero(np.diff(t_all, prepend=-1)).tolist()
    for a, b in zip(cuts, [*cuts[1:], len(run)]):
        t = int(t_all[a])
        alive = alive[t - pool.t[alive] <= max_lost * gap + gap]
        own, free = boxes[a:b], np.ones(b - a, bool)
        i, j = np.nonzero(key[alive][:, None] == key[a:b])
        if len(i):
            score = scorer.pairs(pool, alive, own, i, j, t)
            fine = score >= least
            fi, fj = i[fine], j[fine]
            clash = (np.bincount(fi, minlength=len(alive))[fi] > 1) | (np.bincount(fj, minlength=b - a)[fj] > 1)
            if clash.any():
                hard = np.unique(run[a + fj[clash]])
                easy = ~np.isin(run[a + fj], hard)
                ends = [(fi[easy], fj[easy])]
                for r in hard.tolist():
                    rows, cols = np.flatnonzero(run[alive] == r), np.flatnonzero(run[a:b] == r)
                    some = run[a + j] == r
                    table = np.full((len(rows), len(cols)), -1.0)
                    table[np.searchsorted(rows, i[some]), np.searchsorted(cols, j[some])] = score[some]
                    pairs = np.array(assign(table, least), np.int64).reshape(-1, 2)
                    ends.append((rows[pairs[:, 0]], cols[pairs[:, 1]]))
                fi, fj = (np.concatenate(e) for e in zip(*ends))
        else:
            fi = fj = np.zeros(0, np.int64)
        old, free[fj] = alive[fi], False
        ids[a + fj] = ids[old]
        new = a + np.flatnonzero(free)
        owner = run[new]
        ids[new] = fresh[owner] + np.arange(len(new)) - np.searchsorted(owner, owner)
        fresh += np.bincount(owner, minlength=len(runs))
        scorer.step(pool, old, own[fj], new, boxes[new], t)
        alive = np.concatenate([alive, new])
    out = np.empty_like(ids)
    out[order] = ids
    return np.split(out, np.cumsum(sizes)[:-1])


def scorer_of(name: str, net: dict | None = None):
    return {"overlap": Overlap, "motion": Motion}[name]() if name != "recurrent" else Recurrent(net, (net or {}).get("elapsed", True))


def thinned(t: np.ndarray, gap: int, start: int = 0) -> np.ndarray:
    """Places of a track's boxes, in order of time, that are at least ``gap`` frames apart, from its box ``start`` on."""
    out, last = [], -(10**9)
    for i in range(start, len(t)):
        if t[i] >= last + gap:
            out.append(i)
            last = int(t[i])
    return np.array(out, int)


#: Steps of a training sequence and boxes that a step is tried with: the right one, if it is there, and the nearest others.
STEPS, TRIED = 6, 5


def training_sequences(pdf: pd.DataFrame, gaps: tuple[int, ...] = (1, 2, 4, 8, 16), elapsed: bool = True) -> tuple[np.ndarray, ...]:
    """Sequences of tracks thinned to each gap: inputs of the state, then for every step the match features, labels and mask of the next one.

    ``pdf`` has the tracks as ``obj`` and, where known, looks as a0, a1, ... Each track is thinned from a start of its own, drawn by hash among the first boxes
    of a gap, and cut in pieces of ``STEPS`` boxes and one to match; all pieces are used.
    """
    scorer = Recurrent(None, elapsed)
    pdf = pdf.sort_values(["t", "obj"], kind="stable")
    looks = [c for c in ("a0", "a1", "a2", "a3") if c in pdf]
    t_all, objs, cats, boxes = pdf["t"].to_numpy(), pdf["obj"].to_numpy(), pdf["category"].to_numpy(), pdf[["x", "y", "w", "h", *looks]].to_numpy(float)
    at = {t: (lo, hi) for t, lo, hi in zip(*_runs(t_all))}
    order = np.argsort(objs, kind="stable")
    pieces = []
    for places in np.split(order, np.flatnonzero(np.diff(objs[order])) + 1) if len(objs) else []:
        o = int(objs[places[0]])
        for gap in gaps:
            kept = places[thinned(t_all[places], gap, min(len(places) - 1, abs(o) * 7919 % gap))]
            # where the track ends, one more frame is asked for, in which no box is right
            pieces += [(o, gap, kept[first : first + STEPS + 1], first + STEPS >= len(kept)) for first in range(0, len(kept), STEPS)]
    xs, plains, owns, ys, masks = [], [], [], [], []
    for o, gap, piece, left in pieces:
        x, plain, own = np.zeros((STEPS, INPUTS)), np.zeros((STEPS, TRIED, PLAIN)), np.zeros((STEPS, 2))
        y, mask = np.zeros((STEPS, TRIED)), np.zeros((STEPS, TRIED))
        p = Prefix(o, boxes[piece[0]], int(t_all[piece[0]]), cats[piece[0]])
        for k, j in enumerate(piece[:STEPS].tolist()):
            if k + 1 == len(piece) and not left:
                break
            elapsed_now = 0
            if k:
                elapsed_now = int(t_all[j]) - p.t
                scorer.update(p, boxes[j], int(t_all[j]))
            x[k] = scorer.inputs(p.box, p.v, elapsed_now)
            t = int(t_all[piece[k + 1]]) if k + 1 < len(piece) else int(t_all[j]) + gap
            lo, hi = at.get(t, (0, 0))
            near = lo + np.flatnonzero(cats[lo:hi] == p.category)
            far = np.hypot(*(boxes[near, :2] - p.box[:2] - p.v * (t - p.t)).T) - 1e6 * (objs[near] == o)
            near = near[np.argsort(far, kind="stable")[:TRIED]]
            if not len(near):
                continue
            f, own[k] = (a[0] for a in scorer.plain([p], boxes[near], t))
            plain[k, : len(near)], y[k, : len(near)], mask[k, : len(near)] = f, objs[near] == o, 1.0
        for into, value in ((xs, x), (plains, plain), (owns, own), (ys, y), (masks, mask)):
            into.append(value)
    shapes = ((STEPS, INPUTS), (STEPS, TRIED, PLAIN), (STEPS, 2), (STEPS, TRIED), (STEPS, TRIED))
    return tuple(np.array(v) if v else np.zeros((0, *shape)) for v, shape in zip((xs, plains, owns, ys, masks), shapes))


def _runs(t: np.ndarray) -> tuple[list[int], list[int], list[int]]:
    """Frames, and where their boxes begin and end."""
    cuts = np.flatnonzero(np.diff(t, prepend=-1))
    return t[cuts].tolist(), cuts.tolist(), [*cuts[1:].tolist(), len(t)]


class Confidence:
    """The least confident match of the boxes of a frame with those of another, found once for each two frames; ``boxes_at(t)``: the boxes of a frame, rows x, y, w, h."""

    def __init__(self, boxes_at):
        self.boxes_at, self.known = boxes_at, {}

    def __call__(self, t: int, to: int) -> float | None:
        """None: the first frame has no boxes."""
        if (t, to) not in self.known:
            a, b = self.boxes_at(t), self.boxes_at(to)
            self.known[t, to] = None if not len(a) else self._least(a, b) if len(b) else 0.0
        return self.known[t, to]

    @staticmethod
    def _least(a: np.ndarray, b: np.ndarray) -> float:
        if len(a) * len(b) > 64:
            return float(iou(a, b).max(1).min())
        # the same sums in plain numbers: on so few boxes arrays cost more than they save
        some = [(x - w / 2, x + w / 2, y - h / 2, y + h / 2, w * h) for x, y, w, h in b[:, :4].tolist()]
        least = np.inf
        for x, y, w, h in a[:, :4].tolist():
            x0, x1, y0, y1, area, best = x - w / 2, x + w / 2, y - h / 2, y + h / 2, w * h, -np.inf
            for u0, u1, v0, v1, other in some:
                dx, dy = min(x1, u1) - max(x0, u0), min(y1, v1) - max(y0, v0)
                inter = dx * dy if dx > 0 and dy > 0 else 0.0
                best = max(best, inter / (area + other - inter))
            least = min(least, best)
        return least


def variable_frames(boxes_at, tolerance: float = 0.5, most: int = 16, frames: int = 480, least: Confidence | None = None) -> list[int]:
    """Two-frame matching with a gap that halves when the least confident match is under the tolerance and doubles otherwise.

    ``boxes_at(t)``: the boxes of a frame; ``least``: what is known of them, for several tolerances. Returns the frames that were looked at, in order.
    """
    least = least or Confidence(boxes_at)
    done, t, gap = {0}, 0, most
    while t < frames - 1:
        to = min(frames - 1, t + gap)
        while to - t > 1:
            done.add(to)
            score = least(t, to)
            if score is None or score >= tolerance:
                break
            to = t + (to - t) // 2
        done.add(to)
        gap = min(most, 2 * (to - t)) if to - t >= gap else max(1, to - t)
        t = to
    return sorted(done)


def variable_gap(pdf: pd.DataFrame, tolerance: float = 0.5, most: int = 16) -> tuple[pd.DataFrame, int]:
    """The boxes of the frames that :func:`variable_frames` looks at, and their number."""
    held = {t: g[["x", "y", "w", "h"]].to_numpy(float) for t, g in frames_of(pdf).items()}
    done = variable_frames(lambda t: held.get(t, np.zeros((0, 4))), tolerance, most)
    return pdf[pdf["t"].isin(done)].sort_values(["t", "obj"]), len(done)


class EndSearch:
    """Finds where a track begins and ends inside the frames that were skipped, by bisection with further detector calls.

    ``look(t)``: categories and boxes that the detector returns for a frame. A frame looked at once serves all tracks of
    the clip; ``probes`` holds those that were not processed before.
    """

    def __init__(self, processed: list[int], look, frames: int = 480):
        self.processed, self.look, self.frames, self.probes = np.asarray(sorted(processed)), look, frames, set()

    def _end(self, t: int, box: np.ndarray, v: np.ndarray, category: str, bound: int) -> tuple[int, np.ndarray]:
        """From a box at ``t`` towards ``bound``, a frame where the track was not seen: the last time and box at which it is."""
        known, lo, hi = t, t, bound
        while abs(hi - lo) > 1:
            m = (lo + hi) // 2
            self.probes.add(m)
            cats, boxes = self.look(m)
            some = boxes[cats == category]
            found = None
            if len(some):
                at = box[:2] + v * (m - known)
                off = np.hypot(*(some[:, :2] - at).T)
                i = int(np.argmin(off))
                if off[i] <= 0.6 * np.hypot(*box[2:4]) + 0.5 * np.hypot(*v) * abs(m - known):
                    found = some[i]
            if found is None:
                hi = m
            else:
                v = (found[:2] - box[:2]) / (m - known) if m != known else v
                box, known, lo = found, m, m
        return known, box

    def ends(self, t: np.ndarray, boxes: np.ndarray, category: str) -> tuple[np.ndarray, np.ndarray]:
        """First and last box of a track given its boxes in order of time."""
        i, j = np.searchsorted(self.processed, t[0]), np.searchsorted(self.processed, t[-1], "right")
        before = int(self.processed[i - 1]) if i > 0 else -1
        after = int(self.processed[j]) if j < len(self.processed) else self.frames
        speed = lambda a, b: (boxes[b, :2] - boxes[a, :2]) / max(1, int(t[b] - t[a]))
        one, two = (speed(0, 1), speed(-2, -1)) if len(t) > 1 else (np.zeros(2), np.zeros(2))
        return self._end(int(t[0]), boxes[0], one, category, before)[1], self._end(int(t[-1]), boxes[-1], two, category, after)[1]

    def calls(self) -> int:
        return len(self.probes - set(self.processed.tolist()))


def stitch(left: pd.DataFrame, right: pd.DataFrame, overlap: tuple[int, int]) -> dict[int, int]:
    """Ids of ``right`` that continue a track of ``left``: those that share most boxes (t, obj) inside the overlapping frames."""
    lo, hi = overlap
    a = left[(left["t"] >= lo) & (left["t"] <= hi)][["t", "obj", "track_id"]]
    b = right[(right["t"] >= lo) & (right["t"] <= hi)][["t", "obj", "track_id"]]
    both = a.merge(b, on=["t", "obj"], suffixes=("_a", "_b"))
    best = both.groupby(["track_id_b", "track_id_a"]).size().reset_index(name="n").sort_values(["n", "track_id_a"], ascending=[False, True])
    out: dict[int, int] = {}
    for r in best.itertuples():
        if r.track_id_b not in out and r.track_id_a not in out.values():
            out[int(r.track_id_b)] = int(r.track_id_a)
    return out
