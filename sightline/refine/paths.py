"""Track paths: resampling, distances, clusters of reference paths, and the repair of track ends."""

from __future__ import annotations

from dataclasses import dataclass, field

import numpy as np

POINTS = 20


def resample(xy: np.ndarray, n: int = POINTS) -> np.ndarray:
    """``n`` points evenly spaced along a path, both ends kept."""
    step = np.hypot(*np.diff(xy, axis=0).T)
    s = np.concatenate([[0.0], np.cumsum(step)])
    if s[-1] == 0:
        return np.repeat(xy[:1], n, 0)
    at = np.linspace(0, s[-1], n)
    return np.stack([np.interp(at, s, xy[:, 0]), np.interp(at, s, xy[:, 1])], 1)


def distance(p: np.ndarray, q: np.ndarray) -> float:
    """Mean distance between the points of two paths."""
    return float(np.hypot(*(p - q).T).mean())


def subpath(track: np.ndarray, path: np.ndarray) -> np.ndarray:
    """The part of a reference path between its points nearest to the track's ends, resampled."""
    a, b = (int(np.argmin(np.hypot(*(path - e).T))) for e in (track[0], track[-1]))
    return resample(path[a : b + 1], len(track)) if b > a else path


def dbscan(paths: np.ndarray, eps: float = 40.0, min_pts: int = 3) -> np.ndarray:
    """Cluster ids; noise gets -1. Neighbours are looked up among paths whose mean points are in adjacent cells of side
    ``eps``: the mean distance of two paths is at least the distance of their mean points, so none is lost."""
    n = len(paths)
    cells: dict[tuple[int, int], list[int]] = {}
    mids = np.floor(paths.mean(1) / eps).astype(int) if n else np.zeros((0, 2), int)
    for i, c in enumerate(mids):
        cells.setdefault(tuple(c), []).append(i)

    def near(i: int) -> list[int]:
        cx, cy = mids[i]
        some = np.array([j for dx in (-1, 0, 1) for dy in (-1, 0, 1) for j in cells.get((cx + dx, cy + dy), [])])
        d = np.hypot(*(paths[some] - paths[i]).transpose(2, 0, 1)).mean(1)
        return sorted(some[d <= eps].tolist())

    # neighbours are found again when a cluster grows: lists of all of them would take the square of a cluster's size
    core = [len(near(i)) >= min_pts for i in range(n)]
    label = np.full(n, -1)
    k = 0
    for i in range(n):
        if not core[i] or label[i] >= 0:
            continue
        label[i], work = k, [i]
        while work:
            for j in near(work.pop()):
                if label[j] < 0:
                    label[j] = k
                    if core[j]:
                        work.append(j)
        k += 1
    return label


@dataclass
class Reference:
    """Centres of clustered reference paths with their sizes, and a grid index over them."""

    centres: np.ndarray
    sizes: np.ndarray
    index: dict[tuple[int, int], set[int]]
    cell: float
    _parts: dict[tuple[int, int, int, int], np.ndarray] = field(default_factory=dict, repr=False, compare=False)

    @classmethod
    def build(cls, paths: np.ndarray, eps: float = 40.0, min_pts: int = 3, cell: float = 64.0) -> "Reference":
        """Noise becomes clusters of one, so that rare paths survive."""
        label = dbscan(paths, eps, min_pts)
        groups = [paths[label == k] for k in range(label.max(initial=-1) + 1)] + [paths[i : i + 1] for i in np.flatnonzero(label < 0)]
        centres = np.array([g.mean(0) for g in groups]) if groups else np.zeros((0, POINTS, 2))
        return cls.of(centres, np.array([len(g) for g in groups], int), cell)

    @classmethod
    def of(cls, centres: np.ndarray, sizes: np.ndarray, cell: float = 64.0) -> "Reference":
        index: dict[tuple[int, int], set[int]] = {}
        for k, c in enumerate(centres):
            dense = resample(c, max(2, int(np.hypot(*np.diff(c, axis=0).T).sum() / (cell / 2)) + 2))
            for p in dense:
                index.setdefault(tuple(np.floor(p / cell).astype(int)), set()).add(k)
        return cls(centres, sizes, index, cell)

    def _around(self, point: np.ndarray, ring: int) -> set[int]:
        cx, cy = np.floor(point / self.cell).astype(int)
        return {k for dx in range(-ring, ring + 1) for dy in range(-ring, ring + 1) for k in self.index.get((cx + dx, cy + dy), ())}

    def candidates(self, first: np.ndarray, last: np.ndarray, least: int = 1) -> list[int]:
        """Centres that pass near both ends; the ring of cells grows, then the union counts, then there is none."""
        for ring in (1, 2):
            both = self._around(first, ring) & self._around(last, ring)
            if len(both) >= least:
                return sorted(both)
        return sorted(self._around(first, 1) | self._around(last, 1))

    def nearest(self, path: np.ndarray, k: int = 10, full: bool = False, align: str = "subpath") -> list[tuple[int, int]]:
        """(centre, weight) by distance until the weights, the clusters' sizes, sum up to ``k``; the last is cut unless ``full``."""
        some = self.candidates(path[0], path[-1])
        if not some:
            return []
        centres = self.centres[some]
        others = self._subpaths(path, some, centres) if align == "subpath" else centres
        far = dict(zip(some, np.hypot(path[:, 0] - others[..., 0], path[:, 1] - others[..., 1]).mean(1).tolist()))
        return take_weights([(c, int(self.sizes[c]), far[c]) for c in some], k, full)

    def _subpaths(self, path: np.ndarray, some: list[int], centres: np.ndarray) -> np.ndarray:
        """:func:`subpath` of each centre. A part follows from the centre and its two points alone, so the latest parts are kept."""
        a, b = (np.hypot(centres[..., 0] - e[0], centres[..., 1] - e[1]).argmin(1).tolist() for e in (path[0], path[-1]))
        out = []
        for key, centre in zip(zip(some, a, b, [len(path)] * len(some)), centres):
            part = self._parts.get(key)
            if part is None:
                if len(self._parts) >= 20_000:
                    self._parts.clear()
                part = self._parts[key] = resample(centre[key[1] : key[2] + 1], len(path)) if key[2] > key[1] else centre
            out.append(part)
        return np.array(out)

    def ends(self, path: np.ndarray, k: int = 10) -> tuple[np.ndarray, np.ndarray] | None:
        """Weighted median start and end of the nearest centres, each coordinate for itself."""
        found = self.nearest(path, k)
        if not found:
            return None
        ids, weights = zip(*found)
        out = []
        for at in (0, -1):
            points = self.centres[list(ids), at]
            out.append(np.array([weighted_median(points[:, a], np.array(weights)) for a in (0, 1)]))
        return out[0], out[1]


def take_weights(found: list[tuple[int, int, float]], k: int, full: bool = False) -> list[tuple[int, int]]:
    out, total = [], 0
    for c, size, _ in sorted(found, key=lambda x: (x[2], x[0])):
        if total >= k:
            break
        out.append((c, size if full else min(size, k - total)))
        total += size
    return out


def weighted_median(values: np.ndarray, weights: np.ndarray) -> float:
    """The first value, in order, at which the weights reach half of their sum."""
    order = np.argsort(values, kind="stable")
    reach = np.cumsum(weights[order])
    return float(values[order][np.searchsorted(reach, weights.sum() / 2 - 1e-12)])


def border_ends(xy: np.ndarray, width: float = 640, height: float = 384) -> tuple[np.ndarray, np.ndarray]:
    """Both ends run on straight to the frame's border at the speed of the first and last step."""

    def run(point: np.ndarray, v: np.ndarray) -> np.ndarray:
        steps = [((width if v[0] > 0 else 0) - point[0]) / v[0]] if v[0] else []
        steps += [((height if v[1] > 0 else 0) - point[1]) / v[1]] if v[1] else []
        n = max(0.0, min(steps)) if steps else 0.0
        return point + v * n

    return run(xy[0], xy[0] - xy[1]), run(xy[-1], xy[-1] - xy[-2])


def knn_exact(path: np.ndarray, paths: np.ndarray, k: int = 10) -> tuple[np.ndarray, np.ndarray]:
    """Plain medians of the ends of the ``k`` nearest reference paths, without clusters or index."""
    d = np.array([distance(path, subpath(path, p)) for p in paths])
    some = paths[np.argsort(d, kind="stable")[:k]]
    return np.median(some[:, 0], 0), np.median(some[:, -1], 0)
