"""A flat proximity graph in numpy: robust pruning, shards with overlap, and range-expanding greedy search."""

from __future__ import annotations

import heapq

import numpy as np


def clusters(x: np.ndarray, size: int, overlap: int, seed: int = 7, rounds: int = 4, sample: int = 4096) -> tuple[list[np.ndarray], np.ndarray]:
    """Shards of rows of ``x`` (unit vectors): every row is in its ``overlap`` nearest ones; and the row nearest to each centre.

    Centres come from a few k-means rounds on a fixed sample; shards of more than ``4 * size`` rows are cut in pieces.
    """
    n = len(x)
    k = max(1, -(-n // size))
    if k == 1:
        return [np.arange(n)], np.array([int(np.argmax(x @ x.mean(0)))])
    rng = np.random.default_rng(seed)
    pool = x if n <= sample else x[rng.choice(n, sample, replace=False)]
    centres = pool[rng.choice(len(pool), min(k, len(pool)), replace=False)]
    for _ in range(rounds):
        near = np.argmax(pool @ centres.T, 1)
        for c in range(len(centres)):
            own = pool[near == c]
            if len(own):
                m = own.mean(0)
                centres[c] = m / max(np.linalg.norm(m), 1e-12)
    shards: list[list[np.ndarray]] = [[] for _ in centres]
    best = np.full(len(centres), -2.0)
    medoids = np.zeros(len(centres), np.int64)
    for at in range(0, n, 4096):
        s = x[at : at + 4096] @ centres.T
        near = np.argpartition(-s, min(overlap, len(centres)) - 1, 1)[:, :overlap]
        for c in range(len(centres)):
            shards[c].append(at + np.flatnonzero((near == c).any(1)))
            i = int(np.argmax(s[:, c]))
            if s[i, c] > best[c]:
                best[c], medoids[c] = s[i, c], at + i
    out = []
    for parts in shards:
        rows = np.concatenate(parts)
        out += [rows[i : i + 4 * size] for i in range(0, len(rows), 4 * size)]
    return [s for s in out if len(s)], medoids


def prune(x: np.ndarray, rows: np.ndarray, near: int = 48, degree: int = 20, alpha: float = 1.2) -> dict[int, list[int]]:
    """Robust-pruned neighbours of the rows of one shard: a candidate is dropped when a kept neighbour is alpha times nearer to it."""
    y = x[rows].astype(np.float32)
    out: dict[int, list[int]] = {}
    m = len(rows)
    near = min(near, m - 1)
    if near < 1:
        return {int(r): [] for r in rows}
    for at in range(0, m, 512):
        s = y[at : at + 512] @ y.T
        s[np.arange(len(s)), np.arange(at, at + len(s))] = -2
        top = np.argpartition(-s, near - 1, 1)[:, :near]
        for i, cand in enumerate(top):
            cand = cand[np.argsort(-s[i, cand], kind="stable")]
            dist = np.sqrt(np.maximum(2 - 2 * s[i, cand], 0))
            among = np.sqrt(np.maximum(2 - 2 * (y[cand] @ y[cand].T), 0))
            alive = np.ones(len(cand), bool)
            kept = []
            for j in range(len(cand)):
                if alive[j]:
                    kept.append(int(rows[cand[j]]))
                    if len(kept) >= degree:
                        break
                    alive &= alpha * among[j] > dist
            out[int(rows[at + i])] = kept
    return out


def build(x: np.ndarray, shard: int = 512, overlap: int = 2) -> tuple[list[np.ndarray], np.ndarray]:
    """Adjacency lists, the union over the shards with back links, and the medoids."""
    shards, medoids = clusters(x, shard, overlap)
    links: list[set[int]] = [set() for _ in range(len(x))]
    for rows in shards:
        for i, near in prune(x, rows).items():
            links[i].update(near)
            for j in near:
                links[j].add(i)
    return [np.array(sorted(s), np.int32) for s in links], medoids


def range_search(x: np.ndarray, links: list[np.ndarray], medoids: np.ndarray, q: np.ndarray, least: float, own: int | None = None, beam: int = 24, slack: float = 0.12) -> np.ndarray:
    """Rows with cosine of at least ``least`` to ``q``: greedy search from the medoids with a beam, then expansion of every
    row within ``least - slack`` until none is new. ``own``: the query's own row if it is one of ``x``, a further start."""
    if own is not None:
        medoids = np.append(medoids[medoids != own], own)
    sims = x[medoids] @ q
    seen = np.zeros(len(x), bool)
    seen[medoids] = True
    heap = [(-float(s), int(i)) for s, i in zip(sims, medoids)]
    heapq.heapify(heap)
    found = {int(i): float(s) for s, i in zip(sims, medoids)}
    best = sorted((float(s) for s in sims), reverse=True)[:beam]
    while heap:
        s, i = heapq.heappop(heap)
        if -s < least - slack and len(best) >= beam and -s < best[-1]:
            break
        fresh = links[i]
        fresh = fresh[~seen[fresh]]
        if not len(fresh):
            continue
        seen[fresh] = True
        got = x[fresh] @ q
        bound = best[-1] if len(best) >= beam else -2.0
        for v, j in zip(got.tolist(), fresh.tolist()):
            found[j] = v
            if v >= bound or v >= least - slack:
                heapq.heappush(heap, (-v, j))
        best = sorted(best + got.tolist(), reverse=True)[:beam]
    return np.array([i for i, v in found.items() if v >= least - 1e-6], np.int64)
