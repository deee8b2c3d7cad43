"""Match scores between running prefixes and the boxes of a frame."""

from __future__ import annotations

from collections.abc import Callable, Iterable, Iterator

import numpy as np

HIDDEN = 24
#: Numbers of a box that describe how its object looks; boxes are rows x, y, w, h and, where known, these.
LOOKS = 4
INPUTS = 7 + LOOKS
#: Features of a prefix and a box that are not learnt.
PLAIN = 8


def iou(a: np.ndarray, b: np.ndarray) -> np.ndarray:
    """Overlap of every box of ``a`` with every one of ``b``; rows x, y, w, h with centres."""
    x = np.minimum(a[:, None, 0] + a[:, None, 2] / 2, b[None, :, 0] + b[None, :, 2] / 2) - np.maximum(a[:, None, 0] - a[:, None, 2] / 2, b[None, :, 0] - b[None, :, 2] / 2)
    y = np.minimum(a[:, None, 1] + a[:, None, 3] / 2, b[None, :, 1] + b[None, :, 3] / 2) - np.maximum(a[:, None, 1] - a[:, None, 3] / 2, b[None, :, 1] - b[None, :, 3] / 2)
    inter = np.maximum(x, 0) * np.maximum(y, 0)
    return inter / (a[:, None, 2] * a[:, None, 3] + b[None, :, 2] * b[None, :, 3] - inter)


def looks_of(boxes: np.ndarray) -> np.ndarray:
    """The looks of a box or of many; zeros where they are not known."""
    return boxes[..., 4:] if boxes.shape[-1] == 4 + LOOKS else np.zeros((*boxes.shape[:-1], LOOKS))


class Prefix:
    """A running track: last box and time, speed in px a frame, hidden state, and a running mean of its looks."""

    __slots__ = ("id", "box", "t", "v", "hidden", "n", "category", "looks")

    def __init__(self, id_: int, box: np.ndarray, t: int, category: str):
        self.id, self.box, self.t, self.category = id_, box, t, category
        self.v, self.hidden, self.n, self.looks = np.zeros(2), np.zeros(HIDDEN), 1, looks_of(box)


class Pool:
    """Running tracks of many runs as arrays, a place each: what :class:`Prefix` holds of one."""

    def __init__(self, most: int, width: int):
        self.box, self.t, self.v, self.n = np.empty((most, width)), np.zeros(most, np.int64), np.zeros((most, 2)), np.ones(most, np.int64)
        self.hidden, self.looks = np.zeros((most, HIDDEN)), np.empty((most, LOOKS))

    def start(self, at: np.ndarray, boxes: np.ndarray, t: int) -> None:
        self.box[at], self.t[at], self.looks[at] = boxes, t, looks_of(boxes)


class Overlap:
    """Overlap with the last box, as heuristic trackers use it."""

    least = 0.3

    def update(self, p: Prefix, box: np.ndarray, t: int) -> None:
        p.box, p.t, p.n = box, t, p.n + 1

    def score(self, prefixes: list[Prefix], boxes: np.ndarray, t: int) -> np.ndarray:
        return iou(np.array([p.box for p in prefixes]), boxes)

    def pairs(self, pool: Pool, at: np.ndarray, boxes: np.ndarray, i: np.ndarray, j: np.ndarray, t: int) -> np.ndarray:
        """Scores of the pairs (place ``at[i]``, box ``j``), as ``score`` has them."""
        a, b = pool.box[at[i]], boxes[j]
        x = np.minimum(a[:, 0] + a[:, 2] / 2, b[:, 0] + b[:, 2] / 2) - np.maximum(a[:, 0] - a[:, 2] / 2, b[:, 0] - b[:, 2] / 2)
        y = np.minimum(a[:, 1] + a[:, 3] / 2, b[:, 1] + b[:, 3] / 2) - np.maximum(a[:, 1] - a[:, 3] / 2, b[:, 1] - b[:, 3] / 2)
        inter = np.maximum(x, 0) * np.maximum(y, 0)
        return inter / (a[:, 2] * a[:, 3] + b[:, 2] * b[:, 3] - inter)

    def step(self, pool: Pool, old: np.ndarray, found: np.ndarray, new: np.ndarray, fresh: np.ndarray, t: int) -> None:
        """Places ``old`` go on with the boxes ``found``, places ``new`` begin with ``fresh``."""
        pool.start(new, fresh, t)
        pool.box[old], pool.t[old] = found, t
        pool.n[old] += 1


class Motion(Overlap):
    """A recursive speed state: nearness to where the prefix would be by now; boxes without a speed yet get a wider reach."""

    least = 0.5

    def update(self, p: Prefix, box: np.ndarray, t: int) -> None:
        now = (box[:2] - p.box[:2]) / max(1, t - p.t)
        p.v = now if p.n == 1 else 0.4 * p.v + 0.6 * now
        super().update(p, box, t)

    def offsets(self, prefixes: list[Prefix], boxes: np.ndarray, t: int) -> tuple[np.ndarray, np.ndarray]:
        at = np.array([p.box[:2] + p.v * (t - p.t) for p in prefixes])
        off = boxes[None, :, :2] - at[:, None]
        reach = np.array([0.6 * np.hypot(*p.box[2:4]) + (9.0 * (t - p.t) if p.n == 1 else 1.2 * (t - p.t)) for p in prefixes])
        return off, reach

    def score(self, prefixes: list[Prefix], boxes: np.ndarray, t: int) -> np.ndarray:
        off, reach = self.offsets(prefixes, boxes, t)
        return np.exp(-0.69 * (np.hypot(off[..., 0], off[..., 1]) / reach[:, None]) ** 2)

    def reaches(self, pool: Pool, at: np.ndarray, boxes: np.ndarray, i: np.ndarray, j: np.ndarray, t: int) -> tuple[np.ndarray, np.ndarray]:
        """``offsets`` of pairs."""
        gap = t - pool.t[at]
        off = boxes[j, :2] - (pool.box[at, :2] + pool.v[at] * gap[:, None])[i]
        reach = 0.6 * np.hypot(pool.box[at, 2], pool.box[at, 3]) + np.where(pool.n[at] == 1, 9.0, 1.2) * gap
        return off, reach[i]

    def pairs(self, pool: Pool, at: np.ndarray, boxes: np.ndarray, i: np.ndarray, j: np.ndarray, t: int) -> np.ndarray:
        off, reach = self.reaches(pool, at, boxes, i, j, t)
        return np.exp(-0.69 * (np.hypot(off[:, 0], off[:, 1]) / reach) ** 2)

    def step(self, pool: Pool, old: np.ndarray, found: np.ndarray, new: np.ndarray, fresh: np.ndarray, t: int) -> None:
        now = (found[:, :2] - pool.box[old, :2]) / np.maximum(1, t - pool.t[old])[:, None]
        pool.v[old] = np.where((pool.n[old] == 1)[:, None], now, 0.4 * pool.v[old] + 0.6 * now)
        super().step(pool, old, found, new, fresh, t)


class Recurrent(Motion):
    """A gated recurrent state over the prefix's boxes, speeds, looks and elapsed frames, and a match net on it, trained together.

    The elapsed frames are an input and training sequences are sampled at many gaps, so one set of weights serves all gaps. Without
    weights the score is that of :class:`Motion`.
    """

    least = 0.5

    def __init__(self, weights: dict | None = None, elapsed: bool = True):
        self.elapsed, self.net = elapsed, weights

    def inputs(self, box: np.ndarray, v: np.ndarray, gap: int) -> np.ndarray:
        plain = [box[0] / 640, box[1] / 384, box[2] / 96, box[3] / 64, v[0] / 10, v[1] / 10, np.log2(1 + gap) / 5 if self.elapsed else 0.0]
        return np.concatenate([plain, looks_of(box)])

    def start(self, p: Prefix) -> None:
        if self.net is not None:
            p.hidden = cell(self.net["wx"], self.net["wh"], self.inputs(p.box, p.v, 0), p.hidden)[0]

    def update(self, p: Prefix, box: np.ndarray, t: int) -> None:
        gap = t - p.t
        super().update(p, box, t)
        p.looks = 0.6 * p.looks + 0.4 * looks_of(box)
        if self.net is not None:
            p.hidden = cell(self.net["wx"], self.net["wh"], self.inputs(box, p.v, gap), p.hidden)[0]

    def plain(self, prefixes: list[Prefix], boxes: np.ndarray, t: int) -> tuple[np.ndarray, np.ndarray]:
        """(prefixes, boxes, PLAIN) offsets, sizes and looks; (prefixes, 2) elapsed frames and whether a prefix has one box only."""
        off, reach = self.offsets(prefixes, boxes, t)
        gap = np.array([np.log2(1 + t - p.t) / 5 if self.elapsed else 0.0 for p in prefixes])
        young = np.array([p.n == 1 for p in prefixes], float)
        size = np.array([p.box[2:4] for p in prefixes])[:, None] / boxes[None, :, 2:4] - 1
        looks = np.linalg.norm(np.array([p.looks for p in prefixes])[:, None] - looks_of(boxes)[None], axis=-1)
        parts = [off[..., 0] / reach[:, None], off[..., 1] / reach[:, None], (off**2).sum(-1) / reach[:, None] ** 2, off[..., 0] / 100, off[..., 1] / 100, size[..., 0], size[..., 1], looks]
        return np.clip(np.stack(parts, -1), -6, 6), np.stack([gap, young], 1)

    def score(self, prefixes: list[Prefix], boxes: np.ndarray, t: int) -> np.ndarray:
        if self.net is None:
            return super().score(prefixes, boxes, t)
        plain, own = self.plain(prefixes, boxes, t)
        w = self.net
        # the part of the first layer that depends on the prefix alone is made once for all boxes
        state = np.concatenate([np.array([p.hidden for p in prefixes]), own], 1) @ w["a"][PLAIN:] + w["b"]
        hidden = np.tanh(plain @ w["a"][:PLAIN] + state[:, None])
        return 1 / (1 + np.exp(-np.clip(hidden @ w["c"] + w["d"], -30, 30)))

    def _elapsed(self, gap: np.ndarray) -> np.ndarray:
        return np.log2(1 + gap) / 5 if self.elapsed else np.zeros(len(gap))

    def pairs(self, pool: Pool, at: np.ndarray, boxes: np.ndarray, i: np.ndarray, j: np.ndarray, t: int) -> np.ndarray:
        if self.net is None:
            return super().pairs(pool, at, boxes, i, j, t)
        w = self.net
        off, reach = self.reaches(pool, at, boxes, i, j, t)
        plain = np.empty((len(i), PLAIN))
        plain[:, :2] = off / reach[:, None]
        plain[:, 2] = (off[:, 0] ** 2 + off[:, 1] ** 2) / reach**2
        plain[:, 3:5] = off / 100
        plain[:, 5:7] = pool.box[at, 2:4][i] / boxes[j, 2:4] - 1
        apart = pool.looks[at][i] - looks_of(boxes)[j]
        plain[:, 7] = np.sqrt((apart * apart).sum(1))
        np.minimum(np.maximum(plain, -6, out=plain), 6, out=plain)
        own = np.stack([self._elapsed(t - pool.t[at]), pool.n[at] == 1], 1)
        state = np.concatenate([pool.hidden[at], own], 1) @ w["a"][PLAIN:] + w["b"]
        return _sigmoid(np.tanh(plain @ w["a"][:PLAIN] + state[i]) @ w["c"] + w["d"])

    def step(self, pool: Pool, old: np.ndarray, found: np.ndarray, new: np.ndarray, fresh: np.ndarray, t: int) -> None:
        gap = np.concatenate([t - pool.t[old], np.zeros(len(new), np.int64)])
        super().step(pool, old, found, new, fresh, t)
        pool.looks[old] = 0.6 * pool.looks[old] + 0.4 * looks_of(found)
        if self.net is None:
            return
        every, x = np.concatenate([old, new]), np.empty((len(gap), INPUTS))
        x[:, :4] = pool.box[every, :4] / (640, 384, 96, 64)
        x[:, 4:6] = pool.v[every] / 10
        x[:, 6] = self._elapsed(gap)
        x[:, 7:] = looks_of(pool.box[every])
        pool.hidden[every] = cell(self.net["wx"], self.net["wh"], x, pool.hidden[every])[0]


def _sigmoid(z: np.ndarray) -> np.ndarray:
    return 1 / (1 + np.exp(-np.clip(z, -30, 30)))


def cell(wx: np.ndarray, wh: np.ndarray, x: np.ndarray, h: np.ndarray) -> tuple:
    """One step of the gated state for one input or a batch: the new state, and what its gradient needs."""
    z, r = _sigmoid(x @ wx[0].T + h @ wh[0].T), _sigmoid(x @ wx[1].T + h @ wh[1].T)
    c = np.tanh(x @ wx[2].T + (r * h) @ wh[2].T)
    return (1 - z) * h + z * c, z, r, c


def loss_and_gradient(w: dict, x: np.ndarray, plain: np.ndarray, own: np.ndarray, y: np.ndarray, weight: np.ndarray) -> tuple[float, dict]:
    """Cross-entropy of all matches of a batch of sequences, and its gradient through the match net and back through time.

    x: (sequences, steps, INPUTS) what the state reads; plain: (sequences, steps, boxes, PLAIN), own: (sequences, steps, 2) and
    y: (sequences, steps, boxes) the matches asked for after each step, with their weight (0 where there is none).
    """
    n, steps = x.shape[:2]
    h, kept = np.zeros((n, HIDDEN)), []
    loss = 0.0
    grad = {k: np.zeros_like(v) for k, v in w.items()}
    ups = []
    for t in range(steps):
        before = h
        h, z, r, c = cell(w["wx"], w["wh"], x[:, t], before)
        kept.append((before, z, r, c))
        state = np.concatenate([h, own[:, t]], 1)
        hidden = np.tanh(plain[:, t] @ w["a"][:PLAIN] + (state @ w["a"][PLAIN:] + w["b"])[:, None])
        p = _sigmoid(hidden @ w["c"] + w["d"])
        loss -= float((weight[:, t] * (y[:, t] * np.log(p + 1e-12) + (1 - y[:, t]) * np.log(1 - p + 1e-12))).sum())
        err = weight[:, t] * (p - y[:, t])
        back = err[..., None] * w["c"] * (1 - hidden * hidden)
        both = back.sum(1)
        grad["c"] += np.einsum("sm,smk->k", err, hidden)
        grad["d"] += err.sum()
        grad["b"] += both.sum(0)
        grad["a"][:PLAIN] += np.einsum("smf,smk->fk", plain[:, t], back)
        grad["a"][PLAIN:] += state.T @ both
        ups.append(both @ w["a"][PLAIN : PLAIN + HIDDEN].T)
    down = np.zeros((n, HIDDEN))
    for t in range(steps - 1, -1, -1):
        before, z, r, c = kept[t]
        g = down + ups[t]
        gc = g * z * (1 - c * c)
        gz = g * (c - before) * z * (1 - z)
        through = gc @ w["wh"][2]
        gr = through * before * r * (1 - r)
        for k, (gate, state) in enumerate(((gz, before), (gr, before), (gc, r * before))):
            grad["wx"][k] += gate.T @ x[:, t]
            grad["wh"][k] += gate.T @ state
        down = g * (1 - z) + through * r + gz @ w["wh"][0] + gr @ w["wh"][1]
    return loss, grad


def train_recurrent(x: np.ndarray, plain: np.ndarray, own: np.ndarray, y: np.ndarray, mask: np.ndarray, **options) -> dict:
    """:func:`train_by_parts` on one part."""
    return train_by_parts(lambda: [(x, plain, own, y, mask)], **options)


def train_by_parts(parts: Callable[[], Iterable[tuple[np.ndarray, ...]]], elapsed: bool = True, width: int = 16, steps: int = 120, batch: int = 256, seed: int = 5) -> dict:
    """Recurrent weights and match net by back-propagation through time (Adam); positives weigh as much as negatives.

    ``parts()`` goes through the sequences in parts (x, plain, own, y, mask), each mixed from all of them, so that one is held at a time. Batches go through
    a part in an order drawn by seed: ``steps`` of them with as many passes as that takes, or those of one pass if they are more.
    """
    rng = np.random.default_rng(seed)
    w = {
        "wx": rng.normal(0, 0.4, (3, HIDDEN, INPUTS)), "wh": rng.normal(0, 0.2, (3, HIDDEN, HIDDEN)), "a": rng.normal(0, 0.3, (PLAIN + HIDDEN + 2, width)), "b": np.zeros(width),
        "c": rng.normal(0, 0.3, width), "d": np.zeros(1),
    }
    m, v = ({k: np.zeros_like(a) for k, a in w.items()} for _ in range(2))

    def drawn() -> Iterator[tuple[np.ndarray, ...]]:
        for part in parts():
            order = rng.permutation(len(part[0]))
            for at in range(0, len(order), batch):
                yield tuple(a[order[at : at + batch]].astype(float) for a in part)

    t, passes = 0, 0
    while t < steps:
        for x, plain, own, y, mask in drawn():
            if passes and t == steps:
                break
            t += 1
            positive = mask * (y > 0)
            negative = mask - positive
            weight = positive * 0.5 / max(1.0, positive.sum()) + negative * 0.5 / max(1.0, negative.sum())
            _, grad = loss_and_gradient(w, x, plain, own, y, weight)
            for k in w:
                m[k] = 0.9 * m[k] + 0.1 * grad[k]
                v[k] = 0.99 * v[k] + 0.01 * grad[k] ** 2
                w[k] = w[k] - 0.02 * (m[k] / (1 - 0.9**t)) / (np.sqrt(v[k] / (1 - 0.99**t)) + 1e-8)
        passes += 1
        if not t:
            raise ValueError("no sequences to learn from")
    return w | {"elapsed": elapsed}
