"""Canonical words of many texts at once, as hashes: the fast half of the template join.

Does what ``decontam.canonical`` does, but over arrays of code points instead of text by text. Texts whose case or
digits follow rules of their own (a few characters, see ``ODD``) are marked instead, and the caller looks at them itself.
"""

from __future__ import annotations

import numpy as np

from .hashing import mix

_MASK = (1 << 64) - 1
_BASE = 0x9E3779B97F4A7C15
_BACK = pow(_BASE, -1, 1 << 64)
#: Code points worked on at once, but for longer texts.
STEP = 1 << 18
LOWER, UPPER, LETTER, DIGIT, MARK, POINT, COMMA, MONEY, ODD = range(1, 10)
_GROUP = np.array([0, 1, 1, 1, 2, 0, 0, 0, 3, 0], np.uint8)
_CLASS = np.zeros(0x110000, np.uint8)
_KNOWN = np.zeros(0x1100, bool)
_POWERS: dict[int, np.ndarray] = {}


def _class_of(code: int) -> int:
    c = chr(code)
    if c in "!?:\n|":
        return MARK
    if c in ".,":
        return POINT if c == "." else COMMA
    if c in "%€$£°":
        return MONEY
    if c.isdecimal():
        return DIGIT
    # context decides how these are lower-cased, or they are digits inside words
    if len(c.lower()) != 1 or c == "Σ" or c.isdigit() or (c.islower() and not c.isalnum()):
        return ODD
    if c.isalnum():
        return LOWER if c.islower() else UPPER if c.isupper() else LETTER
    return 0


def _classes(codes: np.ndarray) -> np.ndarray:
    pages = [0, 1] if codes.max(initial=0) < 512 else np.unique(codes >> 8).tolist()
    for p in pages:
        if not _KNOWN[p]:
            _CLASS[p << 8 : (p + 1) << 8] = [_class_of(c) for c in range(p << 8, (p + 1) << 8)]
            _KNOWN[p] = True
    return _CLASS[codes]


def powers(n: int, base: int = _BASE) -> np.ndarray:
    """base ** 0, 1, ... modulo 2 ** 64; what a long text needs beyond a step is not kept."""
    have = _POWERS.get(base)
    if have is None or len(have) < n:
        have = np.full(max(n, STEP + 1), base & _MASK, np.uint64)
        have[0] = 1
        have = np.multiply.accumulate(have)
        if n <= 4 * STEP:
            _POWERS[base] = have
    return have[:n]


def word_hash(word: str) -> int:
    """Hash of a lower-cased word."""
    codes = np.frombuffer(word.encode("utf-32-le"), np.uint32).astype(np.uint64)
    return int(mix((codes * powers(len(codes))).sum(keepdims=True), 5)[0])


NUM, UNIT, NAME = (int(mix(np.array([k], np.uint64), 77)[0]) for k in (1, 2, 3))


def window_hashes(words: np.ndarray, width: int) -> np.ndarray:
    """Hashes of all windows of ``width`` word hashes, at whatever place they stand."""
    n = len(words)
    if n < width or not width:
        return np.zeros(0, np.uint64)
    sums = np.zeros(n + 1, np.uint64)
    np.cumsum(words * powers(n), out=sums[1:])
    x = (sums[width:] - sums[:-width]) * powers(n - width + 1, _BACK)
    x ^= x >> np.uint64(31)
    return x * np.uint64((0xBF58476D1CE4E5B9 + 2 * width) & _MASK)


class Words:
    """Word hashes of consecutive texts in both forms, with the text that each word belongs to."""

    def __init__(self, texts: list[str], units: np.ndarray):
        joined = "\n".join(texts) + "\n"
        self.sizes = np.array([len(t) + 1 for t in texts], np.int64)
        codes = np.frombuffer(joined.encode("utf-32-le", "surrogatepass"), np.uint32)
        small = joined.lower()
        kind = _classes(codes)
        ends = np.cumsum(self.sizes)
        firsts = ends - self.sizes
        self.odd = np.maximum.reduceat(kind, firsts) == ODD
        if len(small) != len(joined):  # only odd characters do that, and what they are lower-cased to counts nowhere
            small = "".join(c if len(c.lower()) != 1 else c.lower() for c in joined)
        low = np.frombuffer(small.encode("utf-32-le", "surrogatepass"), np.uint32)
        joints = np.flatnonzero((kind == POINT) | (kind == COMMA))
        joints = joints[joints > 0]
        joints = joints[(kind[joints - 1] == DIGIT) & (kind[joints + 1] == DIGIT)]
        kind[joints] = DIGIT
        group = _GROUP[kind]
        opens = group != 0
        opens[1:] &= (group[1:] != group[:-1]) | (group[1:] == 3)
        starts = np.flatnonzero(opens)
        own = np.repeat(np.arange(len(texts)), np.diff(np.searchsorted(starts, np.append(0, ends))))
        if not len(starts):
            self.forms = [(np.zeros(0, np.uint64), own), (np.zeros(0, np.uint64), own)]
            return
        value = low.astype(np.uint64)
        value[group != 1] = 0
        value *= powers(len(value))
        words = mix(np.add.reduceat(value, starts) * powers(len(value), _BACK)[starts], 5)
        what = group[starts]
        after = np.flatnonzero((what[:-1] == 2) & (own[:-1] == own[1:])) + 1
        unit = np.zeros(len(starts), bool)
        unit[after] = (what[after] == 3) | ((what[after] == 1) & np.isin(words[after], units))
        words[what == 2] = NUM
        words[unit] = UNIT
        named = np.logical_or.reduceat(kind == LOWER, firsts)
        name = (what == 1) & ~unit & (kind[starts] == UPPER) & named[own]
        marks = np.cumsum((kind == MARK) | (kind == POINT), dtype=np.int32)[starts]
        keep = (what != 3) | unit
        words, own, name, marks = words[keep], own[keep], name[keep], marks[keep]
        run = name.copy()
        run[:1] = False
        run[1:] &= name[:-1] & (marks[1:] == marks[:-1])
        self.forms = [(words, own), (np.where(name, np.uint64(NAME), words)[~run], own[~run])]


class Filter:
    """Which texts may hold a window of an index: a table of bits by hash first, then the hashes themselves."""

    def __init__(self, hashes: np.ndarray, widths: list[int]):
        self.widths, self.hashes = widths, np.unique(hashes)
        self.bits = min(26, max(16, int(len(self.hashes)).bit_length() + 5))
        self.table = np.zeros(1 << self.bits, bool)
        self.table[self._slot(self.hashes)] = True

    def _slot(self, hashes: np.ndarray) -> np.ndarray:
        return (hashes >> np.uint64(64 - self.bits)).astype(np.int64)

    def texts(self, words: np.ndarray, own: np.ndarray) -> np.ndarray:
        out = []
        for width in self.widths:
            got = window_hashes(words, width)
            at = np.flatnonzero(self.table[self._slot(got)])
            at = at[own[at] == own[at + width - 1]]
            near = np.minimum(np.searchsorted(self.hashes, got[at]), max(0, len(self.hashes) - 1))
            out.append(own[at[self.hashes[near] == got[at]]] if len(self.hashes) else own[:0])
        return np.concatenate(out) if out else own[:0]


def steps(texts: list[str]):
    """Places where runs of texts of about ``STEP`` characters begin and end."""
    at = 0
    while at < len(texts):
        to, held = at, 0
        while to < len(texts) and (to == at or held + len(texts[to]) < STEP):
            held += len(texts[to]) + 1
            to += 1
        yield at, to
        at = to
