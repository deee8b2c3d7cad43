"""Benchmark decontamination by canonical templates.

Numbers, names and units become typed placeholders; windows of the canonical words are joined by hash with those of the
benchmark; the values that fill the placeholders must correspond inside one alignment of item and document, which also
catches questions that were asked again with other values.
"""

from __future__ import annotations

import re
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from . import scan
from .common import slices, tidy

_TOKEN = re.compile(r"\d+(?:[.,]\d+)*|[^\W\d_]+|[.!?:\n|]|[%€$£°]")
#: Units, spelled out and short.
UNITS = {
    "mm", "cm", "m", "km", "mg", "g", "kg", "t", "ml", "l", "s", "sec", "second", "seconds", "min", "minute", "minutes", "h", "hour", "hours", "day", "days", "week", "weeks", "month", "months", "year", "years",
    "meter", "meters", "metre", "metres", "kilometer", "kilometers", "kilometre", "kilometres", "gram", "grams", "kilogram", "kilograms", "liter", "liters", "litre", "litres", "mile", "miles", "foot", "feet", "inch", "inches",
    "dollar", "dollars", "euro", "euros", "pound", "pounds", "cent", "cents", "percent", "degree", "degrees", "%", "€", "$", "£", "°",
}
#: The benchmark's windows are broadcast in parts of about so many (16 bytes each).
BROADCAST_WINDOWS = 500_000
#: Texts that a task holds as Python strings at once.
_ROWS = 512
#: Hits of one alignment may be so many words off it, for added or dropped words.
SHIFT = 3
#: A part of an item, or an edited one, has so many words at least that are no placeholders.
LITERAL = 5


def canonical(text: str | None) -> list[tuple[list[str], list[str | None]]]:
    """Canonical forms of a text: words and, for placeholders, the value behind each (else None).

    In both, numbers become <num> and a unit right after a number <unit>, and words are lower-cased. In the second, which is left
    out where it is the same, capitalised words are <name> too, those that begin a sentence as well, so that the form does not
    depend on what stands before; runs of names inside a sentence are one. Texts without any lower-case letter have no names.
    """
    words: list[str] = []
    values: list[str | None] = []
    names: list[int] = []
    fresh: set[int] = {0}
    text = text or ""
    named = any(c.islower() for c in text)
    for token in _TOKEN.findall(text):
        first = token[0]
        if first in ".!?:\n|":
            fresh.add(len(words))
            continue
        low = token.lower()
        if first.isdigit():
            words.append("<num>")
            values.append(token)
        elif low in UNITS and words and words[-1] == "<num>":
            words.append("<unit>")
            values.append(low)
        elif first in "%€$£°":
            continue
        else:
            if named and first.isupper():
                names.append(len(words))
            words.append(low)
            values.append(None)
    if not names:
        return [(words, values)]
    out_words: list[str] = []
    out_values: list[str | None] = []
    done, before = 0, -2
    for at in names:
        out_words += words[done:at]
        out_values += values[done:at]
        if before == at - 1 and at not in fresh:
            out_values[-1] += " " + words[at]  # type: ignore[operator]
        else:
            out_words.append("<name>")
            out_values.append(words[at])
        done, before = at + 1, at
    return [(words, values), (out_words + words[done:], out_values + values[done:])]


_FIXED = {"<num>": scan.NUM, "<unit>": scan.UNIT, "<name>": scan.NAME}


class Index:
    """Windows of some benchmark items, in one form, for the search in documents: sorted hashes with item and place, and each item's words and values."""

    def __init__(self, size: int):
        self.size, self.items, self.parts, self.n = size, [], [], 0
        self.brief: dict[tuple[str, ...], list[int]] = {}
        self.known: dict[str, int] = {}

    def add(self, item_id, words: list[str], values: list[str | None]) -> None:
        n = len(words)
        if not n:
            return
        if n < 3:  # met by texts of just these words
            self.brief.setdefault(tuple(words), []).append(len(self.items))
            self.items.append((item_id, words, n, 1, values))
            self.n += 1
            return
        width = n if n < self.size else min(self.size, max(3, (n - 1) // 2))  # one edit leaves a window of every item from ``size`` words on
        for w in words:
            if w not in self.known:
                self.known[w] = _FIXED.get(w) or scan.word_hash(w)
        got = scan.window_hashes(np.array([self.known[w] for w in words], np.uint64), width)
        self.parts.append((np.full(len(got), len(self.items)), np.arange(len(got)), got))
        self.items.append((item_id, words, width, len(np.unique(got)), values))
        self.n += len(got)

    def close(self) -> Index:
        if not self.parts:
            self.parts = [(np.zeros(0, int), np.zeros(0, int), np.zeros(0, np.uint64))]
        item, place, hashes = (np.concatenate(c) for c in zip(*self.parts))
        order = np.argsort(hashes, kind="stable")
        self.parts, self.item, self.place, self.hashes = [], item[order].astype(np.int32), place[order].astype(np.int32), hashes[order]
        self.widths = sorted({i[2] for i in self.items if len(i[1]) > 2})
        return self

    def hits(self, words: list[str]) -> dict[int, tuple[np.ndarray, np.ndarray]]:
        """Item -> (places in the item, places in the document) of all windows that both hold, word for word."""
        hashes, out = np.array([self.known.get(w, 0) for w in words], np.uint64), []  # what no item holds is only a gap
        for width in self.widths:
            got = scan.window_hashes(hashes, width)
            lo, hi = np.searchsorted(self.hashes, got), np.searchsorted(self.hashes, got, "right")
            at = np.flatnonzero(hi > lo)
            if len(at):
                n = hi[at] - lo[at]
                k = np.repeat(lo[at] - np.cumsum(n) + n, n) + np.arange(n.sum())
                at = np.repeat(at, n)
                same = [words[q : q + width] == self.items[i][1][p : p + width] for i, p, q in zip(self.item[k].tolist(), self.place[k].tolist(), at.tolist())]
                out.append((self.item[k[same]], self.place[k[same]], at[same]))
        if not out:
            return {}
        item, place, found = (np.concatenate(c) for c in zip(*out))
        order = np.argsort(item, kind="stable")
        item, place, found = item[order], place[order], found[order]
        cuts = np.flatnonzero(np.diff(item)) + 1
        return {int(i[0]): (p, q) for i, p, q in zip(np.split(item, cuts), np.split(place, cuts), np.split(found, cuts)) if len(i)}


def _alignments(asked: np.ndarray, found: np.ndarray) -> Iterator[dict[int, int]]:
    """Hits (item place -> document place) of each way to lay the item on the document, those with most hits first.

    A way is one distance of places, with hits up to ``SHIFT`` words off it (added or dropped words); for each item place the nearest counts.
    """
    off = found - asked
    order = np.lexsort((asked, off))
    asked, found, off = asked[order], found[order], off[order]
    anchors, n = np.unique(off, return_counts=True)
    for a in anchors[np.argsort(-n, kind="stable")].tolist():
        lo, hi = np.searchsorted(off, a - SHIFT), np.searchsorted(off, a + SHIFT, "right")
        near = lo + np.argsort(np.abs(off[lo:hi] - a), kind="stable")
        out: dict[int, int] = {}
        for p, q in zip(asked[near].tolist(), found[near].tolist()):
            out.setdefault(p, q)
        yield out


def _judge(hits: dict[int, int], item: tuple, words: list[str], values: list, size: int, coverage: float) -> tuple | None:
    """(words met, n_windows, n_hit, coverage, consistent, same_values) of one alignment if it is a leak."""
    _, asked, width, n_windows, own = item
    n = len(asked)
    met: dict[int, int] = {}
    for p, q in hits.items():
        for i in range(width):
            met.setdefault(p + i, q + i)
    slots = {(own[p], values[q]) for p, q in met.items() if own[p] is not None}
    # a run of names at an end of the item may go on in the document
    slots -= {s for s in slots if s[0] != s[1] and any(p in met and s == (own[p], values[met[p]]) and asked[p] == "<name>" and cut(f" {s[0]}" if p == 0 else f"{s[0]} ") for p, cut in ((0, s[1].endswith), (n - 1, s[1].startswith)))}
    if len({a for a, _ in slots}) < len(slots):
        return None
    share = min(1.0, len(hits) / n_windows)
    run = longest = 0
    for p in range(n):
        run = run + 1 if p in met else 0
        longest = max(longest, run)
    # words beside the windows, which are too short for one of their own, are held against the document with one word of shift
    lo, hi = min(met), max(met)
    for ends, at in ((range(lo), met[lo] - lo), (range(hi + 1, n), met[hi] - hi)):
        some = [[(p, p + at + d) for p in ends if own[p] is None and 0 <= p + at + d < len(words) and words[p + at + d] == asked[p]] for d in (0, 1, -1)]
        met |= dict(max(some, key=len))
    plain = sum(own[p] is None for p in met)
    rest = sum(v is None for v in own) - plain
    whole = len(hits) == n_windows or (n >= size and rest <= 1 and plain >= LITERAL)
    part = longest >= min(size + 2, max(size, (n + 1) // 2)) and plain >= LITERAL
    if not (whole or part or (width == size and share >= coverage)):
        return None
    return len(met), n_windows, min(len(hits), n_windows), share, True, all(a == b for a, b in slots)


def leaks_of(text: str | None, indexes: list[Index], coverage: float) -> dict:
    """Item id -> its best alignment with the text, in either form, that is a leak."""
    out: dict = {}
    for (words, values), index in zip(canonical(text), indexes):
        for k in index.brief.get(tuple(words), ()) if len(words) < 3 else ():
            slots = {(a, b) for a, b in zip(index.items[k][4], values) if a is not None}
            if len({a for a, _ in slots}) == len(slots):
                out[index.items[k][0]] = (1.0, (len(words), 1, 1, 1.0, True, all(a == b for a, b in slots)))
        for k, (asked, found) in index.hits(words).items():
            item = index.items[k]
            for hits in _alignments(asked, found):
                got = _judge(hits, item, words, values, index.size, coverage)
                if got:
                    best = out.get(item[0])
                    share = (got[0] / len(item[1]), got)
                    if best is None or share > best:
                        out[item[0]] = share
                if got and got[0] == len(item[1]) and got[-1]:
                    break
    return {k: got for k, (_, got) in out.items()}


def _may_leak(texts: list[str], filters: list[scan.Filter], units: np.ndarray, brief: bool) -> list[int]:
    """Places of the texts that hold a window of the benchmark in either form, of odd ones, and of very short ones where items are so short."""
    out: list[int] = []
    for at, to in scan.steps(texts):
        words = scan.Words(texts[at:to], units)
        found = words.odd.copy()
        for (hashes, own), some in zip(words.forms, filters):
            found[some.texts(hashes, own)] = True
            if brief:
                found |= np.bincount(own, minlength=to - at) < 3
        out += (at + np.flatnonzero(found)).tolist()
    return out


def _indexes(benchmark: DataFrame, size: int) -> Iterator[list[Index]]:
    """The whole benchmark by form, in parts of at most ``BROADCAST_WINDOWS`` windows or one item."""
    part = [Index(size), Index(size)]
    for r in benchmark.where("item_id is not null").select("item_id", "text").toLocalIterator():
        for index, form in zip(part, canonical(r[1])):
            index.add(r[0], *form)
        if sum(index.n for index in part) >= BROADCAST_WINDOWS:
            yield [index.close() for index in part]
            part = [Index(size), Index(size)]
    if any(index.n for index in part):
        yield [index.close() for index in part]


def find_leaks(docs: DataFrame, benchmark: DataFrame, size: int = 8, coverage: float = 0.6) -> DataFrame:
    """Pairs (doc_id, item_id, n_windows, n_hit, coverage, consistent, same_values) of documents with benchmark items in them.

    An item with fewer than ``size`` canonical words counts as one window of all its words; one of one or two words is met by a text of
    just these words, and one without words by nothing. Texts are first scanned as arrays of hashes for windows of the benchmark; what that finds is compared word for word. Every place of
    a window counts; an item is laid on a document in all ways that windows of both allow, and judged for each way alone. A pair is
    returned when in one of them the slots are consistent and one of these holds: the share of the item's windows in the document
    reaches ``coverage``; all its words but one are there; ``size`` + 2 words in a row are there, or half of an item of under twice
    that, but not under ``size``. Items of under twice ``size`` words have shorter windows. Consistent: each value of the item goes with one value of the document (two values of the item may become one by chance).
    Items and documents are compared in two forms, with names as words and as placeholders; the better one counts.
    ``same_values`` tells a literal copy from a question with other values. Null texts and ids are left out; empty tables give no
    pairs. The benchmark's windows are broadcast in parts of a fixed size, each with a pass over the documents.
    """
    spark = docs.sparkSession
    doc, item = docs.schema["doc_id"].dataType.simpleString(), benchmark.schema["item_id"].dataType
    kind = f"doc_id {doc}, item_id {item.simpleString()}, met bigint, n_windows bigint, n_hit bigint, coverage double, consistent boolean, same_values boolean"
    given = docs.where("doc_id is not null and text is not null").select("doc_id", "text")
    out = spark.createDataFrame([], kind)
    for part in _indexes(benchmark, size):
        held = spark.sparkContext.broadcast(part)

        @tidy
        def run(batches: Iterator[pa.RecordBatch], held=held) -> Iterator[pa.RecordBatch]:
            from pyspark.sql.pandas.types import to_arrow_type

            kinds = [to_arrow_type(item), pa.int64(), pa.int64(), pa.int64(), pa.float64(), pa.bool_(), pa.bool_()]
            names = ["doc_id", "item_id", "met", "n_windows", "n_hit", "coverage", "consistent", "same_values"]
            indexes = held.value
            filters = [scan.Filter(index.hashes, index.widths) for index in indexes]
            units = np.array([scan.word_hash(u) for u in UNITS], np.uint64)
            brief = any(index.brief for index in indexes)
            for part in slices(batches, _ROWS):
                ids, texts = part.column(0), part.column(1).to_pylist()
                rows = []
                for k in _may_leak(texts, filters, units, brief):
                    rows += [(ids[k].as_py(), item_id, *got) for item_id, got in leaks_of(texts[k], indexes, coverage).items()]
                yield pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(list(zip(*rows)) or [()] * 8, [part.schema.field(0).type, *kinds])], names)

        out = out.unionByName(given.mapInArrow(run, kind))
    best = F.max(F.struct("met", "n_windows", "n_hit", "coverage", "consistent", "same_values")).alias("b")
    return out.groupBy("doc_id", "item_id").agg(best).select("doc_id", "item_id", "b.n_windows", "b.n_hit", "b.coverage", "b.consistent", "b.same_values")
