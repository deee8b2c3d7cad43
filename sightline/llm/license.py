"""License statements: fixed phrases, and an exact containment join of text blocks with license templates."""

from __future__ import annotations

import re
from collections import Counter
from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import LOWER_TABLE, slices, tidy

WORD = re.compile("[^\\x00-\\x2F\\x3A-\\x60\\x7B-\\x7F]+")
#: The base phrases and their labels.
PHRASES = {"under the mit license": "mit", "apache license version 2": "apache-2", "cc by nc": "cc-by-nc"}
#: Short license statements and the notices that public licenses ask for; their word sets are the templates.
TEMPLATES = {
    "mit": [
        "released under the mit license",
        "permission is hereby granted free of charge to any person obtaining a copy of this software",
        "the above copyright notice and this permission notice shall be included in all copies or substantial portions of the software",
    ],
    "apache-2": [
        "licensed under the apache license version 2 0",
        "licensed under the apache license version 2 0 the license you may not use this file except in compliance with the license you may obtain a copy of the license at http www apache org licenses license 2 0",
    ],
    "cc-by-nc": ["licensed under cc by nc 4 0", "creative commons attribution noncommercial 4 0 international license"],
    "gpl-3": [
        "this work is licensed under the gnu general public license version 3",
        "you can redistribute it and or modify it under the terms of the gnu general public license as published by the free software foundation either version 3 of the license or at your option any later version",
    ],
    "bsd": ["redistribution and use in source and binary forms with or without modification are permitted provided that the following conditions are met"],
    "isc": ["permission to use copy modify and or distribute this software for any purpose with or without fee is hereby granted provided that the above copyright notice and this permission notice appear in all copies"],
    "mpl-2": ["this source code form is subject to the terms of the mozilla public license v 2 0 if a copy of the mpl was not distributed with this file you can obtain one at http mozilla org mpl 2 0"],
    "unlicense": ["this is free and unencumbered software released into the public domain"],
    "all-rights-reserved": ["all rights reserved"],
}
#: Templates are broadcast; their word sets must stay under this many words in all.
MAX_TEMPLATE_WORDS = 100_000


def words_of(text: str | None) -> list[str]:
    return WORD.findall((text or "").translate(LOWER_TABLE))


def _template_counts(docs: DataFrame, vocabulary: set[str]) -> dict[str, int]:
    """Documents that hold each template word, over all documents: the global frequency order."""

    @tidy
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        seen: Counter = Counter()
        for batch in slices(batches):
            for text in batch.column(0).to_pylist():
                seen.update(vocabulary.intersection(words_of(text)))
        yield pa.RecordBatch.from_arrays([pa.array(list(seen), pa.string()), pa.array(list(seen.values()), pa.int64())], ["word", "n"])

    rows = docs.select("text").mapInArrow(run, "word string, n bigint").groupBy("word").agg(F.sum("n").alias("n")).collect()
    return {r.word: r.n for r in rows}  # at most one row per template word


class Matcher:
    """Finds, for a block of words, the templates whose containment in the block reaches the threshold.

    All template words are ordered from rare to frequent over the corpus; a block's words that no template has play no part. A block with ``need`` of a
    template's n words holds one of its first n - need + 1 words (prefix filter: only these are indexed), has ``need`` words
    at least (length filter), and where the first common word stands at place i of the template and place j of the block, no more than
    the lesser of n - i and the block's size - j can be common (positional filter).
    """

    def __init__(self, templates: dict[str, list[str]], counts: dict[str, int], percent: int):
        every = {w for texts in templates.values() for t in texts for w in words_of(t)}
        self.rank = {w: i for i, w in enumerate(sorted(every, key=lambda w: (counts.get(w, 0), w)))}
        self.index: dict[int, list[tuple[int, int]]] = {}
        self.labels: list[str] = []
        self.sets: list[list[int]] = []
        self.needs: list[int] = []
        self.spans: list[int] = []  # words of each template, repeated ones too
        for label, texts in templates.items():
            for text in texts:
                order = sorted({self.rank[w] for w in words_of(text)})
                need = max(1, -(-percent * len(order) // 100))
                for place, word in enumerate(order[: len(order) - need + 1]):
                    self.index.setdefault(word, []).append((len(self.sets), place))
                self.labels.append(label)
                self.sets.append(order)
                self.needs.append(need)
                self.spans.append(len(words_of(text)))

    def candidates(self, block: list[int]) -> list[int]:
        """Templates that pass the filters, for a block's distinct words in order."""
        out, met = [], set()
        for j, word in enumerate(block):
            for k, place in self.index.get(word, ()):
                if k not in met:  # the first common word decides
                    met.add(k)
                    if len(block) >= self.needs[k] and min(len(self.sets[k]) - place, len(block) - j) >= self.needs[k]:
                        out.append(k)
        return out

    def block(self, words: list[str], found: dict[int, float]) -> None:
        """Adds templates whose words the block holds, wherever they stand in it."""
        block = sorted({r for w in words if (r := self.rank.get(w)) is not None})
        held = set(block)
        for k in self.candidates(block):
            same = len(held.intersection(self.sets[k]))
            if same >= self.needs[k]:
                found[k] = max(found.get(k, 0), same / len(self.sets[k]))

    def windows(self, words: list[str], found: dict[int, float], starts: dict[int, int]) -> None:
        """Adds templates that some run of as many words of the text as the template has holds, and where the first best run starts.

        Only the surroundings of a template's prefix words are looked at: a run without any can't reach the threshold.
        """
        at = [(i, r) for i, w in enumerate(words) if (r := self.rank.get(w)) is not None]
        near: dict[int, list[int]] = {}
        for n, (_, r) in enumerate(at):
            for k, _ in self.index.get(r, ()):
                near.setdefault(k, []).append(n)
        for k, hits in near.items():
            span, need, own = self.spans[k], self.needs[k], set(self.sets[k])
            done = 0
            while done < len(hits):  # a zone: hits whose surroundings touch
                first = last = done
                while last + 1 < len(hits) and at[hits[last + 1]][0] - at[hits[last]][0] < 2 * span:
                    last += 1
                done = last + 1
                low, high = at[hits[first]][0] - span, at[hits[last]][0] + span
                lo, hi = hits[first], hits[last] + 1
                while lo and at[lo - 1][0] > low:
                    lo -= 1
                while hi < len(at) and at[hi][0] < high:
                    hi += 1
                zone = at[lo:hi]
                if k not in self.candidates(sorted({r for _, r in zone})):
                    continue
                self._slide([x for x in zone if x[1] in own], k, span, need, found, starts, len(words))

    def _slide(self, zone: list[tuple[int, int]], k: int, span: int, need: int, found: dict[int, float], starts: dict[int, int], total: int) -> None:
        held: Counter = Counter()
        tail = 0
        for i, r in zone:
            held[r] += 1
            while zone[tail][0] <= i - span:
                gone = zone[tail][1]
                held[gone] -= 1
                if not held[gone]:
                    del held[gone]
                tail += 1
            if len(held) >= need and (share := len(held) / len(self.sets[k])) > found.get(k, 0):
                found[k] = share
                starts[k] = max(0, min(zone[tail][0], total - span))


def scan_licenses(docs: DataFrame, templates: dict[str, list[str]] | None = None, percent: int = 90, by: str = "line") -> DataFrame:
    """Per row of ``docs`` (doc_id, text): doc_id, n_words, n_base, first_word, last_word, base_labels, labels, score, blocks.

    Words: runs of characters other than ASCII punctuation, space and controls, after lower-casing A-Z. The base
    counts all places (overlapping ones too) where the words of a phrase follow each other; first_word and last_word are the
    smallest and largest start or null. ``labels`` adds the licenses with a template of which a line of the text contains
    ``percent`` per cent of the distinct words; ``blocks`` lists their line numbers; ``score`` is the best containment (1 with a
    base hit, 0 without any label). Null and empty texts have no words. Every line of a text is a block, whatever its length.
    With ``by`` "window" instead, every run of as many words as a template has is a block, over line breaks and paragraphs; ``blocks`` lists the words at which the first best runs start.
    """
    templates = TEMPLATES if templates is None else templates
    vocabulary = {w for texts in templates.values() for t in texts for w in words_of(t)}
    if len(vocabulary) > MAX_TEMPLATE_WORDS:
        raise ValueError("too many template words to broadcast")
    matcher = Matcher(templates, _template_counts(docs, vocabulary), percent)
    held = docs.sparkSession.sparkContext.broadcast(matcher)  # MAX_TEMPLATE_WORDS words
    phrases = [(f" {p} ", label) for p, label in PHRASES.items()]

    @tidy
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        matcher = held.value
        prefixes = {w for w, r in matcher.rank.items() if r in matcher.index}
        for batch in slices(batches):
            rows = []
            for doc_id, text in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist()):
                words = words_of(text)
                joined = f" {' '.join(words)} "
                places, base = [], set()
                for phrase, label in phrases:
                    at = joined.find(phrase)
                    while at >= 0:
                        places.append(joined.count(" ", 0, at))
                        base.add(label)
                        at = joined.find(phrase, at + 1)
                best: dict[int, float] = {}
                blocks = []
                if not prefixes.isdisjoint(words):
                    if by == "window":
                        starts: dict[int, int] = {}
                        matcher.windows(words, best, starts)
                        blocks = sorted(set(starts.values()))
                    else:
                        for i, line in enumerate(text.split("\n")):
                            found: dict[int, float] = {}
                            matcher.block(words_of(line), found)
                            if found:
                                blocks.append(i)
                            for k, v in found.items():
                                best[k] = max(best.get(k, 0), v)
                labels = base | {matcher.labels[k] for k in best}
                score = 1.0 if base else max(best.values(), default=0.0)
                rows.append((doc_id, len(words), len(places), min(places, default=None), max(places, default=None), ",".join(sorted(base)), ",".join(sorted(labels)), score, blocks))
            columns = list(zip(*rows)) or [()] * 9
            kinds = [batch.schema.field(0).type, *[pa.int64()] * 4, pa.string(), pa.string(), pa.float64(), pa.list_(pa.int64())]
            names = ["doc_id", "n_words", "n_base", "first_word", "last_word", "base_labels", "labels", "score", "blocks"]
            yield pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(columns, kinds)], names)

    kind = docs.schema["doc_id"].dataType.simpleString()
    return docs.select("doc_id", "text").mapInArrow(
        run, f"doc_id {kind}, n_words bigint, n_base bigint, first_word bigint, last_word bigint, base_labels string, labels string, score double, blocks array<bigint>"
    )
