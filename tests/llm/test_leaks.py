"""Decontamination against brute force: every window of every item held against every place of every text."""

import numpy as np
import pytest

from sightline.llm import decontam as d
from sightline.llm import scan

WORDS = "the big Haus dog runs Über old town Straße and km kg buys Tom Ann Paris 3 12 1,5 7.25 % € a de la où été σοφός x² word kilo 你好 Ünal percent hours . , ? ! | ( -".split()
DOC, ITEM = "doc_id long, text string", "item_id long, text string"


def some_text(rng, n):
    return " ".join(str(w) for w in rng.choice(WORDS, n))


def plain_leaks(text, items, size=8, coverage=0.6):
    """Items in a text by comparing words at all places, without hashes, index or filter."""
    out = {}
    for form, (words, values) in enumerate(d.canonical(text)):
        for item_id, item in items:
            forms = d.canonical(item)
            if form >= len(forms) or not forms[form][0]:
                continue
            asked, own = forms[form]
            n = len(asked)
            if n < 3:
                slots = {(a, b) for a, b in zip(own, values) if a is not None}
                if words == asked and len({a for a, _ in slots}) == len(slots):
                    out[item_id] = max(out.get(item_id, 0), 1.0)
                continue
            width = n if n < size else min(size, max(3, (n - 1) // 2))
            places = [(p, q) for p in range(n - width + 1) for q in range(len(words) - width + 1) if words[q : q + width] == asked[p : p + width]]
            windows = len({tuple(asked[p : p + width]) for p in range(n - width + 1)})
            for a in {q - p for p, q in places}:
                hits = {}
                for p, q in sorted(places, key=lambda h: (abs(h[1] - h[0] - a), h[1] - h[0], h[0])):
                    if abs(q - p - a) <= d.SHIFT:
                        hits.setdefault(p, q)
                got = d._judge(hits, (item_id, asked, width, windows, own), words, values, size, coverage)
                if got:
                    out[item_id] = max(out.get(item_id, 0), got[0] / n)
    return out


@pytest.mark.parametrize("seed", range(3))
def test_scan_is_canonical(seed):
    rng = np.random.default_rng(seed)
    texts = [some_text(rng, int(rng.integers(0, 60))) for _ in range(80)] + ["", "3", "A. B c. D E f 5 % % $ 4 kg € x", "İstanbul ⓐ Σίσυφος x", "d٣e ٣.٤ 1.2.3 ., 5 ,6 7. 8", "ALL UPPER TEXT 4 KM", "\n\n|a"]
    words = scan.Words(texts, np.array([scan.word_hash(u) for u in d.UNITS], np.uint64))
    fixed = {"<num>": scan.NUM, "<unit>": scan.UNIT, "<name>": scan.NAME}
    for k, text in enumerate(texts):
        forms = d.canonical(text)
        for (hashes, own), (want, _) in zip(words.forms, forms * 2 if len(forms) == 1 else forms):
            assert words.odd[k] or hashes[own == k].tolist() == [fixed.get(w) or scan.word_hash(w) for w in want]
    assert words.odd[texts.index("İstanbul ⓐ Σίσυφος x")] and not words.odd[-2]


@pytest.mark.parametrize("seed", range(3))
def test_equals_brute_force(spark, seed):
    rng = np.random.default_rng(seed)
    items = [(k, some_text(rng, int(n))) for k, n in enumerate(rng.integers(1, 30, 25))] + [(90, "Paris"), (91, "3 km"), (92, None), (93, "...")]
    docs, planted = [], set()
    for k in range(120):
        before, after = (some_text(rng, int(n)) for n in rng.integers(0, 25, 2))
        i, item = items[int(rng.integers(0, 25))]
        words = item.split()
        kind = int(rng.integers(0, 6))
        if kind == 1 and len(words) > 9:
            words[int(rng.integers(0, len(words)))] = "other"
        elif kind == 2:
            words = [str(int(rng.integers(20, 30))) if w in ("3", "12") else w for w in words]
        elif kind == 3:
            words = [w.upper() for w in words]
        elif kind == 4:
            words = words[: len(words) // 2]
        docs.append((k, f"{before} {' '.join(words)} {after}" if kind else f"{before} {after}"))
        if kind == 5 and len(d.canonical(item)[0][0]) >= 9:
            planted.add((k, i))
    docs += [(500, "Paris"), (501, "4 km"), (502, "in Paris"), (503, None), (504, "")]
    got = {(r.doc_id, r.item_id) for r in d.find_leaks(spark.createDataFrame(docs, DOC), spark.createDataFrame(items, ITEM)).collect()}
    want = {(k, i) for k, text in docs if text is not None for i in plain_leaks(text, [x for x in items if x[1] is not None])}
    assert got == want and planted <= got and {(500, 90), (501, 91)} <= got and (502, 90) not in got


def test_parts_of_the_benchmark_and_odd_tables(spark, monkeypatch):
    rng = np.random.default_rng(9)
    items = [(k, some_text(rng, 20)) for k in range(30)]
    docs = spark.createDataFrame([(k, f"x y {t} z", 1, 2.0) for k, t in items] * 2, DOC + ", item_id int, met double")
    bench = spark.createDataFrame(items, ITEM)
    want = {tuple(r) for r in d.find_leaks(docs, bench).select("doc_id", "item_id").collect()}
    monkeypatch.setattr(d, "BROADCAST_WINDOWS", 50)
    assert {tuple(r) for r in d.find_leaks(docs, bench).select("doc_id", "item_id").collect()} == want >= {(k, k) for k, _ in items}
