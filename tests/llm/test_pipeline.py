"""The whole pipeline against a plain Python version of its stages, and what the toxicity penalty does."""

import hashlib

import numpy as np
from test_operators import DATA, plain_components, plain_lines

import corpus_pipeline as cp
from sightline.llm import decontam, toxicity
from sightline.llm.queries import BYTE_BPE, REJECT, learn


def test_run_equals_plain_python(spark):
    from tokenizers import Tokenizer

    docs = cp.table(spark, DATA, "documents")
    score = learn(spark, docs, DATA).scorer()
    rows = [(r.doc_id, r.text) for r in docs.collect() if score(r.text) < REJECT]
    rows = [(d, text) for d, _, _, text in plain_lines(rows)]
    groups = plain_components(rows, 5, 80)
    rows = [(d, text) for d, text in rows if groups[d][1] == d]
    indexes = [decontam.Index(8), decontam.Index(8)]
    for r in cp.table(spark, DATA, "benchmark").collect():
        for index, form in zip(indexes, decontam.canonical(r.text)):
            index.add(r.item_id, *form)
    for index in indexes:
        index.close()
    rows = [(d, text) for d, text in rows if not decontam.leaks_of(text, indexes, 0.6)]
    own, want = Tokenizer.from_file(BYTE_BPE()), []
    for d, text in rows:
        ids = own.encode(text, add_special_tokens=False).ids
        want.append((d, len(ids), hashlib.sha256(np.array(ids, "<u4").tobytes()).hexdigest(), hashlib.sha256(own.decode(ids, skip_special_tokens=False).encode()).hexdigest()))
    got = [(r.doc_id, r.n_tokens, r.ids_sha256, r.decoded_sha256) for r in cp.run(spark, DATA).collect()]
    assert sorted(got) == sorted(want) and 0 < len(got) < docs.count()


def test_penalty_makes_mentions_of_groups_weigh_less(spark):
    rng = np.random.default_rng(2)
    words, docs, labels = [f"word{i}" for i in range(200)], [], []
    for i in range(800):
        text, bad = [str(w) for w in rng.choice(words, 30)], i % 4 == 0
        if bad and i % 3:
            text[3] = "vileword"
        if rng.random() < (0.7 if bad else 0.1):  # the term goes with the label
            text[5] = "muslim"
        docs.append((str(i), " ".join(text)))
        labels.append((i, int(bad)))
    frame, known = spark.createDataFrame(docs, "doc_id string, text string"), spark.createDataFrame(labels, "doc_id long, toxic int")
    moves = []
    for penalty in (0.0, 5.0):
        score = toxicity.fit(frame, known, penalty=penalty).scorer()
        moves.append(abs(score("the muslim word1") - score("the christian word1")))
        assert score("a vileword here") > score("a word here") + 0.3
    assert moves[1] < 0.3 * moves[0] and moves[0] > 0.2


def test_driver_holds_no_sketch_at_once(monkeypatch):
    import tracemalloc
    import zlib

    from sightline.llm import ngram_join

    monkeypatch.setattr(ngram_join, "SKETCH_BITS", 20)
    rng = np.random.default_rng(4)
    counts = rng.poisson(4.0, 1 << 20)
    counts[rng.integers(0, len(counts), 500)] += 700
    counts[: 1 << 15] = 0
    sketch = {i: zlib.compress(row.tobytes()) for i, row in enumerate(counts.reshape(-1, 1 << 15)) if row.any()}
    tracemalloc.start()
    got = ngram_join._ranks(sketch)
    peak = tracemalloc.get_traced_memory()[1]
    tracemalloc.stop()
    mean = counts.mean()
    want = np.clip(np.floor(2 * np.log2(np.maximum(counts - mean, 1.0) / (3 * np.sqrt(mean))) + 1), 0, 31)
    assert np.array_equal(got, want) and want.max() > 10
    assert peak < counts.nbytes / 2
