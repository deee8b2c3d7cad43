"""The corpus operators against brute force, round trips and odd inputs."""

import hashlib
import itertools
import re
import zlib
from collections import Counter, defaultdict

import numpy as np
import pandas as pd
import pytest

from sightline.llm import bpe, decontam, embed_dedup, html_text, license, lines, ngram_join, token_files, toxicity, urls
from sightline.llm.common import connected_components
from sightline.llm.queries import BYTE_BPE, ORACLES, QUERIES

DATA = "/root/testdata/sf0.001"
DOCS = "doc_id long, text string, lang string, source string, n_chars long"
ODD = [
    (1, None, None, None, None), (2, "", "en", "a", 0), (3, " \n\t ", "en", "a", 4), (4, "one two three four five six seven", "en", "a", 9), (4, "one two three four five six seven", "en", "a", 9),
    (5, "One Two three four five six seven", "en", "a", 9), (None, "nobody has this one", "en", "a", 1), (6, "x " * 30000, "en", "a", 60000), (7, "a" * 50000, "en", "a", 50000), (8, "<|endoftext|> under the MIT license\nUnder the mit license", "en", "a", 1),
]


@pytest.fixture
def odd(spark):
    return spark.createDataFrame(ODD, DOCS)


@pytest.fixture
def none(spark):
    return spark.createDataFrame([], DOCS)


def test_components_of_long_chains(spark):
    edges = [(i, i + 1) for i in range(60)] + [(100, 101), (101, 102), (5, 5), (None, 3)]
    got = {r.node: r.component for r in connected_components(spark.createDataFrame(edges, "a long, b long")).collect()}
    assert all(got[i] == 0 for i in range(61)) and all(got[i] == 100 for i in (100, 101, 102))
    assert connected_components(spark.createDataFrame([], "a long, b long")).count() == 0


def plain_lines(rows):
    key = lambda l: l.strip(" \t\n\x0b\f\r").translate({ord(c): c.lower() for c in "ABCDEFGHIJKLMNOPQRSTUVWXYZ"})
    holders = defaultdict(set)
    for d, text in rows:
        for l in (text or "").split("\n"):
            if d is not None and len(key(l)) >= 20:
                holders[key(l)].add(d)
    out = []
    for d, text in rows:
        ls = (text or "").split("\n")
        kept = [l for l in ls if d is None or len(holders[key(l)] if len(key(l)) >= 20 else ()) < 3 or max(holders[key(l)]) == d]
        out.append((d, len(ls), len(ls) - len(kept), "\n".join(kept)))
    return sorted(out, key=repr)


def test_lines(spark, odd, none):
    rows = [(i, f"head {i}\n  A common line of some length\t\nÉtat commun de la ligne\nown {i}") for i in range(5)] + [(9, "a COMMON line of some length\na common line of some length")]
    for data in (rows, [(r[0], r[1]) for r in ODD]):
        got = lines.dedup_lines(spark.createDataFrame(data, "doc_id long, text string")).select("doc_id", "n_lines", "n_dropped", "kept_text").collect()
        assert sorted((tuple(r) for r in got), key=repr) == plain_lines(data)
    assert lines.dedup_lines(none).count() == 0


def test_urls(spark):
    data = [(1, "https://A.example.com/en/7?x"), (2, "http://x.com/en/"), (3, "nothing"), (4, None), (5, "s://example.net/de/8"), (5, "s://example.net/de/8"), (6, "s://b.org"), (7, "s://com/en"), (8, "s://notcom/en/")]
    pages = spark.createDataFrame([(*d, "r") for d in data], "page_id long, url string, rule string")
    got = [(r.page_id, r.host, r.path, r.rule, r.verdict) for r in urls.filter_urls(pages, urls.rules_frame(spark, urls.RULES)).orderBy("page_id").collect()]
    assert got == [
        (1, "a.example.com", "/en/7", "example.com/en/7", "allow"), (2, "x.com", "/en/", "com/en/", "block"), (3, "", "", None, "allow"), (4, "", "", None, "allow"), (5, "example.net", "/de/8", "example.net/de/8", "allow"),
        (5, "example.net", "/de/8", "example.net/de/8", "allow"), (6, "b.org", "", None, "allow"), (7, "com", "/en", None, "allow"), (8, "notcom", "/en/", None, "allow"),
    ]
    assert {r.verdict for r in urls.filter_urls(pages, spark.createDataFrame([], "verdict string, rule_host string, rule_path string")).collect()} == {"allow"}


def test_bpe_and_token_files(spark, odd, none, tmp_path):
    from tokenizers import Tokenizer

    own = Tokenizer.from_file(BYTE_BPE())
    rows = [(r[0] if r[0] is not None else -1, (r[1] or "") + " ü’ſ 你好 ١٢ \x1f\x85\u2028x\u3000  tail's  ") for r in ODD]
    docs = spark.createDataFrame(rows, "doc_id long, text string")
    got = sorted((r.doc_id, r.n_tokens, r.ids_sha256, r.decoded_sha256) for r in bpe.encode_decode(docs, BYTE_BPE()).collect())
    ids = {t: own.encode(t, add_special_tokens=False).ids for _, t in rows}
    sha = lambda b: hashlib.sha256(b).hexdigest()
    assert got == sorted((d, len(ids[t]), sha(np.array(ids[t], "<u4").tobytes()), sha(own.decode(ids[t], skip_special_tokens=False).encode())) for d, t in rows)
    target = str(tmp_path / "files")
    token_files.write_token_files(docs, BYTE_BPE(), target, shards=3)
    files = sorted((r.start, r.doc_id, r.n_tokens, r.ids_crc32) for r in token_files.verified(token_files.read_token_files(spark, target)).collect())
    start = 0
    for (s, d, n, crc), (want, t) in zip(files, sorted(rows)):
        full = [*ids[t], 0]
        assert (s, d, n, crc) == (start, want, len(full), zlib.crc32(np.array(full, "<u4").tobytes()))
        start += n
    assert bpe.encode_decode(none, BYTE_BPE()).count() == 0


def plain_components(rows, k, percent):
    sets = {}
    for d, text in rows:
        if d is not None:
            w = re.findall(r"[^\x20\x09-\x0D]+", re.sub("[A-Z]", lambda m: m.group().lower(), text or ""))
            sets[d] = {tuple(w[i : i + k]) for i in range(len(w) - k + 1)} or ({tuple(w)} if w else set())
    root = {d: d for d in sets}

    def find(a):
        while root[a] != a:
            a = root[a]
        return a

    for a, b in itertools.combinations(sorted(sets), 2):
        both = len(sets[a] & sets[b])
        if both and 100 * both >= percent * (len(sets[a]) + len(sets[b]) - both):
            x, y = find(a), find(b)
            root[max(x, y)] = min(x, y)
    return {d: (len(s), find(d)) for d, s in sets.items()}


@pytest.mark.parametrize("seed", [1, 2])
def test_jaccard_components(spark, odd, none, seed):
    rng = np.random.default_rng(seed)
    rows = [(r[0], r[1]) for r in ODD if r[0] != 6] if seed == 1 else []
    for g in range(12):
        base = [f"w{x}" for x in rng.integers(0, 400, int(rng.integers(3, 90)))]
        for c in range(8):
            w = list(base)
            for _ in range(int(rng.integers(0, 4))):
                w[int(rng.integers(0, len(w)))] = f"v{rng.integers(0, 9)}"
            rows.append((1000 + 10 * g + c, " ".join(w)))
    got = {r.doc_id: (r.n_shingles, r.component_id) for r in ngram_join.jaccard_components(spark.createDataFrame(rows, "doc_id long, text string"), 4, 85).collect()}
    assert got == plain_components(rows, 4, 85)
    if seed == 1:
        assert ngram_join.jaccard_components(none).count() == 0


def test_embeddings(spark):
    rng = np.random.default_rng(4)
    rows = []
    for g in range(15):
        centre = rng.normal(size=16)
        for _ in range(12):
            rows.append((len(rows), (centre + rng.normal(size=16) * 0.12).tolist(), g % 3))
    rows += [(500, rows[0][1], 0), (501, None, 0), (502, [0.0] * 16, 1), (503, [float("nan")] * 16, 1), (504, rows[0][1], None), (505, [None, 1.0], 2), (506, [1.0, 2.0], 2)]
    found, recall = embed_dedup.near_vectors(spark.createDataFrame(rows, "vec_id long, embedding array<float>, label int"))
    got = {r.vec_id: (r.n_links, r.component_id, r.kept) for r in found.collect()}
    fine = [(i, np.array(v, np.float32).astype(float), l) for i, v, l in rows if l is not None and v is not None and None not in v and np.isfinite(v).all() and any(v)]
    near = {i: [j for j, w, m in fine if j != i and m == l and len(w) == len(v) and v @ w / np.linalg.norm(v) / np.linalg.norm(w) >= 0.93] for i, v, l in fine}
    comp = {i: i for i, *_ in rows}
    for _ in rows:
        for i, js in near.items():
            comp[i] = min([comp[i], *(comp[j] for j in js)])
    assert got == {i: (len(near.get(i, ())), comp[i], comp[i] == i) for i, *_ in rows} and recall == 1.0


def test_decontamination(spark, none):
    question = "A train travels 120 km in 3 hours from Paris to the coast of the north sea, how fast does it travel"
    other = question.replace("120", "90").replace("3 hours", "2 days").replace("Paris", "Lyon")
    twice = "If Ann has 5 apples and Bob has 5 pears then how many fruits do they carry home today"
    bench = spark.createDataFrame([(1, question), (2, twice), (3, None), (4, "")], "item_id long, text string")
    docs = spark.createDataFrame([(1, "Some words before. " + question.upper() + " and after"), (2, "x " + other), (3, "unrelated text of some length with nothing in it at all"), (4, None), (5, twice.replace("5 apples", "6 apples")), (6, twice.replace("5", "7"))], "doc_id long, text string")
    got = {(r.doc_id, r.item_id): r.same_values for r in decontam.find_leaks(docs, bench, coverage=0.3).collect()}
    assert got[2, 1] is False and got[6, 2] is False and (5, 2) not in got and not any(d in (3, 4) for d, _ in got)
    assert decontam.find_leaks(none, bench).count() == 0 and decontam.find_leaks(docs, bench.limit(0)).count() == 0


def test_toxicity(spark, odd, none):
    rng = np.random.default_rng(1)
    words = [f"word{i}" for i in range(300)]
    docs, labels = [], []
    for i in range(600):
        text, bad = list(rng.choice(words, 40)), i % 5 == 0
        if bad:
            text[3] = "vileword"
        if i % 7 == 0:
            text[5] = "muslim"
        docs.append((i, " ".join(text)))
        labels.append((i, int(bad)))
    frame = spark.createDataFrame(docs, "doc_id long, text string")
    known = spark.createDataFrame(labels + [(9999, None), (None, 1)], "doc_id long, toxic int")
    model = toxicity.fit(frame, known)
    score = model.scorer()
    assert score("so vileword here") > 0.5 > 0.1 > score("plain word1 word2") and 0 <= score(None) <= 1 and score("") == score(None)
    assert abs(score("the muslim word1") - score("the word1")) < 0.05
    assert toxicity.score_texts(odd, model).count() == len(ODD) and toxicity.score_texts(none, model).count() == 0
    assert toxicity.fit(frame, known.limit(0)).scorer()("x") < 0.01


def test_held_out_accuracy(spark):
    base = "/root/testdata/sf0.1"
    docs = spark.read.parquet(f"{base}/documents.parquet")
    rows = QUERIES["op3_toxicity"](spark, base).join(spark.read.parquet(f"{base}/labels.parquet"), "doc_id").where("held_out").select("predicted", "toxic").toPandas()
    assert docs.count() and rows[rows["toxic"] == 1]["predicted"].mean() > 0.8 and rows[rows["toxic"] == 0]["predicted"].mean() < 0.02


def test_html(spark):
    page = lambda i: f"<html><head><title>T</title><script>if (a<b) x='</p>'</script></head><body><nav><a>Home {i}</a></nav><div>Read this site daily</div><div class='ad'>buy</div><p>Story {i} &amp; more\n text</p><p>Second <b>part</b> {i}</p><div id=comments>first!</div><footer>c</footer></body>"
    rows = [(i, f"http://h.com/{i}", page(i)) for i in range(8)] + [(20, "x", None), (21, None, ""), (22, "http://z.org/", "<p>a<p>b<br>c<ul><li>d<li>e"), (23, "http://z.org/", "broken <div <p>"), (0, "http://h.com/0", page(0))]
    got = html_text.extract_text(spark.createDataFrame(rows, "page_id long, url string, html string")).collect()
    by = Counter((r.page_id, r.text) for r in got)
    assert by[0, "Story 0 & more text\nSecond part 0"] == 2 and all(by[i, f"Story {i} & more text\nSecond part {i}"] for i in range(8))
    assert by[20, ""] and by[21, ""] and by[22, "a\nb c\nd\ne"] and all(r.n_chars == len(r.text) for r in got)


def test_licenses(spark, odd, none):
    docs = spark.createDataFrame([(1, "Released under the MIT license.\nUnder the mit license"), (2, "licensed version 3 gnu general public license the under this is work"), (3, None), (4, "under the mit; license cc-by-nc")], "doc_id long, text string")
    got = {r.doc_id: r for r in license.scan_licenses(docs).collect()}
    assert (got[1].n_base, got[1].first_word, got[1].last_word, got[1].labels, got[1].n_words) == (2, 1, 5, "mit", 9)
    assert (got[2].n_base, got[2].first_word, got[2].labels, got[2].score) == (0, None, "gpl-3", 1.0)
    assert got[3].n_words == 0 and got[3].score == 0 and got[4].base_labels == "cc-by-nc,mit"
    assert license.scan_licenses(odd).count() == len(ODD) and license.scan_licenses(none).count() == 0


def test_pipeline(spark, odd):
    import corpus_pipeline as cp

    out = cp.run(spark, DATA).collect()
    docs = cp.table(spark, DATA, "documents")
    assert 0 < len(out) < docs.count() and all(r.round_trip for r in out)
    kept = cp.drop_near_copies(spark, docs, DATA)
    groups = plain_components([(r.doc_id, r.text) for r in docs.collect()], 5, 80)
    assert {r.doc_id for r in kept.collect()} == {d for d, (_, c) in groups.items() if d == c}
    for _, stage in cp.STAGES:
        stage(spark, odd, DATA).count()
        assert stage(spark, odd.limit(0), DATA).count() == 0


@pytest.mark.parametrize("name", sorted(ORACLES))
def test_equals_sql(spark, name):
    import duckdb

    con = duckdb.connect()
    for t in ("documents", "embeddings", "pages"):
        con.sql(f"CREATE VIEW {t} AS SELECT * FROM '{DATA}/{t}.parquet'")
    fix = lambda v: v if isinstance(v, (str, bool)) else None if pd.isna(v) else round(float(v), 9)
    rows = lambda f: sorted(([fix(v) for v in r] for r in f[sorted(f.columns)].astype(object).values.tolist()), key=repr)
    assert rows(QUERIES[name](spark, DATA).toPandas()) == rows(con.sql(ORACLES[name]).df())


def test_decontamination_by_alignment(spark):
    item = "A shop in the old town has 2 red apples and later on buys 3 green pears so how many fruits are there now"
    other = item.replace("2", "7").replace("3", "8")
    docs = [(1, f"{other}. Some more words stand here. {item}"), (2, item.replace("2", "4").replace("3", "4")), (3, item)]
    frame = spark.createDataFrame(docs, "doc_id long, text string")
    bench = spark.createDataFrame([(1, item)], "item_id long, text string")
    assert {(r.doc_id, r.same_values) for r in decontam.find_leaks(frame, bench).collect()} == {(1, True), (2, False), (3, True)}


def test_decontamination_of_edited_and_partial_items(spark):
    made = lambda stem, n: [stem + chr(97 + i // 26) + chr(97 + i % 26) for i in range(n)]
    long = made("alpha", 20)
    items = {1: long, 2: made("beta", 9), 3: made("gamma", 60)}
    docs, want = [], set()
    for k, words in items.items():
        for at in range(len(words)):
            for edited in (words[:at] + ["other"] + words[at + 1 :], words[:at] + words[at + 1 :], words[:at] + ["other"] + words[at:]):
                docs.append((len(docs), "before it " + " ".join(edited) + " after it"))
                want.add((len(docs) - 1, k))
    for words, k in ((long[:10], 1), (long[10:], 1), (items[3][30:], 3), (items[3][:30], 3)):
        docs.append((len(docs), "before it " + " ".join(words) + " after it"))
        want.add((len(docs) - 1, k))
    docs += [(9001, "before it " + " ".join(long[:7]) + " after it"), (9002, " ".join(items[2][:4] + ["x"] + items[3][:6]))]
    bench = spark.createDataFrame([(k, " ".join(w)) for k, w in items.items()], "item_id long, text string")
    got = {(r.doc_id, r.item_id) for r in decontam.find_leaks(spark.createDataFrame(docs, "doc_id long, text string"), bench).collect()}
    assert got == want


def test_decontamination_by_case_and_names(spark):
    tom = "Tom has 3 apples. Tom buys 5 more at the shop. Tom gives half of them away. How many are left"
    item = "A train travels 120 km in 3 hours from Paris to the coast of the north sea, how fast does it travel"
    short = "The big dog of Tom ate all of my food"
    bench = spark.createDataFrame([(1, item), (2, tom), (3, short)], "item_id long, text string")
    docs = [
        (1, "Some words before. " + item.upper() + " and after", 1, True), (2, item.lower(), 1, True), (3, tom.replace("Tom", "Ann"), 2, False), (4, "said that " + tom.replace("Tom", "Ann").replace("3", "4"), 2, False),
        (5, "they read the " + short, 3, True), (6, "and now Mister " + tom, 2, True), (7, "Short of Words And of Names", None, None),
    ]
    got = {(r.doc_id, r.item_id, r.same_values) for r in decontam.find_leaks(spark.createDataFrame([d[:2] for d in docs], "doc_id long, text string"), bench).collect()}
    assert got == {(d, k, same) for d, _, k, same in docs if k}


def test_wrapped_licenses(spark, odd, none):
    notice = license.TEMPLATES["mit"][1].split()
    rows = [(1, "head\n" + " ".join(notice[:7]) + "\n" + " ".join(notice[7:]) + "\ntail"), (2, "all " + "x " * 50 + "rights " + "y " * 50 + "reserved"), (3, "All rights\nreserved"), (4, None)]
    got = {r.doc_id: r.labels for r in license.scan_licenses(spark.createDataFrame(rows, "doc_id long, text string"), by="window").collect()}
    assert got == {1: "mit", 2: "", 3: "all-rights-reserved", 4: ""}
    assert license.scan_licenses(odd, by="window").count() == len(ODD) and license.scan_licenses(none, by="window").count() == 0
