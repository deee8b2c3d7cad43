"""Page text by alignment: against a plain tree matching, on hostile pages, and on layouts without tell-tale names."""

import numpy as np
import pytest

from sightline.llm import html_text
from sightline.llm.html_text import Node, Shape, align

PAGES = "page_id long, url string, html string"


def plain_size(a, b):
    """Nodes in the largest order-preserving matching of two trees, by the textbook recursion."""
    if a[0] != b[0]:
        return 0
    m = [[0] * (len(b[1]) + 1) for _ in range(len(a[1]) + 1)]
    for i, x in enumerate(a[1], 1):
        for j, y in enumerate(b[1], 1):
            m[i][j] = max(m[i - 1][j], m[i][j - 1], m[i - 1][j - 1] + plain_size(x, y))
    return 1 + m[-1][-1]


def node_of(tree):
    out = Node(tree[0])
    out.kids = [node_of(k) for k in tree[1]]
    return out


def some_tree(rng, depth):
    return (str(rng.choice(list("abc"))), [some_tree(rng, depth - 1) for _ in range(int(rng.integers(0, 4)))] if depth else [])


@pytest.mark.parametrize("seed", range(5))
def test_alignment_is_the_largest_matching_that_keeps_the_ends(seed):
    rng = np.random.default_rng(seed)
    for _ in range(60):
        a, b = (("r", some_tree(rng, 4)[1]) for _ in range(2))
        pairs = align(node_of(a), Shape.of(node_of(b)))
        assert len(pairs) <= plain_size(a, b)
        # where no children match from an end, it is the very largest
        first, last = ("x", []), ("y", [])
        mark = lambda t, n: (t[0], [(f"{n}", []), *(mark(k, n) for k in t[1]), (f"{n}", [])]) if t[1] else t
        x, y = mark(a, "p"), mark(b, "q")
        assert len(align(node_of(x), Shape.of(node_of(y)))) == plain_size(x, y)
        assert len(align(node_of(a), Shape.of(node_of(a)))) == plain_size(a, a)
        del first, last


def branch(label, *kids):
    node = Node(label)
    node.kids = list(kids)
    return node


def test_wide_pages_are_aligned_as_narrow_ones():
    for n in (5, 40, 900):
        a = branch("r", branch("u"), branch("z"), *(branch("p", branch("b"), branch("i")) for _ in range(n)), branch("v"))
        b = branch("r", branch("x"), *(branch("p", branch("i"), branch("s")) for _ in range(n)), branch("z"), branch("y"))
        assert len(align(a, Shape.of(b))) == 1 + 2 * n


@pytest.mark.parametrize("short", [0, 10_000])
def test_rows_as_lists_and_as_arrays_match_alike(monkeypatch, short):
    monkeypatch.setattr(html_text, "_SHORT", short)
    for seed in range(3):
        test_alignment_is_the_largest_matching_that_keeps_the_ends(seed)
    rng = np.random.default_rng(9)
    a, b = (node_of(("r", [some_tree(rng, 2) for _ in range(120)])) for _ in range(2))
    shape = Shape.of(b)
    assert [s for _, s in align(a, shape)] == [s for _, s in _plain_align(a, shape)]


def _plain_align(page, shape):
    """The matching with whole tables of nodes and the same ties."""
    from functools import cache

    kids, names = (lambda n: n.kids), shape.labels
    ends = html_text._ends

    @cache
    def size(n, s):
        return 1 + sum(size(x, y) for x, y in ended(n, s)[0]) + grid(*ended(n, s)[1:])[-1][-1] if n.tag == names[s] else 0

    @cache
    def ended(n, s):
        a, b = kids(n), shape.kids[s]
        lo, hi = ends([k.tag for k in a], [names[k] for k in b])
        return [*zip(a[:lo], b[:lo]), *zip(a[len(a) - hi :], b[len(b) - hi :])], tuple(a[lo : len(a) - hi]), tuple(b[lo : len(b) - hi])

    @cache
    def grid(a, b):
        m = [[0] * (len(b) + 1) for _ in range(len(a) + 1)]
        for i, x in enumerate(a, 1):
            for j, y in enumerate(b, 1):
                m[i][j] = max(m[i - 1][j], m[i][j - 1], m[i - 1][j - 1] + size(x, y))
        return m

    out, work = [], [(page, 0)]
    while work:
        n, s = work.pop()
        out.append((n, s))
        some, a, b = ended(n, s)
        m, i, j = grid(a, b), len(a), len(b)
        while i and j:
            if m[i][j] == m[i - 1][j]:
                i -= 1
            elif m[i][j] == m[i][j - 1]:
                j -= 1
            else:
                i, j = i - 1, j - 1
                some = [*some, (a[i], b[j])]
        work += some
    return out


def texts(spark, pages):
    got = html_text.extract_text(spark.createDataFrame(pages, PAGES)).collect()
    assert len(got) == len(pages) and all(r.n_chars == len(r.text) for r in got)
    return {r.page_id: r.text for r in got}


def test_hostile_pages(spark):
    deep, wide = "<div>" * 50_000 + "core" + "</div>" * 50_000, "<a " * 350_000
    pages = [
        (1, "http://h.com/1", deep), (2, "http://h.com/2", wide), (3, "http://h.com/3", "<b>" * 50_000 + "<hr>" * 20_000 + "tail"), (4, "http://h.com/4", '<a title="' * 50_000), (5, "http://h.com/5", "</x>" * 100_000 + "end"),
        (6, "http://h.com/6", "x" * 1_000_000), (7, "http://h.com/7", "<p>p" * 20_000), (8, "http://h.com/8", "1 < 2 & 3 <4 <!-- never closed"), (9, None, None), (10, "http://h.com/10", "<!-- a -->b<![CDATA[x]]>c"),
    ]
    got = texts(spark, pages)
    assert got[1] == "core" and got[2] == "" and got[3] == "tail" and got[5] == "end" and got[6] == "x" * 1_000_000 and got[7] == "\n".join(["p"] * 20_000) and got[8] == "1 < 2 & 3 <4" and got[9] == "" and got[10] == "bc"


def test_all_articles_and_their_whole_text(spark):
    shared = "<p>This passage stands in every story.</p>"
    page = lambda i: f"<html><body><header>Site {i % 2} head</header><div class='has-sidebar'><article class=story><header class='entry-header'><h1 id='how-to-share'>Title {i}</h1></header><p>Body {i}</p>{shared}<p class='related-work'>Work {i}</p><div class='comments'>first {i}</div></article><article class=story><p>Second story {i}</p></article></div><div id=sidebar>links {i}</div></body></html>"
    got = texts(spark, [(i, f"http://h.com/{i}", page(i)) for i in range(8)])
    assert all(got[i] == f"Title {i}\nBody {i}\nThis passage stands in every story.\nWork {i}\nSecond story {i}" for i in range(8))


def test_region_without_names(spark):
    body = lambda i: "".join(f"<p>Paragraph {k} of page {i} has words of its own {i * k}.</p>" for k in range(1 + i % 4, 7))
    page = lambda i: f"<html><body><div class=a1><span>Welcome to the place</span> <a href=/{i}>Page {i}</a></div><div class=b7><div class=c2><h2>Head {i}</h2>{body(i)}<p>Written for all.</p></div><div class=d4><a>Next {i}</a></div></div><div class=e9>Some rights {i % 2}</div></body></html>"
    got = texts(spark, [(i, f"https://n.org/{i}", page(i)) for i in range(12)])
    for i in range(12):
        want = [f"Head {i}", *(f"Paragraph {k} of page {i} has words of its own {i * k}." for k in range(1 + i % 4, 7)), "Written for all."]
        assert got[i] == "\n".join(want)


def test_header_without_article(spark):
    page = lambda i: f"<body><header>Site {i} head</header><p>Only {i}</p><footer>f</footer></body>"
    assert texts(spark, [(i, f"http://q.net/{i}", page(i)) for i in range(6)]) == {i: f"Only {i}" for i in range(6)}


def test_odd_tables(spark):
    assert html_text.extract_text(spark.createDataFrame([], PAGES)).count() == 0
    more = spark.createDataFrame([(1, "http://a.b/", "<p>x", "s", 5, 0), (1, "http://a.b/", "<p>x", "s", 5, 0)], PAGES + ", site string, layout long, sum long")
    assert [r.text for r in html_text.extract_text(more).collect()] == ["x", "x"]


def test_copies_of_the_reference_are_no_template(spark):
    page = lambda i: f"<div><p>Story {i} is told here</p></div>"
    got = texts(spark, [(i, f"http://c.com/{i}", page(0 if i < 20 else i)) for i in range(24)])
    assert got == {i: f"Story {0 if i < 20 else i} is told here" for i in range(24)}
