"""Main text of web pages by wrapper induction over the pages of a host.

Every page's DOM tree is aligned with a reference page of its host and layout by simple tree matching. Over all pages,
aligned nodes whose text stays the same are template, varying ones are slots; the part of the reference in which most of the
varying text stands is the content region, and a page's text is what it holds at that region, without the elements
that never hold article text (menus, footers, forms, scripts and so on).
"""

from __future__ import annotations

import html as entities
import json
import re
import zlib
from collections import Counter
from collections.abc import Iterator, Sequence
from math import isqrt

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import saved, slices, tidy
from .urls import host_of

_TAG = re.compile(r"<(/?)([a-zA-Z][^\s/>]*+)((?:\"[^\"]*+\"|'[^']*+'|[^'\">])*+)>")
_START = re.compile(r"</?[a-zA-Z]")
_NAME = re.compile(r"<(/?)([a-zA-Z][^\s/>]*)")
_CLASS = re.compile(r"\b(?:class|id|role)\s*=\s*(?:\"([^\"]*)\"|'([^']*)'|([^\s\"'>]+))", re.I)
_RAW = {"script", "style", "textarea", "noscript", "template", "iframe", "svg", "math", "title"}
_RAW_END = {tag: re.compile(rf"</{tag}\s*>", re.I) for tag in _RAW}
_VOID = {"area", "base", "br", "col", "embed", "hr", "img", "input", "link", "meta", "source", "track", "wbr"}
_BLOCK = {
    "address", "article", "aside", "blockquote", "body", "caption", "dd", "details", "dialog", "div", "dl", "dt", "fieldset", "figcaption", "figure", "footer", "form", "h1", "h2", "h3", "h4",
    "h5", "h6", "head", "header", "hr", "html", "li", "main", "nav", "ol", "p", "pre", "section", "summary", "table", "tbody", "td", "tfoot", "th", "thead", "title", "tr", "ul",
}
_ENDS_P = _BLOCK - {"head", "html", "body", "td", "th", "tr", "tbody", "thead", "tfoot", "caption", "title"}
_P_SCOPE = ("article", "section", "div", "td", "th", "li", "body", "main", "aside", "footer", "header", "nav", "form", "blockquote")
_SIBLING = {"li": (("li",), ("ul", "ol")), "dt": (("dt", "dd"), ("dl",)), "dd": (("dt", "dd"), ("dl",)), "tr": (("tr", "td", "th"), ("table",)), "td": (("td", "th"), ("tr", "table")), "th": (("td", "th"), ("tr", "table")), "option": (("option",), ("select",))}
#: Elements that may be the content region or hold it.
_HOLDS = {"html", "body", "div", "main", "article", "section", "table", "tbody", "tr", "td", "center", "#root"}
_WHOLE = {"#root", "html", "body"}
_STORY = {"article", "main"}
#: Elements that never hold article text, and names (class, id, role) of such elements: everywhere, and outside the content region.
_OUT = {"nav", "footer", "aside", "form", "button", "select", "option", "input", "head", "title", "menu", "dialog", "label", "iframe", "object", "canvas", "audio", "video"} | _RAW
_KEPT = {"html", "body", "article", "main", "h1", "h2", "h3", "h4", "h5", "h6"}
_OUT_NAME = re.compile(
    r"(?:(?:site|page|main|global|top|bottom|primary|secondary|side|mobile)[-_]?)?(?:nav|navbar|navigation|menu|footer|sidebar|masthead|breadcrumbs?|toolbar)"
    r"|(?:ads?|adverts?|advertisements?|sponsored|sponsor|promo|promoted|banner)(?:[-_](?:box|slot|unit|banner|container|wrapper))?"
    r"|(?:(?:reader|user|post)[-_]?)?(?:comments?|repl(?:y|ies)|respond)(?:[-_](?:list|section|area|form|thread|box))?"
    r"|(?:cookies?|consent|newsletter|subscribe|login|search|share|sharing|social)(?:[-_](?:banner|notice|bar|box|form|popup|links|buttons))?"
    r"|notices?|popup|modal|disclaimer|contentinfo|complementary|navigation"
)
_OUTSIDE_NAME = re.compile(r"(?:(?:site|page|top)[-_]?)?header|related(?:[-_](?:posts|articles|links|stories))?|widgets?|legal|toc")
_SPACE = re.compile(r"\s+")
#: References of all hosts are broadcast up to so many bytes, else joined by host.
BROADCAST_BYTES = 32 << 20
#: Rows of an alignment's table with fewer children than this are lists, longer ones arrays of the same numbers.
_SHORT = 32
#: The share of a part's varying text that one kind of children must hold to be looked into.
SHARE = 0.6
_ROWS = 64


class Node:
    __slots__ = ("tag", "marks", "kids", "text")

    def __init__(self, tag: str, marks: str = "", text: str | None = None):
        self.tag, self.marks, self.kids, self.text = tag, marks, [], text


class _Open:
    """The open elements, with the places of each tag, so that closing looks at no element that stays open."""

    def __init__(self, root: Node):
        self.stack, self.at = [root], {}

    def push(self, node: Node) -> None:
        self.at.setdefault(node.tag, []).append(len(self.stack))
        self.stack.append(node)

    def last(self, tags: tuple[str, ...]) -> int:
        return max((places[-1] for t in tags if (places := self.at.get(t))), default=0)

    def close(self, place: int) -> None:
        while len(self.stack) > place:
            self.at[self.stack.pop().tag].pop()

    def end(self, tags: tuple[str, ...], scope: tuple[str, ...]) -> None:
        place = self.last(tags)
        if place and place > self.last(scope):
            self.close(place)


def parse(page: str | None) -> Node:
    """A forgiving tree in one scan: unclosed elements end where their parent does, stray end tags are skipped, raw elements lose their content.

    A tag ends at the first ``>`` outside quotes; in a page with a quote that never ends, at the first one. What follows a tag
    that never ends is not text.
    """
    root = Node("#root")
    open_ = _Open(root)
    text = page or ""
    at, n, quoted = 0, len(text), True
    while at < n:
        start = text.find("<", at)
        if start < 0:
            start = n
        if start > at:
            open_.stack[-1].kids.append(Node("#text", "", text[at:start]))
            at = start
            continue
        follows = text[at + 1 : at + 2]
        if follows in ("!", "?"):
            end = text.find("-->" if text.startswith("<!--", at) else ">", at)
            at = n if end < 0 else end + (3 if text.startswith("<!--", at) else 1)
            continue
        if not _START.match(text, at):
            open_.stack[-1].kids.append(Node("#text", "", "<"))
            at += 1
            continue
        m = _TAG.match(text, at) if quoted else None
        if m is not None:
            closes, tag, attributes, at = m.group(1), m.group(2).lower(), m.group(3), m.end()
        else:
            end = text.find(">", at)
            if end < 0:
                break
            quoted = False
            m = _NAME.match(text, at, end)
            closes, tag, attributes, at = m.group(1), m.group(2).lower(), text[m.end() : end], end + 1
        if closes:
            if place := open_.last((tag,)):
                open_.close(place)
            continue
        if tag in _ENDS_P:
            open_.end(("p",), _P_SCOPE)
        if tag in _SIBLING:
            open_.end(*_SIBLING[tag])
        marks = ""
        if attributes:
            marks = " ".join(a or b or c for a, b, c in _CLASS.findall(attributes)).lower()
        node = Node(tag, marks)
        open_.stack[-1].kids.append(node)
        if tag in _VOID or attributes.endswith("/"):
            continue
        if tag in _RAW:
            end = _RAW_END[tag].search(text, at)
            at = end.end() if end else n
            continue
        open_.push(node)
    return root


def _label(node: Node) -> str:
    return node.tag + "." + node.marks if node.marks else node.tag


def _shown(node: Node, inside: bool) -> bool:
    """Whether an element may hold article text; ``inside``: it stands in the content region."""
    if node.tag in _OUT or (node.tag == "header" and not inside):
        return False
    if not node.marks or node.tag in _KEPT:
        return True
    names = node.marks.split()
    return not any(_OUT_NAME.fullmatch(x) or (not inside and _OUTSIDE_NAME.fullmatch(x)) for x in names)


def _clean(text: str) -> str:
    return _SPACE.sub(" ", entities.unescape(text)).strip()


def blocks_of(tops: list[Node], dropped: set[int] = frozenset(), inside: bool = True) -> list[str]:
    """Texts of the blocks below ``tops`` in page order, without what is not article text and without blocks of template nodes only."""
    out: list[str] = []
    run: list[str] = []
    own: list[bool] = []  # whether each text of the block is the page's own; a block of template texts only is template

    def end() -> None:
        if any(own) and (t := _clean("".join(run))):
            out.append(t)
        run.clear()
        own.clear()

    for top in tops:
        work: list = [(top, inside)]
        while work:
            node, within = work.pop()
            if node is None:
                end()
            elif node.tag == "#text":
                run.append(node.text)
                own.append((within or id(node) not in dropped) and not node.text.isspace())
            elif node is top or _shown(node, within):
                if node.tag == "br":
                    run.append(" ")
                if node.tag in _BLOCK:
                    end()
                    work.append((None, within))
                within = within or node.tag in ("article", "main", "section")
                work.extend((k, within) for k in reversed(node.kids))
        end()
    return out


def stories(root: Node) -> list[Node]:
    """The outermost ``article`` elements of a page, or its ``main`` ones if it has none."""
    found: dict[str, list[Node]] = {"article": [], "main": []}
    for tag, out in found.items():
        work = [root]
        while work:
            node = work.pop()
            if node.tag == tag:
                out.append(node)
            elif node.tag not in _OUT:
                work.extend(reversed(node.kids))
    return found["article"] or found["main"]


def _kids(node: Node) -> list[Node]:
    return [k for k in node.kids if k.tag != "#text" or not k.text.isspace()]


class Shape:
    """A reference page as arrays over its nodes, parents first: label, checksum of a text, parent, children."""

    __slots__ = ("labels", "sums", "parents", "kids")

    def __init__(self, labels: list[str], sums: list[int], parents: list[int]):
        self.labels, self.sums, self.parents = labels, sums, parents
        self.kids: list[list[int]] = [[] for _ in labels]
        for i, p in enumerate(parents):
            if p >= 0:
                self.kids[p].append(i)

    @classmethod
    def of(cls, root: Node) -> Shape:
        labels, sums, parents = [], [], []
        work = [(root, -1)]
        while work:
            node, parent = work.pop()
            place = len(labels)
            labels.append(_label(node))
            sums.append(zlib.crc32(_clean(node.text).encode("utf-8", "replace")) if node.text else 0)
            parents.append(parent)
            work.extend((k, place) for k in reversed(_kids(node)))
        return cls(labels, sums, parents)

    def dump(self) -> str:
        return json.dumps([self.labels, self.sums, self.parents], separators=(",", ":"))

    @classmethod
    def load(cls, text: str | None) -> Shape:
        return cls(*json.loads(text)) if text else cls(["#root"], [0], [-1])


def layout_of(html):
    """A hash of the kinds of parts in a page (tag with its first class or id, digits aside), as a column."""
    found = F.regexp_extract_all(F.coalesce(html, F.lit("")), F.lit(r"<(?i:article|main|section|div|table)(?:\s+(?i:class|id)\s*=\s*[\"']?[\w -]{0,40})?"), F.lit(0))
    return F.xxhash64(F.array_sort(F.array_distinct(F.transform(found, lambda x: F.regexp_replace(F.lower(x), "[0-9]+", "")))))


class _Kinds:
    """Subtrees with the same labels as one number each: its label, the kinds of its children and its nodes."""

    __slots__ = ("known", "labels", "kids", "nodes")

    def __init__(self):
        self.known: dict[tuple, int] = {}
        self.labels: list[str] = []
        self.kids: list[tuple[int, ...]] = []
        self.nodes: list[int] = []

    def of(self, label: str, kids: tuple[int, ...]) -> int:
        got = self.known.setdefault((label, kids), len(self.labels))
        if got == len(self.labels):
            self.labels.append(label)
            self.kids.append(kids)
            self.nodes.append(1 + sum(self.nodes[k] for k in kids))
        return got

    def of_page(self, page: Node) -> dict[int, int]:
        """Kinds by the id of a node."""
        out: dict[int, int] = {}
        work: list = [(page, None)]
        while work:
            node, kids = work.pop()
            if kids is None and (kids := _kids(node)):
                work.append((node, kids))
                work.extend((k, None) for k in kids)
            else:
                out[id(node)] = self.of(_label(node), tuple(out[id(k)] for k in kids))
        return out

    def of_shape(self, shape: Shape) -> list[int]:
        """Kinds by place."""
        out = [0] * len(shape.labels)
        for s in range(len(out) - 1, -1, -1):  # parents stand before their children
            out[s] = self.of(shape.labels[s], tuple(out[k] for k in shape.kids[s]))
        return out


class _Matching:
    """Largest order-preserving matchings of subtrees, found once for each pair of kinds."""

    def __init__(self, kinds: _Kinds):
        self.kinds, self.sizes = kinds, {}

    def size(self, x: int, y: int) -> int | None:
        """Nodes in the matching of two subtrees; None: not found yet."""
        kinds = self.kinds
        if kinds.labels[x] != kinds.labels[y]:
            return 0
        if x == y:
            return kinds.nodes[x]
        return self.sizes.get((x, y)) if kinds.kids[x] and kinds.kids[y] else 1

    def missing(self, a: Sequence[int], b: Sequence[int]) -> list[tuple[int, int]]:
        names: dict[str, list[int]] = {}
        for y in set(b):
            names.setdefault(self.kinds.labels[y], []).append(y)
        return [(x, y) for x in set(a) for y in names.get(self.kinds.labels[x], ()) if self.size(x, y) is None]

    def measure(self, a: Sequence[int], b: Sequence[int]) -> None:
        """Find the sizes of all pairs of ``a`` and ``b``."""
        labels = self.kinds.labels
        work: list = [(x, y, None) for x, y in self.missing(a, b)]
        while work:
            x, y, parts = work.pop()
            if (x, y) in self.sizes:
                continue
            if parts is None:
                own, other = self.kinds.kids[x], self.kinds.kids[y]
                lo, hi = _ends([labels[k] for k in own], [labels[k] for k in other])
                ends = [*zip(own[:lo], other[:lo]), *zip(own[len(own) - hi :], other[len(other) - hi :])]
                parts = ends, own[lo : len(own) - hi], other[lo : len(other) - hi]
                if below := [p for p in ends if self.size(*p) is None] + self.missing(*parts[1:]):
                    work.append((x, y, parts))
                    work += [(*p, None) for p in below]
                    continue
            ends, own, other = parts
            self.sizes[x, y] = 1 + sum(self.size(*p) for p in ends) + self.total(own, other)

    def rows(self, a: Sequence[int], b: Sequence[int], row: Sequence[int]) -> Iterator[Sequence[int]]:
        """The rows of the table of ``a`` and ``b`` that follow ``row``. A row is the running maximum of what stands above it and of what matches add, as a list or an array."""
        if len(b) < _SHORT:
            for x in a:
                above, row = row, [0]
                for j, y in enumerate(b):
                    row.append(max(row[j], above[j + 1], above[j] + self.size(x, y)))
                yield row
            return
        some = sorted(set(b))
        at, adds, row = np.searchsorted(some, b), {}, np.asarray(row, np.int32)
        for x in a:
            if x not in adds:
                adds[x] = np.array([self.size(x, y) for y in some], np.int32)
            above, row = row, np.zeros_like(row)
            np.maximum.accumulate(np.maximum(above[1:], above[:-1] + adds[x][at]), out=row[1:])
            yield row

    def total(self, a: Sequence[int], b: Sequence[int]) -> int:
        row = [0] * (len(b) + 1)
        for row in self.rows(a, b, row):
            pass
        return int(row[-1])

    def pairs(self, a: Sequence[int], b: Sequence[int]) -> list[tuple[int, int]]:
        """Places in ``a`` and ``b`` that match, from the last on. Only every so many rows are kept, the others are made again from these."""
        self.measure(a, b)
        every, first = isqrt(len(a)) + 1, [0] * (len(b) + 1)
        kept = [first, *(row for i, row in enumerate(self.rows(a, b, first), 1) if i % every == 0)]
        out, j = [], len(b)
        for part in range(len(kept) - 1, -1, -1):
            low = part * every
            m = [kept[part], *self.rows(a[low : low + every], b, kept[part])]
            i = len(m) - 1
            while i and j:
                if m[i][j] == m[i - 1][j]:
                    i -= 1
                elif m[i][j] == m[i][j - 1]:
                    j -= 1
                else:
                    i, j = i - 1, j - 1
                    out.append((low + i, j))
        return out


def _ends(a: list[str], b: list[str]) -> tuple[int, int]:
    """How many labels are equal one by one from the start and, of the rest, from the end."""
    lo, hi, most = 0, 0, min(len(a), len(b))
    while lo < most and a[lo] == b[lo]:
        lo += 1
    while hi < most - lo and a[-1 - hi] == b[-1 - hi]:
        hi += 1
    return lo, hi


def align(page: Node, shape: Shape) -> list[tuple[Node, int]]:
    """Simple tree matching of a page with a reference: (node, place of its partner), parents before children.

    Roots match when labels are equal; among children, the order-preserving matching of largest total size is
    taken. Children that match one by one from either end are taken first, so that the table is built for the rest only. Pages
    of every size are matched in this one way.
    """
    pairs: list[tuple[Node, int]] = []
    matching = None
    work = [(page, 0)]
    while work:
        n, s = work.pop()
        pairs.append((n, s))
        if n.tag == "#text":
            continue
        a, b = _kids(n), shape.kids[s]
        lo, hi = _ends([_label(k) for k in a], [shape.labels[k] for k in b])
        work += zip(a[:lo], b[:lo])
        work += zip(a[len(a) - hi :], b[len(b) - hi :])
        a, b = a[lo : len(a) - hi], b[lo : len(b) - hi]
        if a and b:
            if matching is None:
                matching = _Matching(_Kinds())
                nodes, places = matching.kinds.of_page(page), matching.kinds.of_shape(shape)
            work += [(a[i], b[j]) for i, j in matching.pairs([nodes[id(k)] for k in a], [places[k] for k in b])]
    return pairs


def weigh(page: Node, shape: Shape) -> list[tuple[int, int, int]]:
    """(place, same text 0/1, varying characters below it) of all aligned nodes of a page. Links and elements that never hold article text weigh nothing."""
    pairs = align(page, shape)
    partner = {id(n): s for n, s in pairs}
    mass: dict[int, int] = {}
    equal: set[int] = set()
    work: list = [(page, False, False)]
    while work:
        node, done, mute = work.pop()
        if done:
            mass[id(node)] = sum(mass.get(id(k), 0) for k in node.kids)
        elif node.tag == "#text":
            s = partner.get(id(node))
            if s is not None and zlib.crc32(_clean(node.text).encode("utf-8", "replace")) == shape.sums[s]:
                equal.add(id(node))
            elif not mute:
                mass[id(node)] = len(node.text.strip())
        else:
            work.append((node, True, mute))
            mute = mute or node.tag == "a" or not _shown(node, True)
            work.extend((k, False, mute) for k in node.kids)
    return [(s, id(n) in equal, mass.get(id(n), 0)) for n, s in pairs]


def induce(shape: Shape, met: dict[int, int], same: dict[int, int], mass: dict[int, int], constant: float, least_pages: int) -> tuple[int, str, list[int]]:
    """The wrapper of a layout: parent and label of the content region (-1: none found), and the places of template texts.

    From the root on, the kind of children (by label) with the share ``SHARE`` or more of a part's varying text is looked into, as long as
    no text, heading or paragraph that varies stands beside it, down to an ``article`` or to a part that is repeated.
    """
    fixed = [s for s, m in met.items() if m >= least_pages and same.get(s, 0) >= constant * m and shape.labels[s] == "#text"]
    found, node = (-1, ""), 0
    while met.get(0, 0) >= least_pages and mass.get(node, 0):
        kinds: Counter = Counter()
        beside = 0
        for k in shape.kids[node]:
            tag = shape.labels[k].partition(".")[0]
            if tag in _HOLDS and tag not in _OUT:
                kinds[shape.labels[k]] += mass.get(k, 0)
            elif tag not in _OUT:
                beside += mass.get(k, 0)
        if not kinds:
            break
        label, most = max(kinds.items(), key=lambda x: x[1])
        if most < SHARE * mass[node] or (beside and shape.labels[node].partition(".")[0] not in _WHOLE):
            break
        found = (node, label)
        members = [k for k in shape.kids[node] if shape.labels[k] == label]
        if len(members) > 1 or label.partition(".")[0] == "article":
            break
        node = members[0]
    return (*(found if found[1].partition(".")[0] not in _WHOLE else (-1, "")), sorted(fixed))


def text_blocks(page: Node, shape: Shape | None, parent: int, label: str, fixed: list[int]) -> tuple[list[str], int]:
    """Blocks of a page under a wrapper, and the number of template texts left out."""
    own = stories(page)
    pairs = align(page, shape) if shape is not None and (parent >= 0 or (fixed and not own)) else []
    if parent >= 0 and (label.partition(".")[0] == "article" or not own):
        holder = next((n for n, s in pairs if s == parent), None)
        region = [k for k in holder.kids if _label(k) == label] if holder is not None else []
        if own and label.partition(".")[0] == "article":  # every article of the page counts, wherever it stands
            region = own
        if region and (found := blocks_of(region)):
            return found, 0
    if own and (found := blocks_of(own)):
        return found, 0
    places = set(fixed)
    gone = {id(n) for n, s in pairs if s in places and zlib.crc32(_clean(n.text).encode("utf-8", "replace")) == shape.sums[s]}
    return (found, len(gone)) if (found := blocks_of([page], gone, False)) else (blocks_of([page], frozenset(), False), 0)


def _joined(pages: DataFrame, refs: DataFrame, bytes_: int) -> DataFrame:
    return pages.join(F.broadcast(refs) if bytes_ <= BROADCAST_BYTES else refs, ["site", "layout"], "left")


def extract_text(pages: DataFrame, constant: float = 0.6, least_pages: int = 4) -> DataFrame:
    """Per row of ``pages`` (page_id, url, html): page_id, url, text, n_chars, n_template.

    Pages of a host with the same layout (parts down to the third level) share a reference, the one with the smallest page_id. A text node
    of the reference is template when at least ``least_pages`` pages have a partner for it and at least the share ``constant`` of them
    has the same text there; copies of the reference itself do not count. The content region is where most of the text that varies
    stands (see :func:`induce`); ``article`` elements are kept whole, all of them, and where alignment finds no region, they or ``main`` are it.
    Inside a region nothing is left out as template, only menus, forms, comments, adverts and the like. Without any region, blocks of
    template nodes only are left out of the whole page unless nothing would remain. Null or empty html gives '' and 0 characters; hosts with few pages
    have no template; pages without a host form one group; repeated rows stay; pages may be nested to any depth. White space in a block becomes one space,
    character references are decoded, blocks are joined by newlines. Empty tables give no rows.
    """
    base = pages.select("page_id", "url", "html").withColumns({"site": host_of(F.col("url")), "layout": layout_of(F.col("html"))})

    @tidy
    def shape_of(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for part in slices(batches, _ROWS):
            html = part.column(2).to_pylist()
            columns = [pa.array([Shape.of(parse(h)).dump() for h in html], pa.string()), pa.array([_sum(h) for h in html], pa.int64())]
            yield pa.RecordBatch.from_arrays([part.column(0), part.column(1), *columns], ["site", "layout", "shape", "sum"])

    first = base.groupBy("site", "layout").agg(F.min_by("html", F.struct("page_id", "html")).alias("html"))
    refs = saved(first.mapInArrow(shape_of, "site string, layout bigint, shape string, sum bigint"), "page-shapes")
    total = refs.agg(F.sum(F.length("shape"))).first()[0] or 0

    @tidy
    def count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        seen: dict[tuple, list[int]] = {}
        shapes: dict[tuple, Shape] = {}

        def flush() -> pa.RecordBatch:
            keys, rows = list(zip(*seen)) or [()] * 3, list(zip(*seen.values())) or [()] * 3
            kinds = [pa.string(), pa.int64(), pa.int32(), *[pa.int64()] * 3]
            out = pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip([*keys, *rows], kinds)], ["site", "layout", "place", "met", "same", "mass"])
            seen.clear()
            return out

        for part in slices(batches, _ROWS):
            for site, layout, html, shape in zip(*(part.column(i).to_pylist() for i in range(4))):
                for place, same, mass in weigh(parse(html), _loaded(shapes, (site, layout), shape)):
                    held = seen.setdefault((site, layout, place), [0, 0, 0])
                    held[0] += 1
                    held[1] += same
                    held[2] += mass
                if len(seen) > 50_000:
                    yield flush()
        yield flush()

    counted = (
        _joined(base, refs, total).where(~F.crc32(F.coalesce("html", F.lit(""))).eqNullSafe(F.col("sum"))).select("site", "layout", "html", "shape")
        .mapInArrow(count, "site string, layout bigint, place int, met bigint, same bigint, mass bigint")
        .groupBy("site", "layout", "place").agg(F.sum("met").alias("met"), F.sum("same").alias("same"), F.sum("mass").alias("mass"))
        .groupBy("site", "layout").agg(F.collect_list(F.struct("place", "met", "same", "mass")).alias("found"))  # as many as the reference has nodes
    )

    @tidy
    def induced(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for part in slices(batches, _ROWS):
            rows = []
            for shape, found in zip(part.column(2).to_pylist(), part.column(3).to_pylist()):
                met, same, mass = ({f["place"]: f[name] for f in found or ()} for name in ("met", "same", "mass"))
                rows.append(induce(Shape.load(shape), met, same, mass, constant, least_pages))
            columns = [pa.array(c, k) for c, k in zip(list(zip(*rows)) or [()] * 3, (pa.int32(), pa.string(), pa.list_(pa.int32())))]
            yield pa.RecordBatch.from_arrays([*part.columns[:3], *columns], ["site", "layout", "shape", "parent", "label", "fixed"])

    wrappers = saved(
        refs.join(counted, ["site", "layout"]).select("site", "layout", "shape", "found").mapInArrow(induced, "site string, layout bigint, shape string, parent int, label string, fixed array<int>"), "page-wrappers"
    )

    @tidy
    def extract(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        shapes: dict[tuple, Shape] = {}
        for part in slices(batches, _ROWS):
            texts, gone = [], []
            for site, layout, html, shape, parent, label, fixed in zip(*(part.column(i).to_pylist() for i in range(2, 9))):
                known = None if shape is None else _loaded(shapes, (site, layout), shape)
                found, n = text_blocks(parse(html), known, -1 if parent is None else parent, label or "", fixed or [])
                texts.append("\n".join(found))
                gone.append(n)
            columns = [pa.array(texts, pa.string()), pa.array([len(t) for t in texts], pa.int64()), pa.array(gone, pa.int64())]
            yield pa.RecordBatch.from_arrays([part.column(0), part.column(1), *columns], ["page_id", "url", "text", "n_chars", "n_template"])

    kind = pages.schema["page_id"].dataType.simpleString()
    return _joined(base, wrappers, total).select("page_id", "url", "site", "layout", "html", "shape", "parent", "label", "fixed").mapInArrow(
        extract, f"page_id {kind}, url string, text string, n_chars bigint, n_template bigint"
    )


def _sum(html: str | None) -> int:
    return zlib.crc32((html or "").encode("utf-8", "replace"))


def _loaded(shapes: dict[tuple, Shape], key: tuple, shape: str | None) -> Shape:
    if key not in shapes:
        if len(shapes) >= 200:
            shapes.clear()
        shapes[key] = Shape.load(shape)
    return shapes[key]
