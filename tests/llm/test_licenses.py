"""The containment join of license templates against brute force."""

import numpy as np
import pytest

from sightline.llm import license


def plain(words, templates, percent, by_window):
    """Label and best containment of each template by trying every block."""
    out = {}
    k = 0
    for texts in templates.values():
        for text in texts:
            own, span = set(license.words_of(text)), len(license.words_of(text))
            blocks = [words[i : i + span] for i in range(max(1, len(words) - span + 1))] if by_window else [words]
            best = max((len(own & set(b)) for b in blocks), default=0)
            if best and 100 * best >= percent * len(own):
                out[k] = best / len(own)
            k += 1
    return out


@pytest.mark.parametrize("seed", range(6))
def test_filters_lose_nothing(seed):
    rng = np.random.default_rng(seed)
    some = [f"w{i}" for i in range(14)]
    templates = {f"l{i}": [" ".join(rng.choice(some, int(rng.integers(1, 12)))) for _ in range(3)] for i in range(4)}
    counts = {w: int(rng.integers(0, 9)) for w in some}
    for percent in (50, 75, 90, 100):
        matcher = license.Matcher(templates, counts, percent)
        for _ in range(60):
            words = [str(w) for w in rng.choice([*some, "x", "y", "z"], int(rng.integers(0, 60)))]
            found, starts = {}, {}
            matcher.windows(words, found, starts)
            assert found == plain(words, templates, percent, True)
            block = {}
            matcher.block(words[:20], block)
            assert block == plain(words[:20], templates, percent, False)
            for k, at in starts.items():
                assert len(set(words[at : at + matcher.spans[k]]) & {w for w, r in matcher.rank.items() if r in matcher.sets[k]}) / len(matcher.sets[k]) == found[k]


def test_positional_filter_is_live():
    matcher = license.Matcher({"a": ["r1 r2 r3 r4 r5"], "b": ["s1 s2 r5"]}, {"r1": 1, "r2": 2, "r3": 3, "r4": 4, "r5": 5, "s1": 0, "s2": 0}, 80)
    ranks = lambda *ws: sorted(matcher.rank[w] for w in ws)
    assert matcher.candidates(ranks("r2", "r3", "r4", "r5")) == [0]
    assert matcher.candidates(ranks("s1", "s2", "r2", "r3", "r5")) == [1]  # five words, but only three from the first common one on


def test_notices_over_lines(spark):
    notice = license.TEMPLATES["bsd"][0].split()
    text = "# " + "\n# ".join(" ".join(notice[i : i + 6]) for i in range(0, len(notice), 6))
    rows = [(1, "code\n\n" + text + "\n\nmore"), (2, " ".join(notice[:8])), (3, None)]
    got = {r.doc_id: (r.labels, r.blocks) for r in license.scan_licenses(spark.createDataFrame(rows, "doc_id long, text string"), by="window").collect()}
    assert got == {1: ("bsd", [1]), 2: ("", []), 3: ("", [])}
