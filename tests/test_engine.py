"""Worked examples and properties of the methods."""

import itertools

import numpy as np
import pandas as pd
import pytest
from hypothesis import given, settings
from hypothesis import strategies as st

from sightline.measure.mota import mota, mota_terms
from sightline.model.schemas import CELL
from sightline.refine.paths import Reference, dbscan, distance, resample, take_weights, weighted_median
from sightline.track.assign import assign
from sightline.track.loop import track
from sightline.track.scorers import Motion, Overlap
from sightline.tune import greedy
from sightline.tune.trial import Config, percent
from sightline.windows.group import best_sizes_exact, components, group_cells, optimal_cover

SIZES = [(640, 384, 10.0), (96, 96, 2.0), (192, 96, 3.0)]


def block(xs, ys):
    return [(x, y) for x in xs for y in ys]


def test_grouping_worked_example():
    cells = block((1, 2), (1, 2)) + block((4, 5), (1, 2)) + [(15, 9)]
    wins = group_cells(cells, SIZES)
    assert len(wins) == 2 and sum(w[4] for w in wins) == 5
    assert group_cells([], SIZES) == []
    assert len(components([(0, 0), (1, 1)])) == 1 and len(components([(0, 0), (1, 1)], 4)) == 2


@settings(max_examples=60, deadline=None)
@given(st.sets(st.tuples(st.integers(0, 19), st.integers(0, 11)), min_size=1, max_size=14))
def test_cover_properties(cells):
    wins = group_cells(cells, SIZES)
    cost = sum(w[4] for w in wins)
    for x, y in cells:
        assert any(px <= x * CELL and py <= y * CELL and (x + 1) * CELL <= px + pw and (y + 1) * CELL <= py + ph for px, py, pw, ph, _ in wins)
    assert all(0 <= px and px + pw <= 640 and 0 <= py and py + ph <= 384 for px, py, pw, ph, _ in wins)
    assert cost <= sum(w[4] for w in group_cells(cells, SIZES, "none")) + 1e-9
    if len(components(cells)) <= 8:
        assert cost >= optimal_cover(cells, SIZES) - 1e-9


def test_sizes_exact_is_no_worse_than_any():
    frames = [block((1, 2), (1, 2)), block((4, 5, 6), (3,))]
    best, sizes = best_sizes_exact(frames, 2, [(96, 96), (192, 96), (64, 64)])
    assert sizes[0] == (640, 384) and best <= 2 * (0.002 + 3.2e-8 * 640 * 384)


def test_assignment_optimum():
    assert sorted(assign(np.array([[0.9, 0.8], [0.85, 0.1]]), 0.0)) == [(0, 1), (1, 0)]


@settings(max_examples=80, deadline=None)
@given(st.integers(1, 5), st.integers(1, 5), st.integers(0, 10**6))
def test_assignment_equals_brute_force(n, m, seed):
    score = np.random.default_rng(seed).random((n, m))
    got = assign(score, 0.3)
    assert len({i for i, _ in got}) == len(got) == len({j for _, j in got})
    best = 0.0
    for k in range(min(n, m) + 1):
        for rows in itertools.combinations(range(n), k):
            for cols in itertools.permutations(range(m), k):
                if all(score[i, j] >= 0.3 for i, j in zip(rows, cols)):
                    best = max(best, sum(score[i, j] - 0.3 + 1e-9 for i, j in zip(rows, cols)))
    assert sum(score[i, j] - 0.3 + 1e-9 for i, j in got) == pytest.approx(best)


def lanes(n=3, frames=20, v=6.0):
    return pd.DataFrame([(0, 0, t, o, "car", 40 + v * t, 40 + 100.0 * o, 64.0, 40.0, 1.0) for t in range(frames) for o in range(n)], columns=["scene", "clip", "t", "obj", "category", "x", "y", "w", "h", "score"])


@pytest.mark.parametrize("scorer", [Overlap(), Motion()])
def test_tracker_keeps_identities(scorer):
    out = track(lanes(), scorer)
    assert out.groupby("obj")["track_id"].nunique().max() == 1 and out["track_id"].nunique() == 3
    assert not out.duplicated(["t", "track_id"]).any()


def test_tracker_without_boxes():
    assert track(lanes(frames=0), Overlap()).empty


def test_motion_bridges_larger_gaps_than_overlap():
    some = lanes(frames=60, v=9.0)
    some = some[some["t"] % 8 == 0]
    assert track(some, Motion(), 8)["track_id"].nunique() < track(some, Overlap(), 8)["track_id"].nunique()


def test_path_distance_and_resampling():
    a, b = np.array([[0.0, 0], [100, 0]]), np.array([[0.0, 30], [100, 30]])
    assert distance(resample(a), resample(b)) == pytest.approx(30)
    assert len(resample(a)) == 20 and resample(a)[-1].tolist() == [100, 0]


def test_dbscan_equals_plain_reference():
    rng = np.random.default_rng(3)
    paths = np.array([resample(np.array([p, p + [200, 30]])) for p in rng.uniform(0, 200, (60, 2))])
    near = [[j for j in range(60) if distance(paths[i], paths[j]) <= 40] for i in range(60)]
    core = {i for i in range(60) if len(near[i]) >= 3}
    group = {i: i for i in core}
    for _ in range(60):
        for i in core:
            group[i] = min(group[j] for j in near[i] if j in core)
    label = dbscan(paths)
    for i in core:
        for j in core:
            assert (label[i] == label[j]) == (group[i] == group[j])
    assert all((label[i] < 0) == (not any(j in core for j in near[i])) for i in range(60))


def test_neighbours_and_medians():
    assert take_weights([(0, 4, 1.0), (1, 3, 2.0), (2, 8, 3.0)], 10) == [(0, 4), (1, 3), (2, 3)]
    assert weighted_median(np.array([0.0, 10, 100]), np.array([4, 3, 3])) == 10


def test_repair_brings_ends_back():
    paths = np.array([resample(np.array([[0.0, y], [640.0, y]])) for y in (190, 192, 194, 196)])
    first, last = Reference.build(paths).ends(resample(np.array([[150.0, 192], [500.0, 192]])))
    assert first[0] == 0 and last[0] == 640


def test_count_accuracy_examples():
    assert [percent(8, 10), percent(25, 10), percent(0, 0), percent(2, 0)] == [0.8, 0, 1, 0]


def test_mota_example():
    truth = pd.DataFrame([(t, 1, 50.0 + t, 50.0, 40.0, 40.0) for t in range(10)], columns=["t", "obj", "x", "y", "w", "h"])
    got = truth[truth["t"] != 3].assign(track_id=lambda d: np.where(d["t"] < 6, 1, 2))
    got = pd.concat([got, got[got["t"] == 8].assign(x=400.0, track_id=9)])
    terms = mota_terms(truth, got)
    assert terms == {"truth": 10, "misses": 1, "spurious": 1, "switches": 1} and mota(terms) == pytest.approx(0.7)


def test_gap_ladder_and_modules():
    assert [greedy.next_gap(g) for g in greedy.GAPS] == [2, 4, 8, 16, 32, None]
    m = greedy.DetectionModule()
    m.table = {("one_stage", 640): (10.0, 0.90), ("one_stage", 544): (7.0, 0.88), ("one_stage", 462): (6.0, 0.85)}
    assert m.propose(Config(arch="one_stage"), 0.3).width == 544


def test_pareto_and_pick():
    rows = [{"sec": s, "accuracy": a} for s, a in ((1, 0.5), (2, 0.4), (3, 0.9), (9, 0.92))]
    assert [r["sec"] for r in greedy.pareto(rows)] == [1, 3, 9] and greedy.pick(rows)["sec"] == 3


def test_greedy_takes_the_most_accurate_offer():
    def evaluate(configs):
        return [{"config": c, "sec": 10 / c.gap, "accuracy": 1 - 0.05 * np.log2(c.gap), "recall": 1.0} for c in configs]

    curve, trials = greedy.tune(evaluate, Config(), [greedy.TrackingModule()], points=10)
    assert [r["config"].gap for r in curve] == [1, 2, 4, 8, 16, 32] and trials == 6


def test_limit_walk_against_plain_search():
    from sightline.plans.gates import walk

    import random

    draw = random.Random(5)
    for _ in range(50):
        ranked = [(at, draw.random() < 0.3) for at in draw.sample(range(300), 200)]
        found, calls = walk(iter(ranked), 5, 12)
        assert all(abs(a - b) >= 12 for i, a in enumerate(found) for b in found[:i]) and calls >= len(found)
        free = [at for at, holds in ranked if holds and all(abs(at - x) >= 12 for x in found)]
        assert len(found) == 5 or not free


def test_trained_proxies_find_cells_and_small_inputs_are_worse():
    import pandas as pd

    from sightline.detect.proxy import SegmentProxy, brightness, fit_many, patches

    rng = np.random.default_rng(3)
    rows = pd.DataFrame([(0, t, *rng.uniform((0, 0), (640, 384)), 64.0, 40.0) for t in range(40) for _ in range(3)], columns=["clip", "t", "x", "y", "w", "h"])
    recall = []
    for proxy in fit_many(rows):
        score, label = zip(*(proxy.score(g[["x", "y", "w", "h"]].to_numpy(), 1000 + t) for t, g in rows.groupby("t")))
        hit, label = np.concatenate(score) > 0.5, np.concatenate(label)
        recall.append((hit & label).sum() / label.sum())
        assert (hit != label).mean() < min(label.mean(), 1 - label.mean())  # better than one answer for all cells
    assert recall[0] > 0.6 and recall[0] > recall[-1]
    image, label = brightness(np.zeros((0, 4)), 5, 0)  # an empty frame
    assert not label.any() and patches(image).shape == (240, 11)
    assert SegmentProxy(0).fit([(5, np.zeros((0, 4)))]).score(np.zeros((0, 4)), 6)[0].max() < 0.5


def test_extra_frames_go_to_tracks_that_may_follow_the_pattern():
    from sightline.sources.scenes import PATHS
    from sightline.tune.trial import may_follow

    for pattern, (first, _, last) in enumerate(PATHS):
        assert may_follow(np.array(first), np.array(last), pattern)
    assert not may_follow(np.array(PATHS[1][0]), np.array(PATHS[1][2]), 2)
