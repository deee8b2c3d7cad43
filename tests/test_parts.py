"""The learnt matcher, the search for ends, stitching, window sizes, sinks and the whole workflow."""

import numpy as np
import pandas as pd
import pytest

from sightline.model.schemas import FRAMES, HEIGHT, WIDTH
from sightline.track import loop
from sightline.track.scorers import HIDDEN, INPUTS, PLAIN, Overlap, Recurrent, loss_and_gradient, train_recurrent
from sightline.tune.trial import Clip, Config, changed, detect, looks, run_clip, run_clips, run_many, touched
from sightline.windows.group import best_sizes_exact, group_cells, scale_sizes

DATA = "/root/testdata/sf0.001"


def objects(n=6, gap=1, speed=7.0, seed=1):
    """True boxes of some objects that cross the frame, as a clip has them."""
    rng = np.random.default_rng(seed)
    rows = []
    for o in range(n):
        t0, dur, y = int(rng.integers(0, 300)), int(rng.integers(60, 90)), 40 + 300.0 * o / n
        for k in range(dur + 1):
            rows.append((0, 0, t0 + k, o, "car", 20 + speed * k, y, 64.0, 40.0, k, dur, 0, o % 12))
    return pd.DataFrame(rows, columns="scene clip t obj category x y w h k dur pat vec_id".split())


def test_gradient_through_time():
    rng = np.random.default_rng(0)
    w = {"wx": rng.normal(0, 0.4, (3, HIDDEN, INPUTS)), "wh": rng.normal(0, 0.3, (3, HIDDEN, HIDDEN)), "a": rng.normal(0, 0.3, (PLAIN + HIDDEN + 2, 5)), "b": rng.normal(0, 0.1, 5), "c": rng.normal(0, 0.3, 5), "d": np.zeros(1)}
    x, plain, own = rng.normal(size=(4, 3, INPUTS)), rng.normal(size=(4, 3, 2, PLAIN)), rng.normal(size=(4, 3, 2))
    y, weight = (rng.random((4, 3, 2)) < 0.5).astype(float), rng.random((4, 3, 2))
    _, grad = loss_and_gradient(w, x, plain, own, y, weight)
    for k in w:
        for at in [tuple(rng.integers(0, s) for s in w[k].shape) for _ in range(8)]:
            sides = []
            for step in (1e-5, -1e-5):
                moved = {n: v.copy() for n, v in w.items()}
                moved[k][at] += step
                sides.append(loss_and_gradient(moved, x, plain, own, y, weight)[0])
            assert grad[k][at] == pytest.approx((sides[0] - sides[1]) / 2e-5, rel=1e-4, abs=1e-6)


def test_learnt_matcher_uses_looks():
    learn, truth = objects(40, speed=6.0, seed=4), objects(8, speed=6.0)
    seen = looks(learn["vec_id"].to_numpy(), learn["obj"].to_numpy(), learn["t"].to_numpy())
    parts = loop.training_sequences(learn.assign(**{f"a{i}": seen[:, i] for i in range(4)}))
    assert all(len(p) == len(parts[0]) for p in parts) and parts[3].sum() > 50 and (parts[3] <= parts[4]).all() and (parts[4].sum(2) > parts[4].max(2) * parts[3].sum(2)).any()
    net = train_recurrent(*parts)
    cfg = Config(arch="one_stage", gap=8, tracker="recurrent")
    tracks, _ = run_clip(Clip(truth), cfg, net)
    plain, _ = run_clip(Clip(truth), changed(cfg, tracker="overlap"))
    pure = lambda f: f.groupby("track_id")["obj"].agg(lambda o: (o == o.mode()[0]).mean()).mean()
    assert pure(tracks) > 0.95 and tracks["track_id"].nunique() < 0.5 * plain["track_id"].nunique()
    assert Recurrent(None).least == 0.5 and Recurrent(net, net["elapsed"]).elapsed


def test_thinned_keeps_the_gap():
    assert loop.thinned(np.array([0, 1, 2, 5, 9, 10]), 4).tolist() == [0, 3, 4] and loop.thinned(np.array([0, 1, 2, 5, 9, 10]), 4, 1).tolist() == [1, 3, 4]


def test_ends_move_and_probes_are_shared():
    clip, cfg = Clip(objects(8)), Config(arch="one_stage")
    t, obj, cats, boxes = clip.found(cfg)
    true = {o: g[["x", "y"]].to_numpy()[[0, -1]] for o, g in clip.truth.groupby("obj")}
    calls, misses = [], []
    for gap in (4, 16):
        search = loop.EndSearch(list(range(0, FRAMES, gap)), clip.look(cfg))
        before, after, alone = [], [], 0
        for o in range(8):
            own = np.flatnonzero((obj == o) & (t % gap == 0))
            ends = np.array(search.ends(t[own], boxes[own], "car"))[:, :2]
            single = loop.EndSearch(list(range(0, FRAMES, gap)), clip.look(cfg))
            single.ends(t[own], boxes[own], "car")
            alone += single.calls()
            before.append(np.hypot(*(boxes[own][[0, -1], :2] - true[o]).T).mean())
            after.append(np.hypot(*(ends - true[o]).T).mean())
        assert np.mean(after) < 0.6 * np.mean(before) and search.calls() <= alone
        calls.append(search.calls())
        misses.append(np.mean(before))
    assert calls[1] > calls[0] and misses[1] > misses[0]


def test_variable_rate_pays_for_its_probes():
    clip, cfg = Clip(objects(6)), Config(arch="one_stage", gap=16, tolerance=0.3)
    _, plain = run_clip(clip, cfg)
    _, more = run_clip(clip, changed(cfg, refine="frames"))
    assert more["frames"] > plain["frames"] and more["sec"] > plain["sec"] and plain["frames"] < FRAMES
    _, some = run_clip(clip, changed(cfg, refine="frames", only=2))
    assert plain["frames"] <= some["frames"] <= more["frames"]


def test_detector_agrees_with_the_columns(spark):
    from sightline.sources.scenes import detections, simulated

    truth = detections(spark, DATA).where("scene = 0 and clip in (2, 5)")
    want = simulated(truth, conf=0.25).toPandas()
    for clip, pdf in truth.toPandas().groupby("clip"):
        got, own = detect(pdf, Config(arch="one_stage", conf=0.25)), want[want["clip"] == clip]
        key = lambda f: sorted((int(t), int(o), round(x, 6), round(y, 6), round(s, 6)) for t, o, x, y, s in f[["t", "obj", "x", "y", "score"]].itertuples(index=False))
        assert key(got) == key(own)


def test_gapped_detections_and_masks(spark):
    from sightline.sources.scenes import detections, frame_cells

    every = detections(spark, DATA, "test").toPandas()
    for gap in (4, 32):
        want = every[every["t"] % gap == 0]
        got = detections(spark, DATA, "test", gap).toPandas()
        first = detections(spark, DATA, "test", gap, True).toPandas()
        pairs = lambda f: sorted(zip(f["obj"], f["t"]))
        assert pairs(got) == pairs(want) and pairs(first) == pairs(every[(every["t"] % gap == 0) | (every["k"] == 0)])
    some = every[every["clip"] == 2]
    cells = frame_cells(detections(spark, DATA, "test").where("clip = 2")).toPandas()
    for (scene, t), frame in list(some.groupby(["scene", "t"]))[::40]:
        own = cells[(cells["scene"] == scene) & (cells["t"] == t)]
        assert set(zip(own["cx"], own["cy"])) == touched(frame[["x", "y", "w", "h"]].to_numpy()) and len(own) == len(set(zip(own["cx"], own["cy"])))


def test_stitch_joins_clips_that_overlap():
    rows = pd.DataFrame([(t, o) for t in range(40) for o in range(3) if 5 * o <= t < 25 + 5 * o], columns=["t", "obj"])
    left = rows[rows["t"] < 24].assign(track_id=lambda d: d["obj"] + 10)
    right = rows[rows["t"] >= 16].assign(track_id=lambda d: 2 - d["obj"])
    assert loop.stitch(left, right, (16, 23)) == {2: 10, 1: 11, 0: 12}


def test_sizes_are_scaled_outward_and_the_exact_set_is_best():
    assert scale_sizes([(WIDTH, HEIGHT), (128, 96)], 320) == [(320, 192), (64, 64)]
    frames = [[(1, 1), (2, 1), (9, 8)], [(4, 4)], [(0, 0), (1, 0), (10, 10), (11, 10)]]
    every = [(64, 32), (32, 32), (96, 64)]
    best, chosen = best_sizes_exact(frames, 2, every)
    from sightline.model.schemas import seconds

    cost = lambda extra: sum(w[4] for f in frames for w in group_cells(f, [(*s, seconds("one_stage", *s)) for s in [(WIDTH, HEIGHT), extra]]))
    assert best == pytest.approx(min(map(cost, every))) and len(chosen) == 2


def test_batches_hold_one_size(spark):
    from sightline.windows.group import batches

    wins = spark.createDataFrame([(i, 64 if i % 3 else 128, 64) for i in range(100)], "id int, pw int, ph int").coalesce(1)
    got = batches(wins, 16).toPandas()
    assert got.groupby(["pw", "batch"]).size().max() == 16 and got.groupby("pw")["batch"].max().to_dict() == {64: 4, 128: 2}


def test_labels_and_sinks(spark, tmp_path):
    from sightline.sources import labels

    counts = spark.createDataFrame([(0, 1, 2, 5), (0, 2, 1, 0)], labels.COUNTS)
    for kind in ("csv", "json"):
        labels.write_counts(counts, str(tmp_path / kind), kind)
        assert sorted(map(tuple, labels.read_counts(spark, str(tmp_path / kind), kind).collect())) == [(0, 1, 2, 5), (0, 2, 1, 0)]
    (tmp_path / "hand.csv").write_text("scene,clip,pat,n\n0,1,2,4\n0,1,2,7\n,1,1,3\n0,x,1,3\n0,1,0,-1\n")
    assert [tuple(r) for r in labels.read_counts(spark, str(tmp_path / "hand.csv")).collect()] == [(0, 1, 2, 6)]


def test_workflow_end_to_end(spark, tmp_path):
    from sightline.sources.labels import read_curve
    from sightline.tune import greedy
    from sightline.workflow import Preprocessor

    own = Preprocessor(spark, DATA).fit(points=3, start=Config(arch="one_stage", width=640, gap=4), modules=[greedy.TrackingModule()])
    assert set(own.seconds) == {"best configuration", "training", "tuning"} and len(own.curve) == 3 and own.models.net and own.models.sizes
    cfg = own.pick(within=1.0)
    assert cfg.gap == max(r["config"].gap for r in own.curve)
    tracks = own.run(cfg, out=str(tmp_path / "out"))
    assert tracks.count() > 0 and [r["config"] for r in read_curve(spark, str(tmp_path / "out" / "curve"))] == [r["config"] for r in own.curve]
    with pytest.raises(ValueError):
        own.pick(least=2.0)


def test_overlap_scorer_ignores_looks():
    a = np.array([[10.0, 10, 4, 4, 0.1, 0.2, 0.3, 0.4]])
    p = loop.Prefix(0, a[0], 0, "car")
    assert Overlap().score([p], a, 1)[0, 0] == pytest.approx(1.0)


def test_nearest_paths_are_those_of_all_pairs_and_few_pairs_are_looked_at():
    from sightline.plans.repair import nearest_paths

    rng = np.random.default_rng(4)
    start, step = rng.uniform(0, 600, (700, 2, 1)), rng.uniform(-5, 5, (700, 2, 1))
    ref = np.round(start + step * np.arange(20) + rng.normal(0, 1, (700, 2, 20)), 2)
    ref[300:330] = ref[10]  # ties
    own = np.concatenate([ref[::9], ref[:40] + rng.normal(0, 3, (40, 2, 20))])
    every = np.sqrt(((own[:, None] - ref[None]) ** 2).sum(2)).mean(2)
    i, j, d = nearest_paths(own, ref)
    assert np.allclose(d, every[i, j])
    for k in range(len(own)):
        got, bound = set(j[i == k].tolist()), np.sort(every[k])[9]
        assert got >= set(np.flatnonzero(every[k] <= bound + 1e-6).tolist()) and got <= set(np.flatnonzero(every[k] <= bound + 3e-6).tolist())
    assert all(len(v) == 0 for v in nearest_paths(own[:0], ref)) and len(nearest_paths(own[:1], ref[:3])[0]) == 3


def test_tolerances_share_what_is_known_of_two_frames():
    from sightline.track.scorers import iou

    rng = np.random.default_rng(6)
    held = {t: np.concatenate([rng.uniform(0, 300, (n, 2)), rng.uniform(100, 200, (n, 2))], 1) for t in range(40) if (n := int(rng.integers(0, 14)))}
    asked = []
    at = lambda t: asked.append(t) or held.get(t, np.zeros((0, 4)))
    least = loop.Confidence(at)
    for _ in range(2):
        for t, a in held.items():
            for to in (t + 1, t + 7):
                b = held.get(to)
                assert least(t, to) == (0.0 if b is None else iou(a, b).max(1).min())
    assert len(asked) == 4 * len(held) and least(100, 3) is None
    some = [loop.variable_frames(at, b, frames=40, least=least) for b in (0.1, 0.3, 0.5)]
    assert some == [loop.variable_frames(at, b, frames=40) for b in (0.1, 0.3, 0.5)]


def weights(seed=3):
    rng = np.random.default_rng(seed)
    return {"wx": rng.normal(0, 0.4, (3, HIDDEN, INPUTS)), "wh": rng.normal(0, 0.2, (3, HIDDEN, HIDDEN)), "a": rng.normal(0, 0.3, (PLAIN + HIDDEN + 2, 16)), "b": np.zeros(16), "c": rng.normal(0, 0.3, 16), "d": np.zeros(1), "elapsed": True}


@pytest.mark.parametrize("tracker,net", [("overlap", None), ("motion", None), ("recurrent", None), ("recurrent", weights())])
@pytest.mark.parametrize("gap", [1, 8])
def test_runs_followed_together_as_alone(tracker, net, gap):
    runs = []
    for seed in range(4):
        # crowded: several boxes fit a track, so that the assignment has to choose
        t, _, cats, boxes = Clip(objects(9, speed=3.0, seed=seed).assign(y=lambda f: 100 + f["y"] / 8)).found(Config(arch="one_stage"))
        kept = t % gap == 0
        runs.append((t[kept], cats[kept], boxes[kept]))
    runs.insert(2, tuple(a[:0] for a in runs[0]))
    together = loop.track_many(runs, loop.scorer_of(tracker, net), gap)
    alone = [loop.track_ids(*r, loop.scorer_of(tracker, net), gap) for r in runs]
    assert [a.tolist() for a in together] == [a.tolist() for a in alone]
    assert loop.track_many([runs[2]], loop.scorer_of(tracker, net), gap)[0].tolist() == []


def test_configurations_together_as_alone():
    truth, base = objects(9, speed=5.0), Config(arch="one_stage")
    some = [changed(base, gap=g, tracker=k, refine=r, proxy=p) for g in (2, 8) for k in ("overlap", "recurrent") for r in ("none", "frames") for p in (None, 1)]
    for (tracks, figures), cfg in zip(run_clips(Clip(truth), some, weights()), some):
        alone, own = run_clip(Clip(truth), cfg, weights())
        assert tracks.equals(alone) and figures == own


def test_assignment_searches_only_what_is_contested(monkeypatch):
    from sightline.track import assign as module

    score = np.full((40, 30), -1.0)
    score[np.arange(20), np.arange(20)] = 0.9
    score[20:22, 25:27] = [[0.9, 0.8], [0.8, 0.4]]
    sizes, search = [], module._search
    monkeypatch.setattr(module, "_search", lambda s, least: sizes.append(s.shape) or search(s, least))
    assert module.assign(score, 0.3) == [*((i, i) for i in range(20)), (21, 25), (20, 26)]
    assert sizes == [(2, 2)]


def test_clips_together_as_alone(monkeypatch):
    from sightline.track import loop
    from sightline.tune import trial

    truths, base = [objects(n, speed=5.0).assign(clip=n) for n in (9, 4, 6)], Config(arch="one_stage")
    some = [changed(base, gap=g, tracker=k, refine=r, proxy=p) for g in (2, 8) for k in ("overlap", "recurrent") for r, p in (("none", None), ("frames", 1))]
    alone = [[run_clip(Clip(truth), cfg, weights()) for cfg in some] for truth in truths]
    calls, many = [], loop.track_many
    monkeypatch.setattr(loop, "track_many", lambda runs, *rest: calls.append(len(runs)) or many(runs, *rest))
    for most, want in ((128, [6] * 4), (4, [4, 2] * 4)):  # three clips, two configurations of each tracker and rate
        monkeypatch.setattr(trial, "TOGETHER", most)
        calls.clear()
        for got, own in zip(run_many([Clip(truth) for truth in truths], some, weights(), [None] * 3), alone, strict=True):
            assert all(tracks.equals(t) and figures == f for (tracks, figures), (t, f) in zip(got, own, strict=True))
        assert calls == want


def test_detections_as_arrays():
    truth = objects(12).sort_values(["t", "obj"])
    truth.loc[truth["obj"] == 3, "category"] = "walker"
    for cfg in (Config(arch=a, width=w, conf=c) for a in ("one_stage", "two_stage") for w in (640, 334) for c in (0.25, 0.7)):
        t, obj, cats, boxes = Clip(truth).found(cfg)
        want = detect(truth, cfg).sort_values(["t", "obj"])
        assert t.tolist() == want["t"].tolist() and obj.tolist() == want["obj"].tolist() and cats.tolist() == want["category"].tolist()
        assert (boxes[:, :4] == want[["x", "y", "w", "h"]].to_numpy(float)).all() and (boxes[:, 4:] == looks(want["vec_id"].fillna(0).to_numpy(np.int64), obj, t)).all()


def test_judge_deals_clips_and_tries_a_configuration_once(spark, monkeypatch):
    import sightline.catalog  # noqa: F401  the plans are loaded by it
    from sightline.plans import tuning

    calls, whole = [], tuning.evaluate
    monkeypatch.setattr(tuning, "evaluate", lambda truth, configs, *more: calls.append((truth.rdd.getNumPartitions(), configs)) or whole(truth, configs, *more))
    run, slow, fast = tuning.judge(spark, DATA), changed(tuning.BASE, gap=16), changed(tuning.BASE, gap=32)
    first = run([slow])
    assert [r["config"] for r in run([fast, slow, fast])] == [fast, slow] and run([slow]) == first
    assert [c for _, c in calls] == [[slow], [fast]] and all(n >= spark.sparkContext.defaultParallelism for n, _ in calls)


def test_curves_are_scored_once_for_all_queries(spark, monkeypatch):
    import sightline.catalog  # noqa: F401  the plans are loaded by it
    from sightline.plans import tuning

    calls, base = [], tuning.BASE
    score = lambda configs: calls.append(configs) or [{"config": c, "scene": 0, "sec": 8.0 / c.gap, "accuracy": 0.9, "recall": 1.0, "frames": 1, "over": 0.0} for c in configs]
    for name, fake in (("best_of", lambda *a: (base, [])), ("models", lambda *a: None), ("tuned", lambda *a: [{"config": changed(tuning.OURS, gap=32)}]), ("judge", lambda *a, **k: score), ("_SCORED", {})):
        monkeypatch.setattr(tuning, name, fake)
    monkeypatch.setattr(tuning.greedy, "rate_res", lambda *a: [{"config": changed(base, gap=2)}])
    got = tuning.curves(spark, "nowhere").groupBy("method").count().collect()
    assert {r["method"]: r["count"] for r in got} == {"ours": 1, "rate_res": 1, "frame_gate": 5, "var_rate": 4}
    assert [tuple(r) for r in tuning.table_within5(spark, "nowhere").collect()] == [(0, 0.9, 0.25, 4.0, 8.0, 0.5, 2.0)] and len(calls) == 1


def test_merging_many_frames_at_once_is_that_of_each():
    from sightline.model.schemas import seconds
    from sightline.windows.group import merge, merged_seconds

    rng, draw = np.random.default_rng(9), lambda n: [(int(x), int(y), int(x + w), int(y + h)) for w, h in rng.integers(1, 6, (n, 2)) for x, y in [(rng.integers(0, 21 - w), rng.integers(0, 13 - h))]]
    for n in (1, 2, 5, 11):
        frames = [draw(n) for _ in range(150)]
        sets = [[(w, h, seconds("one_stage", w, h)) for w, h in [(WIDTH, HEIGHT), *(32 * rng.integers(1, (21, 13), (2, 2))).tolist()]] for _ in frames]
        assert merged_seconds(np.array(frames), np.array(sets)) == pytest.approx([sum(size[2] for _, size in merge(f, s)) for f, s in zip(frames, sets)], abs=1e-12)


def test_total_times_are_those_of_the_frames(spark):
    from sightline.model.schemas import seconds
    from sightline.windows.group import signatures, total_times

    rng = np.random.default_rng(2)
    frames = {(s, t): {(int(x), int(y)) for x, y in rng.integers(0, (20, 12), (t % 4 + 1, 2))} for s in (0, 1) for t in range(12)}
    cells = spark.createDataFrame([(s, 0, t, x, y) for (s, t), own in frames.items() for x, y in own], "scene int, clip long, t long, cx int, cy int")
    have, every = [(WIDTH, HEIGHT), (96, 64)], [(WIDTH, HEIGHT), (32, 32), (128, 96), (320, 192)]
    got = {(r.scene, r.w, r.h): r.total for r in total_times(signatures(cells), have, every).collect()}
    cost = lambda own, extra: sum(w[4] for w in group_cells(own, [(*s, seconds("one_stage", *s)) for s in [*have, extra]]))
    assert got == pytest.approx({(s, *extra): sum(cost(own, extra) for (scene, _), own in frames.items() if scene == s) for s in (0, 1) for extra in every})


def test_matcher_learns_from_every_sequence(spark, monkeypatch):
    from sightline.sources.scenes import detections
    from sightline.track import scorers
    from sightline.tune import trial

    clip = objects(40, speed=6.0, seed=4)
    starts = {g: [min(len(own) - 1, o * 7919 % g) for o, own in clip.groupby("obj")] for g in (1, 2, 4, 8, 16)}
    pieces = sum(-(-len(loop.thinned(own["t"].to_numpy(), g, starts[g][n])) // loop.STEPS) for n, (_, own) in enumerate(clip.groupby("obj")) for g in starts)
    parts = loop.training_sequences(clip)
    assert {len(p) for p in parts} == {pieces} and pieces > 500

    seen, gradient = set(), loss_and_gradient
    monkeypatch.setattr(scorers, "loss_and_gradient", lambda w, x, *more: seen.update(x[:, 0, 0].tolist()) or gradient(w, x, *more))
    some = [p[:50].copy() for p in parts]
    some[0][:, 0, 0] = np.arange(50) / 64
    train_recurrent(*some, steps=2, batch=4)
    assert len(seen) == 50

    fitted = []
    monkeypatch.setattr(trial, "train_by_parts", lambda parts, **options: fitted.append(sum(len(p[0]) for p in parts())) or {})
    trial.train(spark, DATA, clips=60)
    boxes = detections(spark, DATA, "train", clips=60).toPandas()
    assert fitted == [sum(len(loop.training_sequences(own)[0]) for _, own in boxes.groupby(["scene", "clip"]))] and fitted[0] > 800


def test_sizes_are_learnt_from_every_frame_of_the_training_set(spark, monkeypatch):
    import sightline.catalog  # noqa: F401  the plans are loaded by it
    from sightline.plans import tuning
    from sightline.sources.scenes import detections, frame_cells, simulated
    from sightline.tune.trial import Models

    asked = []
    monkeypatch.setattr(tuning, "_MODELS", {})
    monkeypatch.setattr(tuning, "train", lambda *a, **options: asked.append(options) or Models())
    monkeypatch.setattr(tuning, "choose_sizes", lambda cells, k, **options: asked.append((cells.select("scene", "clip", "t").distinct().count(), k, options)))
    tuning.models(spark, DATA)
    seen = frame_cells(simulated(detections(spark, DATA, "train"), "one_stage", 640, 0.5)).select("scene", "clip", "t").distinct().count()
    assert asked == [{"best": tuning.BASE, "clips": 60}, (seen, 3, {"sample": None})] and seen > 500


def test_proxies_are_tried_on_every_frame():
    from sightline.tune import greedy

    tried = []
    greedy.ProxyModule().cache(lambda configs: tried.extend(configs) or [{"config": c, "sec": 1.0, "recall": 1.0} for c in configs], Config(gap=4))
    assert len(tried) == 26 and {c.gap for c in tried} == {1}
