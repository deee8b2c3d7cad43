"""Queries that tune, compare with the baselines, and repeat the experiments on the simulated scenes."""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..catalog import query
from ..model.schemas import COST, FRAMES, SPLITS
from ..sources.scenes import detections, frame_cells, objects, sampled, simulated
from ..track.loop import EndSearch
from ..tune import greedy
from ..tune.trial import Clip, Config, Models, changed, evaluate, outcomes, train
from ..windows.group import choose_sizes
from .sql import with_scene

BASE = Config(arch="one_stage", width=640, conf=0.5)
OURS = changed(BASE, tracker="recurrent", refine="clusters")
FULL = changed(OURS, gap=4, proxy=1, threshold=0.2)
#: The method's sets: so many one-minute clips of each scene for training, validation and test. All of them are used; the study of trained proxies takes fewer.
CLIPS, PAIR_CLIPS = 60, 12
_MODELS: dict[tuple, Models] = {}


def models(spark: SparkSession, sf_dir: str, best: Config = BASE, **options) -> Models:
    """What is learnt from a best configuration's output on all clips and frames of the training set: match net, reference paths, window sizes."""
    key = (spark.sparkContext.applicationId, sf_dir, best.id, repr(sorted(options.items())))
    if key not in _MODELS:
        own = train(spark, sf_dir, best=best, clips=CLIPS, **options)
        seen = simulated(detections(spark, sf_dir, "train", clips=CLIPS), best.arch, best.width, best.conf)
        own.sizes = choose_sizes(frame_cells(seen), 3, sample=None)
        _MODELS[key] = own
    return _MODELS[key]


def clips(spark: SparkSession, sf_dir: str, split: str, scenes: str = "true", gap: int = 1) -> DataFrame:
    """True boxes of the sampled clips of a split (all of them where there are no more): the tuner's validation clips, the experiments' test clips."""
    return detections(spark, sf_dir, split, gap, True, CLIPS).where(scenes)


def dealt(spark: SparkSession, sf_dir: str, split: str, truth: DataFrame, parts: int) -> DataFrame:
    """The boxes of the sampled clips (a bounded number) with a column ``part``: each scene's clips are dealt evenly, and every part has a partition to itself."""
    # a number for each partition that its hash leads to
    found = spark.range(40 * parts).select("id", F.expr(f"pmod(hash(id), {parts})").alias("to")).groupBy("to").agg(F.min("id").alias("id")).collect()
    labels = F.array(*[F.lit(r.id).cast("long") for r in found])
    places = sampled(spark, sf_dir, split, CLIPS).select("scene", "clip", F.get(labels, F.expr(f"int(pmod(place + 7 * scene, {len(found)}))")).alias("part"))
    return truth.join(F.broadcast(places), ["scene", "clip"]).repartition(parts, "part")


def judge(spark: SparkSession, sf_dir: str, split: str = "val", scenes: str = "true", by: tuple[str, ...] = (), own: Models | None = None):
    """Scores configurations on sampled clips; the learnt parts are made when a configuration needs them."""
    # dealt once, so that no trial moves boxes; clips of a part share the steps over frames, so parts are few
    truth = dealt(spark, sf_dir, split, clips(spark, sf_dir, split, scenes), 2 * spark.sparkContext.defaultParallelism).cache()

    known: dict[Config, list[dict]] = {}

    def run(configs: list[Config]) -> list[dict]:
        if todo := [c for c in dict.fromkeys(configs) if c not in known]:
            plain = all(c.tracker != "recurrent" and c.refine != "clusters" and c.proxy is None for c in todo)
            rows = evaluate(truth, todo, Models() if plain and own is None else own or models(spark, sf_dir), by)
            known.update((c, [r for r in rows if r["config"] == c]) for c in todo)
        return [r for c in dict.fromkeys(configs) for r in known[c]]

    return run


def best_of(spark: SparkSession, sf_dir: str) -> tuple[Config, list[dict]]:
    """The best configuration on the validation clips, and the trace of its search."""
    key = (spark.sparkContext.applicationId, sf_dir)
    if key not in _BEST:
        _BEST[key] = greedy.find_best(judge(spark, sf_dir), BASE)
    return _BEST[key]


def tuned(spark: SparkSession, sf_dir: str, points: int = 8) -> list[dict]:
    """The joint tuner's curve from the best configuration on, with the parts that learnt from that configuration's output."""
    key = (spark.sparkContext.applicationId, sf_dir, points)
    if key not in _CURVES:
        best, _ = best_of(spark, sf_dir)
        own = models(spark, sf_dir, best)
        start = changed(best, tracker="recurrent", refine="clusters")
        _CURVES[key] = greedy.tune(judge(spark, sf_dir, own=own), start, [greedy.DetectionModule(), greedy.ProxyModule(), greedy.TrackingModule()], points=points)[0]
    return _CURVES[key]


_BEST: dict[tuple, tuple[Config, list[dict]]] = {}
_CURVES: dict[tuple, list[dict]] = {}
_SCORED: dict[tuple, list[dict]] = {}
_ROW = "place int, arch string, width int, proxy int, threshold double, gap int, tracker string, refine string, gate double, tolerance double, sec double, accuracy double, recall double, frames bigint, over double"


def frame(spark: SparkSession, rows: list[dict], **more: str) -> DataFrame:
    """Trial rows as a DataFrame; ``more``: further columns and their types."""
    out = []
    for i, r in enumerate(rows):
        c = r["config"]
        out.append((i, c.arch, c.width, c.proxy, c.threshold, c.gap, c.tracker, c.refine, c.gate, c.tolerance, r["sec"], r["accuracy"], r["recall"], r["frames"], r["over"], *(r[k] for k in more)))
    return spark.createDataFrame(out, _ROW + "".join(f", {k} {t}" for k, t in more.items()))


@query()
def turning_counts_full(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Turning counts of the test clips after the full method: cells, windows, detector, reduced-rate tracker, repaired ends."""
    return outcomes(detections(spark, sf_dir, "test", FULL.gap, True), [FULL], models(spark, sf_dir)).select("scene", "clip", "pat", F.col("est").cast("long").alias("n"), F.col("truth").cast("long").alias("truth"))


@query()
def best_config_trace(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Both descents of the search for the best configuration."""
    return frame(spark, best_of(spark, sf_dir)[1], step="string")


@query()
def tune_curve(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The joint greedy tuner's curve on validation clips, from the best configuration on."""
    return frame(spark, tuned(spark, sf_dir), module="string")


@query()
def rate_res_curve(spark: SparkSession, sf_dir: str) -> DataFrame:
    return frame(spark, greedy.rate_res(judge(spark, sf_dir), BASE))


@query()
def frame_gate_curve(spark: SparkSession, sf_dir: str) -> DataFrame:
    return frame(spark, greedy.frame_gate(judge(spark, sf_dir), BASE))


@query()
def var_rate_curve(spark: SparkSession, sf_dir: str) -> DataFrame:
    return frame(spark, greedy.var_rate(judge(spark, sf_dir), BASE))


@query()
def proxy_grid(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Runtime and recall of every proxy size and threshold."""
    configs = [changed(BASE, gap=8, proxy=p, threshold=b) for p in range(5) for b in (0.05, 0.2, 0.4, 0.6, 0.8)]
    return frame(spark, judge(spark, sf_dir)(configs))


@query()
def sweep_gap(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Single-knob curve: only the sampling gap, for each tracker."""
    return frame(spark, judge(spark, sf_dir)([changed(BASE, gap=g, tracker=t) for g in greedy.GAPS for t in ("overlap", "motion", "recurrent")]))


@query()
def refine_variants(spark: SparkSession, sf_dir: str) -> DataFrame:
    """No repair, run to the border, extra frames, and reference clusters at reduced rates."""
    return frame(spark, judge(spark, sf_dir)([changed(OURS, gap=g, refine=r) for g in (4, 8, 16) for r in ("none", "border", "frames", "clusters")]))


@query()
def ablation(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Four steps on one scene: detector only, with reduced rate and overlap tracker, with the recurrent tracker, with the proxy."""
    run = judge(spark, sf_dir, scenes="scene = 1")
    steps = {
        "detector": (BASE, [greedy.DetectionModule()]), "overlap": (BASE, [greedy.DetectionModule(), greedy.TrackingModule()]),
        "recurrent": (OURS, [greedy.DetectionModule(), greedy.TrackingModule()]), "proxy": (OURS, [greedy.DetectionModule(), greedy.TrackingModule(), greedy.ProxyModule()]),
    }
    rows = [r | {"variant": name} for name, (start, modules) in steps.items() for r in greedy.tune(run, start, modules, points=6)[0]]
    return frame(spark, rows, variant="string")


def curves_of(spark: SparkSession, sf_dir: str) -> list[dict]:
    """Curves of all methods: tuned on validation clips, every point scored on test clips by scene; scored once for all queries that ask."""
    key = (spark.sparkContext.applicationId, sf_dir)
    if key in _SCORED:
        return _SCORED[key]
    best, _ = best_of(spark, sf_dir)
    val, test = judge(spark, sf_dir), judge(spark, sf_dir, "test", by=("scene",), own=models(spark, sf_dir, best))
    points = {
        "ours": [r["config"] for r in tuned(spark, sf_dir)], "rate_res": [r["config"] for r in greedy.rate_res(val, best)],
        "frame_gate": [changed(best, gate=b) for b in (0.1, 0.3, 0.5, 0.7, 0.9)], "var_rate": [changed(best, gap=16, tolerance=b, refine="frames") for b in (0.1, 0.3, 0.5, 0.7)],
    }
    names = {c.id: m for m, some in points.items() for c in some}
    _SCORED[key] = [r | {"method": names[r["config"].id]} for r in test([c for some in points.values() for c in some])]
    return _SCORED[key]


@query()
def curves(spark: SparkSession, sf_dir: str) -> DataFrame:
    return frame(spark, curves_of(spark, sf_dir), scene="int", method="string")


@query()
def table_within5(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Seconds of each method's fastest point within five points of the best accuracy of any method, by scene, and the gain over the next best."""
    rows = curves_of(spark, sf_dir)
    out = []
    for scene in sorted({r["scene"] for r in rows}):
        own = [r for r in rows if r["scene"] == scene]
        best = max(r["accuracy"] for r in own)
        got = {m: greedy.pick([r for r in own if r["method"] == m], least=best - 0.05) for m in ("ours", "rate_res", "frame_gate", "var_rate")}
        sec = {m: r["sec"] if r else None for m, r in got.items()}
        rest = [s for m, s in sec.items() if m != "ours" and s is not None]
        out.append((scene, best, *sec.values(), min(rest) / sec["ours"] if rest and sec["ours"] else None))
    return spark.createDataFrame(out, "scene int, best double, ours double, rate_res double, frame_gate double, var_rate double, gain double")


_CLIPS = "n AS (SELECT scene, count(DISTINCT clip) AS n FROM obj GROUP BY scene)"


def n_clips(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Clips of every scene: scene, n."""
    return objects(spark, sf_dir).groupBy("scene").agg(F.countDistinct("clip").alias("n"))


def _values(values) -> F.Column:
    return F.array(*[F.lit(v) for v in values])


@query(with_scene("SELECT scene, k AS rung, width, round((n * 480)::DOUBLE * (0.002e0 + 3.2e-8 * (width::DOUBLE * width::DOUBLE * 0.6e0)), 6) AS sec FROM (SELECT *, round(640 * pow(0.85e0, k))::INT AS width FROM n, range(0, 6) t(k))", _CLIPS))
def res_ladder(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Widths that the tuner steps down, and the detector's seconds over all frames of a scene at each."""
    base, unit = COST["one_stage"]
    rungs = n_clips(spark, sf_dir).select("scene", "n", F.posexplode(_values(greedy.resolution_ladder())).alias("rung", "width"))
    return rungs.select("scene", F.col("rung").cast("long").alias("rung"), "width", F.round(F.expr(f"double(n * {FRAMES}) * ({base!r}D + {unit!r}D * (double(width) * double(width) * 0.6e0))"), 6).alias("sec"))


@query(with_scene("SELECT scene, gap, next_gap, n * (480 // gap) AS frames, n * (480 // next_gap) AS next_frames FROM (SELECT *, CASE WHEN g < 32 THEN 2 * g END AS next_gap, g AS gap FROM n, (VALUES (1), (2), (4), (8), (16), (32)) v(g))", _CLIPS))
def gap_ladder(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The tuner's next gap from each gap, and the frames of a scene that are looked at before and after the step."""
    steps = F.array(*[F.struct(F.lit(g).alias("gap"), F.lit(greedy.next_gap(g)).cast("int").alias("next_gap")) for g in greedy.GAPS])
    rungs = n_clips(spark, sf_dir).select("scene", "n", F.inline(steps))
    return rungs.select("scene", "gap", "next_gap", F.expr(f"n * ({FRAMES} div gap)").alias("frames"), F.expr(f"n * ({FRAMES} div next_gap)").alias("next_frames"))


@query(with_scene("""SELECT scene, arch, width, gap, round((n * (480 // gap))::DOUBLE * (base + unit * (width::DOUBLE * width::DOUBLE * 0.6e0)), 6) AS sec FROM (SELECT *, round(640 * pow(0.85e0, k))::INT AS width, g AS gap
    FROM n, (VALUES ('one_stage', 0.002e0, 3.2e-8), ('two_stage', 0.01e0, 1.2e-7)) v(arch, base, unit), range(0, 6) t(k), (VALUES (1), (2), (4), (8), (16), (32)) w(g))""", _CLIPS))
def config_space(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The discretised space of detector and rate, for the exhaustive tuner, with each configuration's seconds on a scene."""
    costs = F.array(*[F.struct(F.lit(a).alias("arch"), F.lit(base).alias("base"), F.lit(unit).alias("unit")) for a, (base, unit) in COST.items()])
    space = n_clips(spark, sf_dir).select("scene", "n", F.inline(costs)).withColumn("width", F.explode(_values(greedy.resolution_ladder()))).withColumn("gap", F.explode(_values(greedy.GAPS)))
    return space.select("scene", "arch", "width", "gap", F.round(F.expr(f"double(n * ({FRAMES} div gap)) * (base + unit * (double(width) * double(width) * 0.6e0))"), 6).alias("sec"))


@query()
def ablation_elapsed(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The recurrent matcher without elapsed frames as input, and trained at the native rate only, beside the full one, by sampling gap."""
    variants = {"full": {}, "no_elapsed": {"elapsed": False}, "native_rate": {"gaps": (1,)}}
    rows = []
    for name, options in variants.items():
        run = judge(spark, sf_dir, own=models(spark, sf_dir, **options))
        rows += [r | {"variant": name} for r in run([changed(OURS, gap=g, refine="none") for g in (1, 4, 8, 16)])]
    return frame(spark, rows, variant="string")


@query()
def brute_force(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Every combination of a small space of widths, gaps and proxies on the sparsest scene's validation clips."""
    run = judge(spark, sf_dir, scenes="scene = 4")
    return frame(spark, greedy.brute(run, OURS, [640, 393], [1, 4, 16], [(None, 0.3), (1, 0.2), (3, 0.4)]))


@query(with_scene("""SELECT scene, split, clip, place FROM (SELECT *, row_number() OVER (PARTITION BY scene, split ORDER BY draw, clip) AS place
    FROM (SELECT DISTINCT scene, clip, CASE clip % 3 WHEN 0 THEN 'train' WHEN 1 THEN 'val' ELSE 'test' END AS split, ((clip * 7919 + scene * 104729) % 1000003) % 1000 AS draw FROM obj)) WHERE place <= 60"""))
def sample_clips(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The sample of one-minute clips: sixty of each scene for training, validation and test."""
    parts = [sampled(spark, sf_dir, split, CLIPS).select("scene", F.lit(split).alias("split"), "clip", F.col("place").cast("long").alias("place")) for split in SPLITS]
    return parts[0].unionByName(parts[1]).unionByName(parts[2])


@query(with_scene("SELECT scene, g AS gap, round(480e0 * n / (480 // g * n * (0.002e0 + 3.2e-8 * 245760e0)), 6) AS fps FROM (SELECT scene, count(DISTINCT clip)::DOUBLE AS n FROM obj GROUP BY scene), (VALUES (1), (2), (4), (8), (16)) v(g)"))
def frames_per_second(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Frames of video for each modelled second of the detector, by sampling gap."""
    n = objects(spark, sf_dir).groupBy("scene").agg(F.countDistinct("clip").cast("double").alias("n")).withColumn("gap", F.explode(F.expr("array(1, 2, 4, 8, 16)")))
    return n.select("scene", "gap", F.round(F.expr(f"480e0 * n / (480 div gap * n * ({COST['one_stage'][0]!r}D + {COST['one_stage'][1]!r}D * 245760e0))"), 6).alias("fps"))


@query()
def end_search(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Ends of the sampled test clips' tracks found by bisection inside skipped frames: mean miss before and after, and the detector calls made."""

    def run(key, pdf: pd.DataFrame) -> pd.DataFrame:
        clip, out = Clip(pdf), []
        t, obj, cats, boxes = clip.found(BASE)
        true = {o: g[["x", "y"]].to_numpy()[[0, -1]] for o, g in clip.truth.groupby("obj")}
        for gap in (4, 8, 16):
            search = EndSearch(list(range(0, FRAMES, gap)), clip.look(BASE))
            for o in np.unique(obj[obj >= 0]).tolist():
                own = np.flatnonzero((obj == o) & (t % gap == 0))
                if len(own) > 1:
                    ends = np.array(search.ends(t[own], boxes[own], cats[own[0]]))[:, :2]
                    miss = [float(np.hypot(*(p - true[o]).T).mean()) for p in (boxes[own][[0, -1], :2], ends)]
                    out.append((*key, gap, *miss, 0))
            out.append((*key, gap, None, None, search.calls()))
        return pd.DataFrame(out, columns=["scene", "clip", "gap", "before", "after", "calls"])

    rows = clips(spark, sf_dir, "test").groupBy("scene", "clip").applyInPandas(run, "scene int, clip bigint, gap int, before double, after double, calls bigint")
    return rows.groupBy("scene", "gap").agg(F.count("before").alias("tracks"), F.avg("before").alias("before"), F.avg("after").alias("after"), F.sum("calls").alias("calls"))
