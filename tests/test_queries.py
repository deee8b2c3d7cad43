"""The registered queries against their SQL twins, and plans that must hold at scale."""

import duckdb
import numpy as np
import pytest

from sightline.catalog import ORACLES, QUERIES

DATA = "/root/testdata/sf0.001"
TABLES = "region nation customer supplier part orders lineitem events documents embeddings pages benchmark labels conversations".split()


def rows(frame):
    frame = frame[sorted(frame.columns)].astype(object).where(frame.notna(), None)
    fix = lambda v: v if v is None or isinstance(v, (str, bool)) else round(float(v), 6)
    return sorted(([fix(v) for v in r] for r in frame.values.tolist()), key=repr)


@pytest.mark.parametrize("name", sorted(ORACLES))
def test_equals_sql(spark, name):
    con = duckdb.connect()
    for t in TABLES:
        con.sql(f"CREATE VIEW {t} AS SELECT * FROM '{DATA}/{t}.parquet'")
    want, got = con.sql(ORACLES[name]).df(), QUERIES[name](spark, DATA).toPandas()
    assert sorted(got.columns) == sorted(want.columns)
    assert rows(got) == rows(want)


def test_flagship(spark):
    got = QUERIES["turning_counts_full"](spark, DATA).toPandas()
    assert set(got["pat"]) == set(range(5)) and got["n"].sum() > 0


def test_filters_and_columns_reach_the_scan(spark):
    plan = QUERIES["scan_projection"](spark, DATA)._jdf.queryExecution().executedPlan().toString()
    assert "PushedFilters: [IsNotNull(l_quantity), GreaterThan(l_quantity,45.0)]" in plan and "l_extendedprice" not in plan


def test_stream_tracker_equals_batch(spark, tmp_path):
    from sightline.sources.scenes import detections
    from sightline.stream.windows import drained, tracker
    from sightline.track.loop import track
    from sightline.track.scorers import Overlap

    boxes = detections(spark, DATA).where("scene = 4 and clip < 2 and category = 'car'").select("scene", "clip", "t", "obj", "category", "x", "y", "w", "h")
    boxes.coalesce(1).write.parquet(str(tmp_path / "boxes"))
    got = drained(tracker(spark.readStream.schema(boxes.schema).parquet(str(tmp_path / "boxes")))).toPandas()
    for clip, pdf in boxes.toPandas().groupby("clip"):
        want = track(pdf, Overlap()).groupby("obj")["track_id"].nunique().to_dict()
        assert got[got["clip"] == clip].groupby("obj")["track_id"].nunique().to_dict() == want


def test_experiments_read_all_clips_of_a_split(spark):
    from sightline.plans.tuning import BASE, clips
    from sightline.refine.paths import Reference, resample
    from sightline.sources.scenes import detections, objects
    from sightline.tune.trial import Models, changed, evaluate, train

    some = DATA.replace("0.001", "0.01")
    every = objects(spark, some, "val").select("scene", "clip").distinct().count()
    got = evaluate(clips(spark, some, "val"), [changed(BASE, gap=32)], Models())
    assert got[0]["clips"] == every > 90
    own, tracks = train(spark, some, rows=200), objects(spark, some, "train").toPandas()
    alone = detections(spark, some, "train").where("scene = 4").toPandas()
    paths = [resample(one.sort_values("t")[["x", "y"]].to_numpy()) for _, one in alone.groupby(["clip", "obj"]) if len(one) > 1]
    assert sorted(own.references) == sorted(tracks["scene"].unique()) and sorted(own.references[4].sizes) == sorted(Reference.build(np.array(paths)).sizes)


def test_whole_tables_beside_the_slices_of_the_sql(spark):
    some = DATA.replace("0.001", "0.01")
    whole, few = QUERIES["mota_mutual_all"](spark, some).toPandas(), QUERIES["mota_mutual"](spark, some).toPandas()
    assert rows(whole[(whole["scene"] == 0) & whole["clip"].isin([2, 5, 8, 11])].drop(columns="scene")) == rows(few)
    assert set(whole["scene"]) == set(range(5)) and whole["clip"].nunique() == 20
    assert set(QUERIES["subsample_tracks_all"](spark, some).toPandas()["scene"]) == set(range(5))


@pytest.mark.parametrize("name", ["sweep_threshold", "pareto", "proxy_next"])
def test_thresholds_make_no_row_for_a_cell_and_move_no_box(spark, name):
    plan = QUERIES[name](spark, DATA)._jdf.queryExecution().executedPlan().toString()
    assert "getbit" not in plan
    objects = plan.index("REPARTITION_BY_NUM")
    assert plan[plan.rindex("bit_or", 0, objects) : objects].count("Exchange") == 1  # that of the objects alone


def test_masks_of_boxes_across_and_beyond_the_border(spark):
    from sightline.sources.scenes import frame_cells

    rng = np.random.default_rng(3)
    some = [(0, 0, i, float(rng.integers(-120, 760)), float(rng.integers(-120, 500)), float(rng.integers(1, 700)), float(rng.integers(1, 400))) for i in range(200)]
    boxes = spark.createDataFrame(some, "scene int, clip long, t long, x double, y double, w double, h double")
    want = set()
    for _, _, t, x, y, w, h in some:
        x0, x1, y0, y1 = max(x - w / 2, 0), min(x + w / 2, 640), max(y - h / 2, 0), min(y + h / 2, 384)
        if x1 > x0 and y1 > y0:
            want |= {(t, i, j) for i in range(int(x0 // 32), int(-(-x1 // 32))) for j in range(int(y0 // 32), int(-(-y1 // 32)))}
    assert {(r.t, r.cx, r.cy) for r in frame_cells(boxes).collect()} == want


@pytest.mark.parametrize("name", ["config_space", "detection_next", "fit_size", "gap_ladder", "pick_within5", "published_speedup", "res_ladder"])
def test_reads_the_given_tables_in_spark(spark, name):
    plan = QUERIES[name](spark, DATA)._jdf.queryExecution().optimizedPlan().collectLeaves().toString()
    assert "o_orderkey" in plan and "c_custkey" in plan


def test_stream_tracker_gives_a_clip_at_once_and_parts_are_made_by_many_tasks(spark):
    from sightline.stream import windows as w

    jobs = spark.sparkContext.statusTracker()
    spark.sparkContext.setJobGroup("parts", "parts of a stream")
    w.in_order([spark.range(0, 80, 1, 8).selectExpr("id", "timestamp_seconds(id) AS ts")])
    spark.sparkContext.setLocalProperty("spark.jobGroup.id", None)
    tasks = [jobs.getStageInfo(s).numTasks for j in jobs.getJobIdsForGroup("parts") for s in jobs.getJobInfo(j).stageIds if jobs.getStageInfo(s)]
    assert 8 in tasks
