import struct
import zlib

import numpy as np
import pytest
from pyspark.sql import functions as F

from bedvoids.functions import scalar
from bedvoids.functions.grid import GridSpec, bed_grid
from bedvoids.operators import relational, similarity, supervoxel
from bedvoids.operators.gaussian import fit_clusters
from bedvoids.plans import measures, pipeline, queries, workloads
from bedvoids.plans.scenes import GRID, run_of
from bedvoids.sources import fields as store_fields
from bedvoids.sources import particles as P
from bedvoids.sources import stepfiles
from bedvoids.streaming import stream

SF = "/root/testdata/sf0.01"


def rows(df):
    return sorted(map(tuple, df.collect()), key=str)


@pytest.fixture(scope="module")
def rise(spark):
    return run_of(spark, SF)


def test_one_task_a_step_gives_what_joins_give(spark):
    grid = bed_grid((12, 3, 12))
    particles = P.planted_bed(spark, SF, "rise", grid, steps=2)
    goal = workloads.fitted(spark, particles, grid)
    for norm in ("max", "minmax", "coefficient"):
        a, b = (pipeline.in_situ(particles, grid, goal, engine=e, max_iter=3, norm=norm) for e in ("array", "relational"))
        for one, other in ((a.density, b.density), (a.labels, b.labels), (a.gaussians, b.gaussians), (a.report, b.report)):
            assert rows(one.select(*sorted(one.columns))) == rows(other.select(*sorted(one.columns)))
        near = lambda x: sorted((r.step, r.voxel, round(r.similarity, 9), r.rise_velocity) for r in x.fields.collect())
        assert near(a) == near(b)
    whole = similarity.bsf(a.labels, fit_clusters(a.labels, a.density), goal, scope="run")
    assert rows(pipeline.in_situ(particles, grid, goal, max_iter=3, scope="run").fields.select("step", "voxel", F.round("similarity", 9))) == rows(whole.select("step", "voxel", F.round("similarity", 9)))


def test_extraction_finds_the_planted_voids(rise):
    hit = workloads.run("E3", rise.bsf.sparkSession, SF)["result"].collect()
    assert len(hit) == 11 and min(r.recall for r in hit) > 0.85 and min(r.precision for r in hit) > 0.9


def test_merge_and_split_at_the_planted_steps(rise):
    spark = rise.bsf.sparkSession
    assert {(r.event, r.hit, r.missed) for r in queries.QUERIES["event_accuracy"](spark, SF).collect()} == {("merge", 1, 0), ("split", 1, 0)}
    out = workloads.run("E6", spark, SF)
    assert {(r.step, r.event) for r in out["graph"].collect()} == {(5, "merge"), (8, "split")}
    assert {r.event for r in out["result"].collect()} == {"merge", "split"}


def test_tracks_of_found_bubbles_follow_the_true_ones(rise):
    got = queries.QUERIES["tracking_accuracy"](rise.bsf.sparkSession, SF).collect()
    assert all(r.covered == r.steps and r.switches <= 1 for r in got)


def test_larger_supervoxels_lose_small_bubbles(spark):
    got = {(r["size"], r.partition, r.small): r.recalled / r.bubbles for r in workloads.run("E10", spark, SF)["result"].collect()}
    assert got[3, "supervoxels", True] > got[6, "supervoxels", True] and got[3, "supervoxels", True] > got[3, "blocks", True]


def test_thresholds_around_the_chosen_one_change_little(spark):
    n = {r.threshold: r.bubbles for r in workloads.run("E11", spark, SF)["result"].collect()}
    assert abs(n[0.92] - n[0.94]) <= 0.2 * n[0.92]


def test_boxes_link_what_does_not_overlap(spark):
    n = {(r.bubbles, r.links): r.n for r in workloads.run("E19", spark, SF)["result"].collect()}
    assert n["planted", "boxes only"] > 0 and n["extracted", "boxes"] >= n["extracted", "overlap"]


def test_local_clustering_computes_fewer_distances(spark):
    got = workloads.run("E20", spark, SF)["result"].collect()
    by = {m: sum(r.distances for r in got if r.method == m) for m in ("local", "global")}
    assert by["global"] > 5 * by["local"]


def test_stages_and_storage_of_a_run(spark):
    out = workloads.run("E14", spark, SF)
    stages = {r.stage: r for r in out["result"].collect()}
    assert stages["supervoxels and similarity"].rows == 6 * GRID.voxels and stages["all"].seconds >= stages["supervoxels and similarity"].seconds > 0
    assert all(r.share_of_producing > 0 for r in stages.values())
    stored = {r.kind: r.bytes for r in out["storage"].collect()}
    assert stored["raw, every step"] > 5 * stored["fields at the stride"] > 0
    io = {r.kind: r.bytes for r in workloads.run("E17", spark, SF)["result"].collect()}
    assert io["raw"] > io["checkpoint"] > io["fields"]


def test_post_hoc_and_any_number_of_tasks_give_the_same(spark):
    got = workloads.run("E16", spark, SF)["result"].collect()
    assert len(got) == 5 and {r.rows_that_differ for r in got} == {0}
    assert len({r.labels for r in workloads.run("E15", spark, SF)["result"].collect()}) == 1


def test_distribution_field_and_views_on_disk(rise, tmp_path):
    store_fields.write_distribution(rise.gaussians, rise.labels, str(tmp_path / "d"))
    back = rise.bsf.sparkSession.read.parquet(str(tmp_path / "d" / "gaussians"))
    assert rows(back.select("step", "cluster", "mu", "sigma", "n")) == rows(rise.gaussians.select("step", "cluster", "mu", "sigma", "n"))
    store_fields.write_fields(rise.field.select("step", "voxel", "density"), str(tmp_path / "f"))
    size = {r.what: r.bytes for r in store_fields.field_bytes(back.sparkSession, {"gaussians": str(tmp_path / "d" / "gaussians"), "field": str(tmp_path / "f")}).collect()}
    assert 0 < size["gaussians"] < size["field"]
    store_fields.write_view(back.sparkSession.createDataFrame([("tracked", 0.5)], "layer string, opacity double"), str(tmp_path / "v"))
    assert back.sparkSession.read.json(str(tmp_path / "v")).first().layer == "tracked"


def test_pictures_lie_where_the_table_says(rise, tmp_path):
    path = workloads.images_of(rise.bsf.sparkSession, SF, str(tmp_path / "db"))
    table = rise.bsf.sparkSession.read.option("header", True).csv(f"{path}/index").collect()
    assert len(table) == rise.traits.count()
    for r in table[:5]:
        raw = (tmp_path / "db" / "images" / r.FILE).read_bytes()
        assert raw[:8] == b"\x89PNG\r\n\x1a\n" and struct.unpack(">II", raw[16:24]) == (GRID.n[2], GRID.n[0])
        size = struct.unpack(">I", raw[33:37])[0]
        assert len(zlib.decompress(raw[41 : 41 + size])) == GRID.n[0] * (GRID.n[2] + 1)


def test_packed_fields_come_back(spark):
    grid = GridSpec((0.0, 0.0, 0.0), (1.0, 1.0, 1.0), (2, 2, 2))
    df = spark.createDataFrame([(0, 3, 0.5, None), (0, 0, 0.25, 1.0), (1, 7, 1.0, 2.0)], "step int, voxel long, a double, b double")
    packed = store_fields.pack(df, grid, ["a", "b"])
    assert {r.step: r.a for r in packed.collect()} == {0: [0.25, None, None, 0.5, None, None, None, None], 1: [None] * 7 + [1.0]}
    back = store_fields.unpack(packed, ["a", "b"]).where("a is not null")
    assert rows(back) == rows(df.select("step", "voxel", F.col("a").cast("float"), F.col("b").cast("float")))


def test_engines_of_components_in_a_run(rise):
    found = [rows(pipeline.post_hoc(rise.bsf, GRID, min_voxels=4, engine=e).labels.select("step", "voxel", "bubble")) for e in ("local", "tiled")]
    assert found[0] == found[1] == rows(rise.voxels.select("step", "voxel", "bubble"))


def test_position_only_and_value_only(spark):
    grid = bed_grid((6, 3, 6))
    field = np.random.default_rng(2).poisson(5, grid.n)
    for gamma in (0.0, 1.0):
        label, centre, _ = supervoxel.cluster_arrays(field, (3, 3, 3), gamma, 1)
        seeds, start, _ = supervoxel.cluster_arrays(field, (3, 3, 3), gamma, 0)
        at = np.stack(np.unravel_index(np.arange(field.size), grid.n), 1)
        for v in range(field.size):
            reach = np.flatnonzero((np.abs(at[v] - start[:, :3]) <= 3).all(1))
            d = np.linalg.norm(at[v] - start[reach, :3], axis=1) if gamma else np.abs(field.reshape(-1)[v] - start[reach, 3])
            assert label[v] == reach[d == d.min()].min()


def test_step_files(spark, tmp_path):
    r = np.random.default_rng(0)
    made = {s: r.random((50, 6)) for s in (0, 1, 2, 10)}
    for s, x in made.items():
        stepfiles.write_step(str(tmp_path), s, x)
    spark.dataSource.register(stepfiles.StepFileSource)
    read = spark.read.format("step_files").option("path", str(tmp_path)).option("stride", 2).load()
    got = {s: n for s, n in read.groupBy("step").agg(F.count(F.lit(1))).collect()}
    assert got == {0: 50, 2: 50, 10: 50}
    assert read.where("step = 2").agg(F.sum("x")).first()[0] == pytest.approx(made[2][:, 0].sum())


def test_producer_at_a_rate(spark, tmp_path):
    import time

    grid = bed_grid()
    q = stream.producer(spark, 200, grid).writeStream.format("memory").queryName("produced").option("checkpointLocation", str(tmp_path)).start()
    end = time.time() + 40
    while time.time() < end and not spark.table("produced").count():
        time.sleep(0.5)
    q.stop()
    got = spark.table("produced")
    assert got.count() and got.where(~grid.inside()).isEmpty()


def test_intervals_samples_and_reference_dice(spark, rise):
    points = spark.range(40).select(F.col("id").cast("int").alias("t"))
    spans = spark.createDataFrame([(1, 0, 3), (2, 3, 30), (3, 39, 90), (4, 8, 7)], "i int, lo int, hi int")
    want = sorted((t, i) for i, lo, hi in ((1, 0, 3), (2, 3, 30), (3, 39, 90)) for t in range(40) if lo <= t <= hi)
    assert sorted(map(tuple, relational.interval_join(points, spans, "t", "lo", "hi", 8).select("t", "i").collect())) == want
    some = relational.sampled(rise.field, 0.1)
    assert 0.05 < some.count() / rise.field.count() < 0.15 and rows(some) == rows(relational.sampled(rise.field, 0.1))
    assert {r.step for r in relational.sampled(rise.field, 0, by="step", shares={2: 0.5}).select("step").distinct().collect()} == {2}
    a, b = (rise.voxels.where(f"step = {s}").select("voxel", F.lit(1).alias(f"m{s}")) for s in (3, 4))
    both = a.join(b, "voxel", "full").na.fill(0)
    n = [x.count() for x in (a, b, a.join(b, "voxel"))]
    assert both.agg(scalar.dice_reference()("m3", "m4").alias("d")).first().d == pytest.approx(2 * n[2] / (n[0] + n[1]))


def test_every_query_needs_its_tables(spark):
    """All but the planted truth itself fail where there are no tables."""
    for name in ("components_6", "bubble_traits", "track_collective", "volume_events", "splom", "images", "asof_step", "workload_e7", "workload_e19"):
        with pytest.raises(Exception, match="(?i)path|exist"):
            (queries.QUERIES | queries.workload_queries())[name](spark, "/nowhere").collect()


def test_shares_of_a_base(spark):
    stages = spark.createDataFrame([("a", 1.0), ("b", 3.0)], "stage string, seconds double")
    assert tuple(measures.share(stages, 8.0).first()) == (4.0, 0.5)
