import pytest
from pyspark.sql import functions as F

from bedvoids.functions import scalar
from bedvoids.functions.grid import bed_grid
from bedvoids.operators import baselines, components, density, explore, flow, imagedb, lifecycle, track, traits
from bedvoids.plans import measures
from bedvoids.sources import particles as P

GRID = bed_grid()


@pytest.fixture(scope="module")
def rise(spark):
    labels = components.label(P.truth(spark, "rise", GRID), GRID).cache()
    return labels, traits.describe(labels, GRID).cache(), track.measured(track.overlaps(labels)).cache()


def rows(df):
    return sorted(map(tuple, df.collect()), key=lambda r: tuple((v is None, v) for v in r))


def test_set_measures_of_hand(spark):
    at = spark.createDataFrame([(0, 1, 1), (0, 2, 1), (0, 3, 1), (1, 2, 1), (1, 3, 1), (1, 4, 1)], "step int, voxel long, bubble int")
    r = track.measured(track.overlaps(at)).first()
    assert (r.inter, r.dice, r.jaccard, r.overlap) == (2, pytest.approx(2 / 3), 0.5, pytest.approx(2 / 3))
    sets = spark.range(1).select(scalar.dice_of_sets(F.array(*map(F.lit, (1, 2, 3))), F.array(*map(F.lit, (2, 3, 4)))).alias("d"))
    assert sets.first().d == pytest.approx(2 / 3)


def test_planted_sizes(rise):
    sizes = {}
    for r in rise[1].collect():
        sizes.setdefault(r.step, []).append(r.voxels)
    assert {k: sorted(v) for k, v in sizes.items() if k in (0, 4, 5, 7, 8)} == {0: [24, 26, 30, 34], 4: [26, 28, 44, 56], 5: [46, 50, 52], 7: [54, 54, 58], 8: [26, 28, 50, 62]}


def test_planted_events(rise):
    _, what, edges = rise
    assert rows(lifecycle.graph_events(edges).select("step", "event")) == [(5, "merge"), (8, "split")]
    tracks = track.with_traits(track.trace_all(edges, 5, bubbles=what), what)
    events = lifecycle.volume_events(tracks).where("event is not null")
    assert {(r.step, r.event) for r in events.collect()} >= {(5, "merge"), (8, "split")}
    planted = events.sparkSession.createDataFrame([(5, "merge"), (8, "split")], "step int, event string")
    found = {r.event: (r.hit, r.missed) for r in measures.event_accuracy(lifecycle.graph_events(edges), planted).collect()}
    assert found == {"merge": (1, 0), "split": (1, 0)}


def test_ways_to_follow_agree(rise):
    _, what, edges = rise
    one = rows(track.trace(edges, 5, 1))
    assert one == rows(track.trace_recursive(edges, 5, 1))
    assert one == [r for r in rows(track.trace_all(edges, 5, bubbles=what)) if r[0] == 1]
    everything = track.all_tracks(edges, what)
    assert everything.count() == what.count() == everything.select("step", "bubble").distinct().count()


def test_window_overlaps_and_gaps(rise):
    labels = rise[0]
    for gap in (1, 2, 3):
        assert rows(track.overlaps(labels, gap)) == rows(track.overlaps(labels, gap, "window"))
    mean = [measures.linked_dice(track.best_links(track.overlaps(labels, g)), rise[1], g).first()["mean"] for g in (1, 2, 4)]
    assert mean[0] > mean[1] > mean[2]  # stored more rarely, bubbles overlap less


def test_backward_is_forward_of_reversed_time(rise):
    labels, _, edges = rise
    turned = track.measured(track.overlaps(labels.withColumn("step", 100 - F.col("step"))))
    a = track.best_links(edges, "backward").select("step", "src", "dst")
    b = track.best_links(turned, "forward").select((99 - F.col("step")).alias("step"), F.col("dst").alias("src"), F.col("src").alias("dst"))
    assert rows(a) == rows(b)


def test_boxes_link_what_does_not_overlap(spark):
    labels = components.label(P.truth(spark, "shapes", GRID), GRID)
    what = traits.describe(labels, GRID)
    edges = track.overlaps(labels).select("step", "src", "dst")
    boxes = baselines.box_overlaps(what)
    assert edges.join(boxes, ["step", "src", "dst"], "left_anti").count() == 0
    assert boxes.join(edges, ["step", "src", "dst"], "left_anti").count() > 0
    ends = {(r.step, r.event) for r in lifecycle.births_deaths(track.overlaps(labels), what).collect()}
    assert ends == {(4, "birth"), (8, "dissipation")}


def test_low_dice_of_hand(spark):
    dice = [0.8, 0.8, 0.82, 0.79, 0.81, 0.2]
    df = spark.createDataFrame([(1, i, v) for i, v in enumerate(dice)], "track int, step int, dice double")
    got = [r.low_confidence for r in track.flag_low_confidence(df, k=5.0).orderBy("step").collect()]
    assert got == [False] * 5 + [True]


def test_volumes_of_hand(spark):
    df = spark.createDataFrame([(1, i, float(v)) for i, v in enumerate([10, 10, 16, 16, 8])], "track int, step int, volume double")
    assert [r.event for r in lifecycle.volume_events(df).orderBy("step").collect()] == [None, None, "merge", None, "split"]


def test_growing_bubble_speeds_up(rise):
    _, what, edges = rise
    one = track.rise_velocity(track.with_traits(track.trace(edges, 0, 1), what))
    r = {(x.row_trait, x.col_trait): x.r for x in explore.correlations(one, ["step", "volume", "xc", "rise_velocity"]).collect()}
    assert all(v > 0.5 for v in r.values())


def test_particles_around(spark):
    p = P.planted_bed(spark, "/root/testdata/sf0.01", "rise", GRID, steps=2, wakes=True)
    field = density.density_field(density.histogram(p, GRID), GRID)
    labels = components.label(P.truth(spark, "rise", GRID).where("step < 2"), GRID)
    near = flow.around(labels, field, GRID)
    mean = {r.region: r.m for r in near.groupBy("region").agg(F.avg("mean_rise").alias("m")).collect()}
    assert mean["side"] < 0 < mean["above"] < mean["below"]
    assert flow.wake_contrast(near).agg(F.avg("contrast")).first()[0] > 0


def test_pictures(rise, spark, tmp_path):
    labels, what, _ = rise
    images = imagedb.render(labels.where("step = 0"), None, GRID)
    assert images.count() == 4 and all(len(r.pixels) == 24 * 24 for r in images.collect())
    assert all(bytes(r.png).startswith(b"\x89PNG") for r in imagedb.pictures(images).collect())
    imagedb.write(images, what.where("step = 0"), str(tmp_path))
    index = spark.read.option("header", True).csv(f"{tmp_path}/index")
    assert index.count() == 4 and "FILE" in index.columns


def test_views(rise):
    _, what, edges = rise
    axes = explore.parallel_axes(what, ["voxels", "aspect"])
    assert axes.count() == 2 * what.count() and axes.where("scaled not between 0 and 1").count() == 0
    assert explore.lookup(what, 0, 1).count() == 1
    assert explore.brush(what, "voxels", 0.25).count() >= what.count() * 0.25
    assert explore.spherical(what, 0.2).where("abs(aspect - 1) > 0.2").count() == 0
    assert measures.tracking_accuracy(track.all_tracks(edges, what), track.all_tracks(edges, what), rise[0], rise[0]).agg(F.sum("switches")).first()[0] == 0
