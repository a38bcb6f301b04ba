from math import log, sqrt

import numpy as np
import pytest
from pyspark.sql import functions as F

from bedvoids.functions import scalar
from bedvoids.functions.grid import Box, GridSpec, Target, bed_grid, simulation_step
from bedvoids.operators import baselines, components, density, gaussian, segment, similarity, supervoxel, target
from bedvoids.sources import fields as store_fields
from bedvoids.sources import particles as P

P_SCHEMA = "step int, x double, y double, z double, vx double, vy double, vz double"


@pytest.fixture(scope="module")
def bed(spark):
    grid = bed_grid((12, 4, 12))
    particles = P.planted_bed(spark, "/root/testdata/sf0.01", "rise", grid, steps=2)
    hist = density.histogram(particles, grid).cache()
    return grid, particles, hist, density.density_field(hist, grid).cache()


def test_bins_of_hand(spark):
    grid = GridSpec((0.0, 0.0, 0.0), (2.0, 1.0, 2.0), (2, 1, 2))
    rows = [(0, 0.5, 0.5, 0.5, 2.0, 0.0, 0.0), (0, 2.0, 1.0, 2.0, 4.0, 0.0, 0.0), (0, 0.9, 0.1, 0.2, 0.0, 0.0, 0.0), (0, 2.1, 0.5, 0.5, 9.0, 0.0, 0.0)]
    p = spark.createDataFrame(rows, P_SCHEMA)
    field = {r.voxel: (r.density, r.rise_velocity) for r in density.density_field(density.histogram(p, grid), grid).collect()}
    assert field == {0: (2, 1.0), 1: (0, None), 2: (0, None), 3: (1, 4.0)}
    assert density.outside(p, grid).first().outside == 1
    assert density.bounds(p) == ((0.5, 0.1, 0.2), (2.1, 1.0, 2.0))
    still = density.rise_velocity_field(density.histogram(p, grid), grid, empty_velocity=0.0)
    assert {r.voxel: r.rise_velocity for r in still.collect()} == {0: 1.0, 1: 0.0, 2: 0.0, 3: 4.0}


def test_sums_are_kept(bed):
    grid, particles, hist, field = bed
    assert field.agg(F.sum("density")).first()[0] == particles.where(grid.inside()).count()
    a = field.agg(F.sum(F.col("density") * F.col("rise_velocity"))).first()[0]
    assert a == pytest.approx(particles.where(grid.inside()).agg(F.sum("vx")).first()[0])
    direct = density.histogram(particles, grid.coarser(2))
    assert sorted(map(tuple, density.coarser(hist, 2).select("step", "ix", "iy", "iz", "n").collect())) == sorted(map(tuple, direct.select("step", "ix", "iy", "iz", "n").collect()))


def test_bhattacharyya_of_hand(spark):
    def at(mu, sigma, goal, spread):
        return spark.range(1).select(scalar.bhattacharyya(F.lit(float(mu)), F.lit(float(sigma)), goal, spread).alias("d")).first().d

    assert at(0, 1, Target(0, 1, 1), "std") == 0
    assert at(0, 1, Target(2, 1, 1), "std") == pytest.approx(0.5)
    assert at(0, 1, Target(0, 4, 1), "std") == pytest.approx(0.5 * log(2.5 / 2))
    assert at(0, 2, Target(1, 3, 1), "var") == pytest.approx(1 / 8 / 6.5 + 0.5 * log(6.5 / 6))
    assert scalar.bhattacharyya_many(np.zeros(1), np.array([[4.0]]), np.ones(1), np.array([[9.0]])) == pytest.approx(at(0, 2, Target(1, 3, 1), "var"))


def test_target_knows_its_bins(bed):
    grid, _, _, field = bed
    goal = target.fit_target(field, Box((1, 2), (1, 2), (1, 2)), 0, grid=grid)
    assert goal.check(grid) is goal
    with pytest.raises(ValueError, match="bins"):
        goal.check(grid.coarser(2))
    with pytest.raises(ValueError, match="no voxel"):
        target.fit_target(field, Box((50, 51), (0, 0), (0, 0)), 0)


@pytest.mark.parametrize("window", ["closed", "half_open"])
def test_engines_of_supervoxels_agree(bed, window):
    grid, _, _, field = bed
    a, ca, ra = supervoxel.slic(field, grid, max_iter=4, window=window)
    b, cb, rb = supervoxel.slic(field, grid, max_iter=4, engine="relational", window=window)
    rows = lambda df: sorted(map(tuple, df.select("step", "voxel", "cluster").collect()))
    assert rows(a) == rows(b)
    numbers = lambda df: sorted(map(tuple, df.select("step", "iteration", "changed", "distances", "converged").collect()))
    assert numbers(ra) == numbers(rb)
    assert len(rows(a)) == grid.voxels * 2
    place = lambda df: {(r.step, r.cluster): (r.cx, r.cv, r["size"]) for r in df.collect()}
    p, q = place(ca), place(cb)
    assert p.keys() == q.keys() and all(np.allclose(p[k], q[k]) for k in p)


def test_supervoxels_end_and_beat_blocks(bed):
    from bedvoids.plans import measures

    grid, _, _, field = bed
    labels, _, report = supervoxel.slic(field, grid, max_iter=60)
    last = {r.step: (r.changed, r.converged) for r in report.orderBy("iteration").collect()}
    assert all(c == 0 and k for c, k in last.values())
    own, regular = (measures.reconstruction_rmse(x, field).where("step = 0").first().rmse for x in (labels, baselines.blocks(field, grid)))
    assert own < regular
    assert measures.distance_count(report).where("step = 0").first().distances < baselines.kmeans(field, grid, 64, max_iter=5)[1].where("step = 0").agg(F.sum("distances")).first()[0] * 5


@pytest.mark.parametrize("norm", ["max", "minmax", "coefficient"])
@pytest.mark.parametrize("scope", ["step", "run"])
def test_similarity_range(bed, norm, scope):
    grid, _, _, field = bed
    labels = baselines.blocks(field, grid)
    g = gaussian.fit_clusters(labels, field)
    row = similarity.bsf(labels, g, Target(1.0, 1.0, 9), norm, scope).agg(F.min("similarity"), F.max("similarity"), F.count(F.lit(1))).first()
    assert 0 <= row[0] <= row[1] <= 1 and row[2] == grid.voxels * 2


def test_moments_add_up(bed):
    grid, _, _, field = bed
    labels = baselines.blocks(field, grid)
    both = labels.join(field.select("step", "voxel", "density"), ["step", "voxel"]).withColumn("part", F.col("voxel") % 3)
    merged = gaussian.of_moments(gaussian.merge(both.groupBy("step", "cluster", "part").agg(*gaussian.moments()), ["step", "cluster"]))
    assert sorted(map(tuple, merged.select("step", "cluster", "mu", "sigma", "n").collect())) == sorted(map(tuple, gaussian.fit_clusters(labels, field).collect()))
    assert merged.agg(F.min("sigma")).first()[0] >= sqrt(1 / 12)


def test_touching_corners_and_edges(spark):
    grid = GridSpec((0.0,) * 3, (1.0,) * 3, (4, 4, 4))
    corner = spark.createDataFrame([(0, 0), (0, (1 * 4 + 1) * 4 + 1)], "step int, voxel long")
    edge = spark.createDataFrame([(0, 0), (0, (0 * 4 + 1) * 4 + 1)], "step int, voxel long")
    n = lambda df, c, e: components.label(df, grid, c, engine=e, tile=(1, 1, 1)).agg(F.max("bubble")).first()[0]
    for engine in ("local", "tiled", "propagate"):
        assert [n(corner, c, engine) for c in (6, 18, 26)] == [2, 2, 1]
        assert [n(edge, c, engine) for c in (6, 18, 26)] == [2, 1, 1]


def test_engines_of_components_agree(spark):
    grid = bed_grid()
    at = P.truth(spark, "rise", grid)
    rows = lambda e, c: sorted(map(tuple, components.label(at, grid, c, e, tile=(5, 2, 7)).select("step", "voxel", "bubble").collect()))
    for c in (6, 26):
        local = rows("local", c)
        assert local == rows("tiled", c) == rows("propagate", c)


def test_thresholds_nest(bed):
    grid, _, _, field = bed
    labels = baselines.blocks(field, grid)
    bsf = similarity.bsf(labels, gaussian.fit_clusters(labels, field), Target(1.0, 1.0, 9))
    n = {r.threshold: r.n for r in segment.sweep(bsf, [0.8, 0.9, 0.95]).groupBy("threshold").agg(F.count(F.lit(1)).alias("n")).collect()}
    assert n.get(0.8, 0) >= n.get(0.9, 0) >= n.get(0.95, 0)
    assert segment.by_similarity(bsf, 0.9).count() == n.get(0.9, 0)
    assert segment.levels(bsf, [0.8, 0.9]).where("level = 0.9D").count() == n.get(0.9, 0)


def test_fields_survive_storage(spark, bed, tmp_path):
    grid, _, _, field = bed
    rows = field.select("step", "voxel", F.col("density").cast("float").alias("density"), F.col("rise_velocity").cast("float").alias("rise_velocity"))
    back = store_fields.unpack(store_fields.pack(rows, grid, ["density", "rise_velocity"]), ["density", "rise_velocity"])
    want = sorted(map(tuple, rows.collect()))
    assert sorted(map(tuple, back.collect())) == want
    path = str(tmp_path / "f")
    store_fields.write_fields(rows, path)
    store_fields.write_fields(rows.where("step = 1"), path)  # a step written again
    assert sorted((r.step, r.voxel) for r in store_fields.read_fields(spark, path).collect()) == sorted((w[0], w[1]) for w in want)


def test_names_in_sql(spark):
    scalar.register_sql(spark)
    row = spark.sql("SELECT dice(2L, 3L, 3L) a, jaccard(2L, 3L, 3L) b, bhattacharyya(0D, 1D, 2D, 1D) c, mixed_distance(2D, -1D, 0.3D) d").first()
    assert row.a == pytest.approx(2 / 3) and row.b == 0.5 and row.c == 0.5 and row.d == pytest.approx(1.3)
    assert spark.range(1).select(simulation_step(F.lit(116))).first()[0] == 11600
    neighbours = supervoxel.neighbours_python()
    assert neighbours(F.lit(1), F.lit(1), F.lit(1), F.lit(6)).count() == 6
