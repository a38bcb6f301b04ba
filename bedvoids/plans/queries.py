"""Queries over the given tables: one for each method, variant, baseline, measure and operator."""

from __future__ import annotations

from collections.abc import Callable
from functools import lru_cache

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions import scalar
from ..functions.grid import bed_grid
from ..operators import baselines, components, density, explore, flow, gaussian, imagedb, lifecycle, relational, segment, similarity, supervoxel, target, track, traits
from ..sources import particles as P
from ..sources.shared import store, table
from . import measures, workloads
from .pipeline import ensemble
from .scenes import BOXES, GRID, run_of

SIZE = (3, 3, 3)
BOX = BOXES["rise"]

Query = Callable[[SparkSession, str], DataFrame]
QUERIES: dict[str, Query] = {}


def query(f: Query) -> Query:
    QUERIES[f.__name__] = f
    return f


def w1(spark, d):
    return P.slice_by_date(spark, d)


def w2(spark, d):
    return P.planted_bed(spark, d, "rise", GRID)


def field_w2(spark, d):
    return run_of(spark, d).field


def seed(spark, d, step: int = 5) -> int:
    """The largest bubble of a step."""
    return run_of(spark, d).traits.where(F.col("step") == step).orderBy(F.desc("voxels"), "bubble").first()["bubble"]


def tracks_of(spark, d):
    """All bubbles of the step in the middle, followed both ways."""
    r = run_of(spark, d)
    return track.with_traits(track.trace_all(r.edges, 5, bubbles=r.traits), r.traits)


# particles and fields
@query
def particles_w1(spark, d):
    return w1(spark, d).groupBy("step").agg(F.count(F.lit(1)).alias("n"), F.min("x").alias("x_min"), F.max("x").alias("x_max"), F.round(F.sum("y"), 4).alias("y_sum"), F.round(F.sum("z"), 4).alias("z_sum"), F.sum("vx").alias("vx_sum"))


@query
def particles_w2(spark, d):
    return w2(spark, d).groupBy("step").agg(F.count(F.lit(1)).alias("n"), F.sum("vx").alias("vx_sum"))


@query
def planted_truth(spark, d):
    return P.truth(spark, "rise", GRID).unionByName(P.truth(spark, "shapes", GRID).withColumn("step", F.col("step") + 100))


@query
def bounds(spark, d):
    lo, hi = density.bounds(w1(spark, d))
    return spark.range(1).select(*[F.lit(v).alias(f"{n}_{a}") for n, at in (("lo", lo), ("hi", hi)) for a, v in zip("xyz", at, strict=True)])


@query
def histogram(spark, d):
    return density.histogram(w1(spark, d), GRID, axes=("x", "y"))


@query
def outside_bounds(spark, d):
    return density.outside(P.event_bed(spark, d, cap=None), P.event_grid())


@query
def density_dense(spark, d):
    return field_w2(spark, d).select("step", "voxel", "density")


@query
def density_rebin(spark, d):
    return density.coarser(density.histogram(w1(spark, d), GRID), 2)


@query
def density_image_space(spark, d):
    return density.histogram(w1(spark, d), bed_grid((24, 1, 24)))


@query
def pvf(spark, d):
    h = density.histogram(w1(spark, d), GRID)
    return h.select("step", GRID.voxel().alias("voxel"), F.round(F.col("sum_vx") / F.col("n"), 9).alias("rise_velocity"))


@query
def pvf_dense(spark, d):
    f = field_w2(spark, d)
    return f.select("step", "voxel", F.round("rise_velocity", 9).alias("rise_velocity"), density.motion_class(F.col("rise_velocity")).alias("motion"))


@query
def smooth_density(spark, d):
    return density.smooth_counts(field_w2(spark, d), GRID, "triangle").select("step", "voxel", F.round("estimate", 9).alias("estimate"))


# target, clusters, similarity
@query
def target_box(spark, d):
    return target.select_box(field_w2(spark, d), BOX, 0).select("step", "voxel", "density")


@query
def target_gaussian(spark, d):
    return target.box_gaussian(field_w2(spark, d), BOX, 0).select(F.round("mu", 9).alias("mu"), F.round("sigma", 9).alias("sigma"), "n")


@query
def supervoxel_seeds(spark, d):
    return supervoxel.seeds(field_w2(spark, d), GRID, SIZE)


@query
def supervoxel_blocks(spark, d):
    return baselines.blocks(field_w2(spark, d), GRID, SIZE)


def blocks_w2(spark, d):
    f = field_w2(spark, d)
    return f, baselines.blocks(f, GRID, SIZE)


@query
def block_gaussians(spark, d):
    f, b = blocks_w2(spark, d)
    return gaussian.fit_clusters(b, f).select("step", "cluster", F.round("mu", 9).alias("mu"), F.round("sigma", 9).alias("sigma"), "n")


def _rounds(spark, d, n: int):
    f = field_w2(spark, d)
    labels, _, report = supervoxel.slic(f, GRID, SIZE, max_iter=n, engine="relational")
    return labels, report


@query
def supervoxel_iter1(spark, d):
    return _rounds(spark, d, 1)[0]


@query
def supervoxel_iter2(spark, d):
    return _rounds(spark, d, 2)[0]


@query
def supervoxel_array(spark, d):
    return run_of(spark, d).labels


@query
def supervoxel_report(spark, d):
    return run_of(spark, d).report


@query
def supervoxel_gaussians(spark, d):
    r = run_of(spark, d)
    return gaussian.fit_clusters(r.labels, r.field).select("step", "cluster", F.round("mu", 9).alias("mu"), F.round("sigma", 9).alias("sigma"), "n")


@query
def supervoxel_value_only(spark, d):
    return supervoxel.slic(field_w2(spark, d), GRID, SIZE, gamma=0.0, max_iter=4)[0]


@query
def supervoxel_place_only(spark, d):
    return supervoxel.slic(field_w2(spark, d), GRID, SIZE, gamma=1.0, max_iter=4)[0]


@query
def merged_moments(spark, d):
    """Moments of tiles of each block, put together."""
    f, b = blocks_w2(spark, d)
    parts = f.join(b, ["step", "voxel"]).groupBy("step", "cluster", F.pmod("voxel", F.lit(5)).alias("tile")).agg(*gaussian.moments())
    return gaussian.of_moments(gaussian.merge(parts, ["step", "cluster"])).select("step", "cluster", F.round("mu", 9).alias("mu"), F.round("sigma", 9).alias("sigma"), "n")


def _distance(spark, d, spread: str):
    f, b = blocks_w2(spark, d)
    return similarity.distances(gaussian.fit_clusters(b, f), run_of(spark, d).target, spread, 6).select("step", "cluster", "distance")


@query
def bhattacharyya_std(spark, d):
    return _distance(spark, d, "std")


@query
def bhattacharyya_var(spark, d):
    return _distance(spark, d, "var")


def _bsf(spark, d, norm: str, scope: str = "step"):
    f, b = blocks_w2(spark, d)
    return similarity.bsf(b, gaussian.fit_clusters(b, f), run_of(spark, d).target, norm, scope).select("step", "voxel", F.round("similarity", 6).alias("similarity"))


@query
def bsf_max(spark, d):
    return _bsf(spark, d, "max")


@query
def bsf_minmax(spark, d):
    return _bsf(spark, d, "minmax")


@query
def bsf_coefficient(spark, d):
    return _bsf(spark, d, "coefficient")


@query
def bsf_run_scope(spark, d):
    return _bsf(spark, d, "max", "run")


@query
def bsf_supervoxels(spark, d):
    return run_of(spark, d).bsf.select("step", "voxel", F.round("similarity", 6).alias("similarity"))


@query
def mv_bhattacharyya(spark, d):
    g = gaussian.fit_vectors(P.vector_bed(spark, d), "label", ["x", "y", "z"])
    a, b = g.select(*[F.col(c).alias(f"{c}_a") for c in g.columns]), g.select(*[F.col(c).alias(f"{c}_b") for c in g.columns])
    pairs = a.join(b, F.col("label_a") < F.col("label_b"))  # a few labels
    return pairs.select("label_a", "label_b", F.round(scalar.bhattacharyya_mv()("mu_a", "cov_a", "mu_b", "cov_b"), 8).alias("distance"))


# segmentation, components, traits
@query
def segmented(spark, d):
    return segment.by_similarity(run_of(spark, d).bsf).select("step", "voxel")


@query
def segment_sweep(spark, d):
    found = segment.sweep(run_of(spark, d).bsf, [0.88, 0.9, 0.92, 0.94, 0.96])
    return found.groupBy("threshold", "step").agg(F.count(F.lit(1)).alias("voxels"))


@query
def segment_levels(spark, d):
    return segment.levels(run_of(spark, d).bsf, [0.5, 0.8, 0.92])


@query
def threshold_profile(spark, d):
    return segment.threshold_profile(run_of(spark, d).bsf, 20)


@query
def components_6(spark, d):
    return run_of(spark, d).found.select("step", "voxel", "bubble")


@query
def components_18(spark, d):
    return components.label(segment.by_similarity(run_of(spark, d).bsf), GRID, 18).select("step", "voxel", "bubble")


@query
def components_26(spark, d):
    return components.label(segment.by_similarity(run_of(spark, d).bsf), GRID, 26, engine="propagate").select("step", "voxel", "bubble")


@query
def components_tiled(spark, d):
    return components.label(segment.by_similarity(run_of(spark, d).bsf), GRID, 6, engine="tiled").select("step", "voxel", "bubble")


def _traits(spark, d):
    return run_of(spark, d).traits


@query
def bubble_traits(spark, d):
    cols = [F.round(c, 6).alias(c) for c in ("volume", "xc", "yc", "zc", "aspect")]
    return _traits(spark, d).select("step", "bubble", "voxels", *cols, "ix_min", "ix_max", "iz_min", "iz_max", "is_freeboard")


@query
def trait_moments(spark, d):
    return traits.describe(run_of(spark, d).voxels, GRID, moments=True, width_axis="max").select("step", "bubble", F.round("aspect", 6).alias("aspect"), F.round("aspect_moments", 6).alias("aspect_moments"))


@query
def freeboard(spark, d):
    return segment.flag_freeboard(run_of(spark, d).found, GRID)


@query
def trait_fields(spark, d):
    r = run_of(spark, d)
    out = traits.enrich(r.voxels, r.bsf, r.field)
    return out.select("step", "bubble", F.round("mean_similarity", 6).alias("mean_similarity"), F.round("mean_rise", 6).alias("mean_rise"))


# tracking
@query
def overlap_edges(spark, d):
    return track.overlaps(run_of(spark, d).voxels)


@query
def overlap_edges_window(spark, d):
    return track.overlaps(run_of(spark, d).voxels, engine="window")


@query
def dice_edges(spark, d):
    return run_of(spark, d).edges.select("step", "src", "dst", F.round("dice", 9).alias("dice"))


@query
def jaccard_edges(spark, d):
    return run_of(spark, d).edges.select("step", "src", "dst", F.round("jaccard", 9).alias("jaccard"))


@query
def overlap_coefficient_edges(spark, d):
    return run_of(spark, d).edges.select("step", "src", "dst", F.round("overlap", 9).alias("overlap"))


@query
def box_edges(spark, d):
    return baselines.box_overlaps(_traits(spark, d))


@query
def links_without_confidence(spark, d):
    return baselines.overlap_links(track.overlaps(run_of(spark, d).voxels), "largest")


@query
def best_forward(spark, d):
    return track.best_links(run_of(spark, d).edges).select("step", "src", "dst", "inter", F.round("dice", 9).alias("dice"))


@query
def best_backward(spark, d):
    return track.best_links(run_of(spark, d).edges, "backward").select("step", "src", "dst", "inter", F.round("dice", 9).alias("dice"))


def _rounded(df: DataFrame) -> DataFrame:
    return df.withColumn("dice", F.round("dice", 9))


@query
def track_single(spark, d):
    return _rounded(track.trace(run_of(spark, d).edges, 5, seed(spark, d)))


@query
def track_single_recursive(spark, d):
    return _rounded(track.trace_recursive(run_of(spark, d).edges, 5, seed(spark, d)))


@query
def track_collective(spark, d):
    return _rounded(track.trace_all(run_of(spark, d).edges, 5))


@query
def track_all(spark, d):
    return _rounded(track.all_tracks(run_of(spark, d).edges, _traits(spark, d)))


@query
def rise_velocity(spark, d):
    return track.rise_velocity(tracks_of(spark, d)).select("track", "step", "bubble", F.round("rise_velocity", 4).alias("rise_velocity"))


@query
def low_dice_flag(spark, d):
    return track.flag_low_confidence(tracks_of(spark, d)).select("track", "step", "low_confidence")


@query
def volume_events(spark, d):
    return lifecycle.volume_events(tracks_of(spark, d)).select("track", "step", F.round("change", 6).alias("change"), "event")


@query
def graph_events(spark, d):
    return lifecycle.graph_events(track.overlaps(run_of(spark, d).voxels))


@query
def births_deaths(spark, d):
    r = run_of(spark, d, "shapes")
    return lifecycle.births_deaths(r.edges, r.traits, burst_layer=18)


@query
def event_counts(spark, d):
    return lifecycle.event_counts(lifecycle.graph_events(track.overlaps(run_of(spark, d).voxels)))


@query
def track_summary(spark, d):
    out = lifecycle.summary(tracks_of(spark, d))
    return out.select("track", "first_step", "last_step", "lifetime", F.round("path_length", 4).alias("path_length"), F.round("max_volume", 4).alias("max_volume"), "max_volume_step")


# exploration
@query
def query_panel(spark, d):
    return explore.query(_traits(spark, d), {"aspect": (0.6, 1.4), "voxels": (25, 45)}).select("step", "bubble", "voxels", F.round("aspect", 6).alias("aspect"))


@query
def query_centred(spark, d):
    return explore.query(_traits(spark, d), {"aspect": (1.0, 0.3)}, centred=True).select("step", "bubble")


@query
def spherical(spark, d):
    return explore.spherical(_traits(spark, d), 0.2).select("step", "bubble")


@query
def largest_brush(spark, d):
    return explore.brush(_traits(spark, d), "voxels", 0.25).select("step", "bubble", "voxels")


@query
def parallel_axes(spark, d):
    out = explore.parallel_axes(_traits(spark, d), ["voxels", "aspect", "xc"])
    return out.select("step", "bubble", "place", "axis", F.round("value", 4).alias("value"), F.round("scaled", 6).alias("scaled"))


@query
def scatter_bins(spark, d):
    return explore.scatter(_traits(spark, d), "step", "voxels", bins=5)


@query
def splom(spark, d):
    out = explore.splom(tracks_of(spark, d), ["step", "voxels", "xc"], ids=("track", "step"))
    return out.select("track", "step", "row_trait", "col_trait", F.round("y", 4).alias("y"), F.round("x", 4).alias("x"), F.round("color", 9).alias("color"))


@query
def correlations(spark, d):
    one = tracks_of(spark, d).where(F.col("track") == seed(spark, d))
    return explore.correlations(track.rise_velocity(one), ["step", "voxels", "xc"]).select("row_trait", "col_trait", F.round("r", 6).alias("r"))


@query
def trends(spark, d):
    out = explore.trends(track.rise_velocity(tracks_of(spark, d)))
    return out.select("track", F.round("volume_velocity_r", 6).alias("volume_velocity_r"), F.round("volume_per_step", 3).alias("volume_per_step"), F.round("volume_fit", 6).alias("volume_fit"), "n")


@query
def growth_share(spark, d):
    return explore.growth_share(tracks_of(spark, d))


@query
def velocity_by_volume(spark, d):
    out = explore.velocity_by_volume_change(track.rise_velocity(tracks_of(spark, d)))
    return out.select("direction", "n", F.round("mean_velocity", 3).alias("mean_velocity"), F.round("mean_change", 3).alias("mean_change"))


@query
def compare_tracks(spark, d):
    t = tracks_of(spark, d)
    return explore.compare(t, spark.range(12).select(F.col("id").cast("int").alias("step"))).select("step", "track", F.round("volume", 4).alias("volume"))


@query
def event_window(spark, d):
    return explore.event_window(lifecycle.volume_events(tracks_of(spark, d)), 4, 8).select("track", "step", "event")


@query
def projection_xz(spark, d):
    return imagedb.projection(run_of(spark, d).voxels)


@query
def images(spark, d):
    return imagedb.render(run_of(spark, d).voxels, None, GRID).select("step", "bubble", "width", "height", F.size("pixels").alias("pixels"), F.aggregate("pixels", F.lit(0.0), lambda a, b: a + b).alias("total"))


@query
def scene_layers(spark, d):
    r = run_of(spark, d)
    out = explore.scene(r.voxels, track.trace(r.edges, 5, seed(spark, d)), r.field.select("step", "voxel", "rise_velocity"))
    return out.select("layer", "step", "voxel", F.round("value", 9).alias("value"))


@query
def flow_around(spark, d):
    out = flow.around(run_of(spark, d).voxels, field_w2(spark, d), GRID)
    return out.select("step", "bubble", "region", "voxels", F.round("mean_rise", 6).alias("mean_rise"), F.round("up_share", 6).alias("up_share"), F.round("down_share", 6).alias("down_share"))


@query
def wake_contrast(spark, d):
    near = flow.around(run_of(spark, d).voxels, field_w2(spark, d), GRID)
    return flow.wake_contrast(near).select("step", "bubble", *[F.round(c, 6).alias(c) for c in ("below", "above", "side", "contrast")])


@query
def pixels(spark, d):
    """The pixels of every picture that aren't black."""
    r = run_of(spark, d)
    out = imagedb.render(r.voxels, r.bsf, GRID).select("step", "bubble", F.posexplode("pixels").alias("pixel", "value"))
    return out.where("value > 0").select("step", "bubble", "pixel", F.round(F.col("value").cast("double"), 4).alias("value"))


@query
def traits_weighted(spark, d):
    r = run_of(spark, d)
    return traits.describe(r.voxels, GRID, r.bsf).select("step", "bubble", *[F.round(c, 4).alias(c) for c in ("xc", "yc", "zc")])


@query
def lookup(spark, d):
    return explore.lookup(_traits(spark, d), 5, seed(spark, d)).select("step", "bubble", "voxels")


# baselines and measures
@query
def density_threshold_12(spark, d):
    return baselines.density_threshold(field_w2(spark, d), 12)


@query
def density_threshold_baseline(spark, d):
    return baselines.density_threshold(field_w2(spark, d), 5)


@query
def void_fraction_baseline(spark, d):
    return baselines.void_fraction_threshold(field_w2(spark, d), 30, 0.75)


@query
def kmeans_global(spark, d):
    return baselines.kmeans(field_w2(spark, d), GRID, 64, max_iter=5)[1]


@query
def accuracy_voxels(spark, d):
    out = measures.accuracy(segment.by_similarity(run_of(spark, d).bsf).join(_below_top(spark), "voxel", "left_semi"), P.truth(spark, "rise", GRID))
    return out.select("step", "hit", "missed", "extra", *[F.round(c, 6).alias(c) for c in ("precision", "recall", "iou")])


@query
def accuracy_bubbles(spark, d):
    return measures.bubble_recall(run_of(spark, d).voxels, components.label(P.truth(spark, "rise", GRID), GRID))


def _true(spark):
    labels = components.label(P.truth(spark, "rise", GRID), GRID)
    return labels, store(track.measured(track.overlaps(labels)), "true-edges")


@query
def tracking_accuracy(spark, d):
    r, (labels, edges) = run_of(spark, d), _true(spark)
    return measures.tracking_accuracy(track.all_tracks(r.edges, r.traits), track.all_tracks(edges, labels), r.voxels, labels)


@query
def event_accuracy(spark, d):
    return measures.event_accuracy(lifecycle.graph_events(run_of(spark, d).edges), lifecycle.graph_events(_true(spark)[1]))


def _below_top(spark):
    return spark.range(GRID.voxels).select(F.col("id").alias("voxel")).where(F.col("voxel") < 20 * GRID.n[1] * GRID.n[2])


@query
def homogeneity(spark, d):
    f, b = blocks_w2(spark, d)
    return measures.homogeneity(b, f)


@query
def reconstruction_rmse(spark, d):
    f, b = blocks_w2(spark, d)
    return measures.reconstruction_rmse(b, f)


@query
def compactness(spark, d):
    return measures.compactness(blocks_w2(spark, d)[1])


@query
def dice_profile(spark, d):
    out = measures.dice_profile(run_of(spark, d).edges)
    return out.select("links", *[F.round(c, 9).alias(c) for c in ("lowest", "mean", "median", "highest")])


@query
def sensitivity_cube(spark, d):
    found = segment.sweep(run_of(spark, d).bsf, [0.88, 0.92, 0.96])
    per = found.groupBy("threshold", "step").agg(F.count(F.lit(1)).alias("voxels"))
    return measures.sensitivity(per, ["threshold", "step"])


@query
def strided_dice(spark, d):
    labels = run_of(spark, d).voxels
    parts = [measures.dice_profile(track.measured(track.overlaps(labels, gap=g))).select(F.lit(g).alias("gap"), "links", F.round("mean", 9).alias("mean")) for g in (1, 2, 4, 8)]
    return parts[0].unionByName(parts[1]).unionByName(parts[2]).unionByName(parts[3])


# other tables and general operators
@query
def ensemble_rollup(spark, d):
    h = ensemble(P.ensemble_bed(spark, d), GRID)
    return relational.rollup_counts(h, ["member", "step"], F.col("n"))


@query
def material_density(spark, d):
    h = density.histogram(P.material_bed(spark, d), bed_grid((6, 2, 6)), keys=("diameter",))
    return h.groupBy("diameter").agg(F.sum("n").alias("particles"), F.count(F.lit(1)).alias("bins"), F.sum("sum_vx").alias("momentum"))


@query
def order_bed_histogram(spark, d):
    return density.histogram(P.order_bed(spark, d), workloads.ORDER_GRID)


@query
def event_hist_daily(spark, d):
    return density.histogram(P.event_bed(spark, d), P.event_grid()).groupBy("step").agg(F.sum("n").alias("n"), F.sum("sum_vx").alias("momentum"), F.count(F.lit(1)).alias("bins"))


@query
def event_sliding(spark, d):
    e = table(spark, d, "events").select(F.col("ts").cast("timestamp").alias("ts"), "value")
    out = e.groupBy(F.window("ts", "1 day", "6 hours").alias("w")).agg(F.count(F.lit(1)).alias("n"))
    return out.select(F.date_format("w.start", "yyyy-MM-dd HH:mm:ss").alias("start"), "n")


@query
def asof_step(spark, d):
    """Each step with the last one that a dump of every fourth step has."""
    per = run_of(spark, d).traits.groupBy("step").agg(F.count(F.lit(1)).alias("bubbles")).withColumn("run", F.lit(1))
    stored = per.where("step % 4 = 0").select("step", "run", F.col("bubbles").alias("stored"))
    return relational.asof_join(per, stored, "step", ["run"]).select("step", "bubbles", F.col("step_right").alias("stored_step"), "stored")


@query
def interval_join(spark, d):
    """Tracks that live at each step."""
    lives = lifecycle.summary(track.with_traits(track.all_tracks(run_of(spark, d).edges, run_of(spark, d).traits), run_of(spark, d).traits)).select("track", "first_step", "last_step")
    steps = run_of(spark, d).traits.select("step").distinct()
    return relational.interval_join(steps, lives, "step", "first_step", "last_step", width=4).select("step", "track")


@query
def morton_order(spark, d):
    return run_of(spark, d).voxels.select("step", "voxel", GRID.morton().alias("morton"))


@query
def bins_by_bucket(spark, d):
    return w1(spark, d).where(GRID.inside()).groupBy(*[GRID.bucket(i).alias(f"i{a}") for i, a in enumerate("xyz")]).agg(F.count(F.lit(1)).alias("n"))


@query
def void_voxels(spark, d):
    """The planted voxels of the first scene by the table function, with the particles that stay in them."""
    spark.udtf.register("void_voxels", P.void_voxels())
    voids = spark.createDataFrame(P.void_rows("rise"), P._VOID)
    voids.createOrReplaceTempView("_voids")
    args = ", ".join(c for c in voids.columns if c != "void")
    at = spark.sql(f"SELECT DISTINCT v.step, v.voxel FROM _voids, LATERAL void_voxels({args.replace('step', '_voids.step')}, {GRID.n[0]}, {GRID.n[1]}, {GRID.n[2]}) v")
    return at.join(field_w2(spark, d).select("step", "voxel", "density"), ["step", "voxel"])


@query
def range_join(spark, d):
    v = _traits(spark, d).select("step", "bubble", "xc", "zc")
    near = relational.bucketed_range_join(v.select("step", F.col("bubble").alias("a"), "xc", "zc"), v.select(F.col("step").alias("s2"), F.col("bubble").alias("b"), F.col("xc").alias("x2"), F.col("zc").alias("z2")), ["xc", "zc"], ["x2", "z2"], [6000.0, 4.0], [12000.0, 8.0])
    return near.where("s2 = step + 1").select("step", "a", "b")


@query
def top_bubbles(spark, d):
    return relational.top_k(_traits(spark, d), "voxels", 2, per=["step"]).select("step", "bubble", "voxels")


@query
def unpivoted(spark, d):
    return relational.unpivot(_traits(spark, d), ["step", "bubble"], ["voxels", "ix_min", "ix_max"])


@query
def moving_volume(spark, d):
    return relational.moving(tracks_of(spark, d), "track", "step", "voxels", 2, 2).select("track", "step", F.round("moving_mean", 9).alias("moving_mean"))


@query
def set_operations(spark, d):
    a = run_of(spark, d).voxels.where("step = 3").select("voxel")
    b = run_of(spark, d).voxels.where("step = 4").select("voxel")
    kinds = {"intersect": a.intersect(b), "union": a.union(b).distinct(), "except": a.exceptAll(b)}
    parts = [df.agg(F.count(F.lit(1)).alias("n"), F.sum("voxel").alias("total")).select(F.lit(k).alias("kind"), "n", "total") for k, df in kinds.items()]
    return parts[0].unionByName(parts[1]).unionByName(parts[2])


@query
def dice_array_sets(spark, d):
    sets = run_of(spark, d).voxels.where("step in (3, 4)").groupBy("step").agg(F.collect_set("voxel").alias("s")).groupBy().pivot("step", [3, 4]).agg(F.first("s"))
    return sets.select(F.round(scalar.dice_of_sets(F.col("3"), F.col("4")), 9).alias("dice"))


@query
def event_json(spark, d):
    e = table(spark, d, "events").select("event_type", F.from_json("props", "k int").alias("p"))
    return e.groupBy("event_type").agg(F.count("p.k").alias("n"), F.sum("p.k").alias("total"))


@query
def quality_points(spark, d):
    docs = table(spark, d, "documents", ["doc_id", "n_chars", "lang"]).join(table(spark, d, "labels"), "doc_id")
    return docs.groupBy("lang", "quality").agg(F.count(F.lit(1)).alias("n"), F.min("n_chars").alias("shortest"), F.max("n_chars").alias("longest"))


@lru_cache(maxsize=1)
def workload_queries() -> dict[str, Query]:
    return {f"workload_{k.lower()}": (lambda spark, d, k=k: workloads.run(k, spark, d)["result"]) for k in workloads.WORKLOADS}
