"""The experiments, on the given tables. Each returns named tables; "result" is the one to look at."""

from __future__ import annotations

import time
from collections.abc import Callable
from functools import reduce

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions.grid import Box, GridSpec, Target, bed_grid
from ..operators import baselines, components, density, explore, flow, gaussian, imagedb, lifecycle, segment, similarity, supervoxel, target, track, traits
from ..sources import fields as store_fields
from ..sources import particles as P
from ..sources.shared import fresh_path, store
from . import measures, pipeline
from .scenes import BOXES, GRID, LEAST, run_of

ORDER_GRID = GridSpec((900.0, 0.0, 0.0), (450000.0, 5.0, 51.0), (12, 3, 12))
Tables = dict[str, DataFrame]
WORKLOADS: dict[str, Callable[..., Tables]] = {}


def workload(name: str):
    def put(f: Callable[..., Tables]) -> Callable[..., Tables]:
        WORKLOADS[name] = f
        return f

    return put


def run(name: str, spark: SparkSession, sf_dir: str, **params) -> Tables:
    return WORKLOADS[name](spark, sf_dir, **params)


def _grid(n: tuple[int, int, int] = (24, 6, 24)) -> GridSpec:
    return bed_grid(n)


def void_box(grid: GridSpec, scene: str = "rise", void: str = "grow", step: int = 0, share: float = 0.6) -> Box:
    """A box inside a planted void, as a user would draw it."""
    row = next(r for r in P.void_rows(scene) if r[0] == void and r[1] == step)
    centre, radius = row[2:5], row[5:8]
    ends = []
    for c, r, n in zip(centre, radius, grid.n, strict=True):
        lo, hi = int((c - r * share) * n + 0.5), int((c + r * share) * n - 0.5)
        mid = min(n - 1, int(c * n))
        ends.append((min(lo, mid), max(hi, mid)))
    return Box(*ends)


def bed(spark: SparkSession, sf_dir: str, grid: GridSpec, scene: str = "rise", steps: int | None = None, wakes: bool = False) -> DataFrame:
    return P.planted_bed(spark, sf_dir, scene, grid, steps=steps, wakes=wakes)


def fitted(spark: SparkSession, particles: DataFrame, grid: GridSpec, scene: str = "rise", void: str = "grow", step: int = 0) -> Target:
    field = density.density_field(density.histogram(particles.where(F.col("step") == step), grid), grid)
    return target.fit_target(field, void_box(grid, scene, void, step), step, grid=grid)


@workload("E1")
def e1(spark, sf_dir, **_) -> Tables:
    """The Gaussian of the selected region against that of the whole bed."""
    r = run_of(spark, sf_dir)
    parts = {"target": BOXES["rise"], "bed": Box((0, 19), (0, GRID.n[1] - 1), (0, GRID.n[2] - 1))}
    rows = [target.box_gaussian(r.field, box, 0).select(F.lit(k).alias("region"), F.round("mu", 9).alias("mu"), F.round("sigma", 9).alias("sigma"), "n") for k, box in parts.items()]
    return {"result": reduce(DataFrame.unionByName, rows)}


@workload("E2")
def e2(spark, sf_dir, **_) -> Tables:
    """All tables in situ."""
    r = run_of(spark, sf_dir)
    fields = r.bsf.select("step", "voxel", F.round("similarity", 6).alias("similarity"), F.round("rise_velocity", 9).alias("rise_velocity"))
    return {"result": fields, "density": r.field, "labels": r.labels, "gaussians": r.gaussians, "report": r.report}


def _rounded(df: DataFrame, **digits: int) -> DataFrame:
    return df.select(*[F.round(c, digits[c]).alias(c) if c in digits else c for c in df.columns])


@workload("E3")
def e3(spark, sf_dir, **_) -> Tables:
    """Segmentation at 0.92 and components, against the planted voxels."""
    r = run_of(spark, sf_dir)
    return {"result": _rounded(measures.accuracy(r.voxels, P.truth(spark, "rise", GRID)), precision=6, recall=6, iou=6), "labels": r.voxels}


@workload("E4")
def e4(spark, sf_dir, **_) -> Tables:
    """Overview: the largest bubbles, a query on aspect and volume, their pictures."""
    r = run_of(spark, sf_dir)
    large = explore.brush(r.traits, "volume", 0.3)
    near = explore.query(r.traits, {"aspect": (0.5, 1.5), "voxels": (10, 60)})
    images = imagedb.render(r.voxels, r.bsf, GRID)
    return {"result": _rounded(near.select("step", "bubble", "voxels", "aspect"), aspect=6), "large": large, "axes": explore.parallel_axes(r.traits, ["volume", "aspect", "xc"]), "spread": explore.spread(near, images)}


@workload("E5")
def e5(spark, sf_dir, step: int = 5, **_) -> Tables:
    """The largest bubble in the middle of the run, both ways."""
    r = run_of(spark, sf_dir)
    seed = r.traits.where(F.col("step") == step).orderBy(F.desc("voxels"), "bubble").first()
    found = track.with_traits(track.trace(r.edges, step, seed["bubble"]), r.traits)
    out = track.flag_low_confidence(track.rise_velocity(found)).select("track", "step", "bubble", "voxels", "dice", "rise_velocity", "low_confidence")
    return {"result": _rounded(out, dice=9, rise_velocity=4)}


@workload("E6")
def e6(spark, sf_dir, step: int = 5, **_) -> Tables:
    """Volume against time, with merges and splits."""
    r = run_of(spark, sf_dir)
    found = track.with_traits(track.trace_all(r.edges, step, bubbles=r.traits), r.traits)
    events = lifecycle.volume_events(found)
    out = events.where("event is not null").select("track", "step", "voxels", "change", "event")
    return {"result": _rounded(out, change=6), "scatter": explore.scatter(found, "step", "volume", color="dice"), "graph": lifecycle.graph_events(r.edges)}


@workload("E7")
def e7(spark, sf_dir, **_) -> Tables:
    """Scatterplot matrix and correlations of the growing, accelerating bubble: the first step's outermost."""
    r = run_of(spark, sf_dir)
    seed = r.traits.where("step = 0").orderBy("zc", "bubble").first()["bubble"]
    one = track.rise_velocity(track.with_traits(track.trace(r.edges, 0, seed), r.traits))
    names = ["step", "volume", "xc", "rise_velocity"]
    return {"result": _rounded(explore.correlations(one, names), r=6), "splom": explore.splom(one, names)}


@workload("E8")
def e8(spark, sf_dir, step: int = 6, **_) -> Tables:
    """All bubbles of a step followed and compared; births and ends."""
    r = run_of(spark, sf_dir, "shapes")
    tracks = track.with_traits(track.trace_all(r.edges, step, bubbles=r.traits), r.traits)
    return {"result": _rounded(explore.compare(tracks, r.field.select("step")), volume=4), "events": lifecycle.births_deaths(r.edges, r.traits)}


@workload("E9")
def e9(spark, sf_dir, **_) -> Tables:
    """Velocities of particles around extracted bubbles: as the rows have them, and with the motion that a scene sets."""
    r = run_of(spark, sf_dir)
    moved = density.density_field(density.histogram(P.planted_bed(spark, sf_dir, "rise", GRID, wakes=True), GRID), GRID)
    out, contrast = [], {}
    for name, field in (("as given", r.field), ("set", moved)):
        near = flow.around(r.voxels, field, GRID)
        out.append(near.groupBy("region").agg(F.count(F.lit(1)).alias("bubbles"), *[F.round(F.avg(c), 5).alias(c) for c in ("mean_rise", "up_share", "down_share")]).select(F.lit(name).alias("velocity"), "*"))
        contrast[name] = flow.wake_contrast(near)
    return {"result": reduce(DataFrame.unionByName, out), "contrast": contrast["set"]}


@workload("E10")
def e10(spark, sf_dir, sizes: tuple[int, ...] = (3, 4, 6), **_) -> Tables:
    """Larger supervoxels lose small bubbles: recall of the true bubbles by size of clusters, and blocks for comparison."""
    r = run_of(spark, sf_dir, "shapes")
    true = store(components.label(P.truth(spark, "shapes", GRID), GRID), "true")
    out = []
    for s in sizes:
        for how in ("supervoxels", "blocks"):
            labels = supervoxel.slic(r.field, GRID, (s, s, s))[0] if how == "supervoxels" else baselines.blocks(r.field, GRID, (s, s, s))
            bsf = similarity.bsf(labels, gaussian.fit_clusters(labels, r.field), r.target)
            hit = measures.bubble_recall(segment.by_similarity(bsf), true)
            out.append(hit.select(F.lit(s).alias("size"), F.lit(how).alias("partition"), (F.col("voxels") <= 14).alias("small"), "recalled"))
    rows = reduce(DataFrame.unionByName, out)
    return {"result": rows.groupBy("size", "partition", "small").agg(F.count(F.lit(1)).alias("bubbles"), F.count_if("recalled").alias("recalled"))}


@workload("E11")
def e11(spark, sf_dir, thresholds: tuple[float, ...] = (0.88, 0.9, 0.92, 0.94, 0.96), **_) -> Tables:
    """Bubbles at thresholds around 0.92, all in one pass."""
    bsf = run_of(spark, sf_dir).bsf
    found = segment.sweep(bsf, list(thresholds))
    # steps of different thresholds stand side by side as steps of their own
    place = found.select((F.col("step") + F.lit(1000) * F.array_position(F.array(*map(F.lit, thresholds)), F.col("threshold"))).cast("int").alias("step"), "voxel")
    what = traits.describe(components.label(place, GRID), GRID).where((F.col("voxels") >= LEAST) & ~F.col("is_freeboard"))
    per = what.select(F.element_at(F.array(*map(F.lit, thresholds)), F.floor(F.col("step") / 1000).cast("int")).alias("threshold"), "voxels")
    return {"result": per.groupBy("threshold").agg(F.count(F.lit(1)).alias("bubbles"), F.sum("voxels").alias("voxels")), "profile": segment.threshold_profile(bsf)}


#: An eighth of the bin counts of the published sweep on each axis.
BINS = ((8, 1, 8), (16, 2, 16), (16, 3, 16), (32, 8, 32))


@workload("E12")
def e12(spark, sf_dir, bins: tuple[tuple[int, int, int], ...] = BINS, **_) -> Tables:
    """Numbers of bins: bubbles found, and how well they cover the planted voxels."""
    out = []
    for n in bins:
        grid = bed_grid(n)
        hist = store(density.histogram(bed(spark, sf_dir, grid), grid), "histogram")
        goal = target.fit_target(density.density_field(hist.where("step = 0"), grid), void_box(grid), 0, grid=grid)
        found = components.label(segment.by_similarity(pipeline.of_histogram(hist, grid, goal).fields), grid)
        what = traits.describe(found, grid).where((F.col("voxels") >= LEAST) & ~F.col("is_freeboard"))
        per = found.join(what.select("step", "bubble"), ["step", "bubble"], "left_semi")
        count = what.agg(F.count(F.lit(1)).alias("bubbles"), F.round(F.sum("volume"), 3).alias("volume"))
        hit = _overall(measures.accuracy(per, P.truth(spark, "rise", grid)))
        out.append(count.crossJoin(F.broadcast(hit)).select(F.lit("x".join(map(str, n))).alias("bins"), "*"))  # one row each
    return {"result": reduce(DataFrame.unionByName, out)}


def _overall(accuracy: DataFrame) -> DataFrame:
    """hit, missed, extra, precision, recall, iou over all steps."""
    n = accuracy.agg(*[F.sum(c).alias(c) for c in ("hit", "missed", "extra")])
    h, m, e = F.col("hit"), F.col("missed"), F.col("extra")
    ratio = lambda b: F.round(F.when(b > 0, h / b), 6)
    return n.select("*", ratio(h + e).alias("precision"), ratio(h + m).alias("recall"), ratio(h + m + e).alias("iou"))


def order_grid(n: tuple[int, int, int]) -> GridSpec:
    return GridSpec((900.0, 0.0, 0.0), (500000.0, 5.0, 50.0), n)


#: Bins for the second bed: all are reported, none is picked.
ORDER_BINS = ((12, 3, 12), (16, 4, 16), (20, 5, 20), (24, 6, 24))
#: The published density threshold.
FIXED = 12.0


@workload("E13")
def e13(spark, sf_dir, bins: tuple[tuple[int, int, int], ...] = ORDER_BINS, **_) -> Tables:
    """Density thresholds, the published one and one tuned on the first bed, and the similarity, on two beds of different density."""
    orders = P.order_bed(spark, sf_dir).withColumn("l_suppkey", F.floor(F.col("x")).cast("long")).drop("step")
    cases = [("lines", GRID, None), *[("orders", order_grid(n), orders) for n in bins]]
    out, tuned = [], None
    for name, grid, source in cases:
        hist = store(density.histogram(P.planted_bed(spark, sf_dir, "rise", grid, source=source), grid), "histogram")
        first = density.density_field(hist.where("step = 0"), grid)
        goal = target.fit_target(first, void_box(grid), 0, grid=grid)
        if tuned is None:  # what separates the first bed: halfway between target and bed
            row = first.where((F.col("ix") + 0.5) / grid.n[0] < P.BED_TOP).agg(F.sum("density"), F.count(F.lit(1))).first()
            tuned = (goal.mu + row[0] / row[1]) / 2
        made = pipeline.of_histogram(hist, grid, goal)
        below = lambda df, grid=grid: df.where(F.col("voxel") < int(-(-P.BED_TOP * grid.n[0] // 1) if (int(P.BED_TOP * grid.n[0]) + 0.5) / grid.n[0] < P.BED_TOP else int(P.BED_TOP * grid.n[0])) * grid.n[1] * grid.n[2])
        for how, found in (("similarity", segment.by_similarity(made.fields)), ("density tuned on lines", baselines.density_threshold(made.density, tuned)), ("density 12", baselines.density_threshold(made.density, FIXED))):
            hit = _overall(measures.accuracy(below(found), P.truth(spark, "rise", grid)))
            out.append(hit.select(F.lit(name).alias("case"), F.lit("x".join(map(str, grid.n))).alias("bins"), F.lit(how).alias("method"), "hit", "missed", "extra", "precision", "recall", "iou"))
    return {"result": reduce(DataFrame.unionByName, out)}


@workload("E14")
def e14(spark, sf_dir, stride: int = 2, grid: GridSpec | None = None, **_) -> Tables:
    """A run in situ: seconds, rows and share of producing the particles of each stage; bytes of particles and of fields."""
    grid = grid or GRID
    particles = bed(spark, sf_dir, grid)
    goal = fitted(spark, particles, grid)
    read = pipeline.accessed(particles, stride=stride)
    base = measures.seconds(read)
    held: dict[str, DataFrame] = {}

    def kept(name: str, make: Callable[[], DataFrame]) -> tuple:
        t = time.perf_counter()
        held[name] = store(make(), name)
        return name, time.perf_counter() - t

    rows = [
        kept("density and velocity", lambda: density.histogram(read, grid)),
        kept("supervoxels and similarity", lambda: pipeline.of_histogram(held["density and velocity"], grid, goal).fields),
    ]
    total = sum(x for _, x in rows)
    counts = {k: df.count() for k, df in held.items()}
    result = spark.createDataFrame([(k, t, t / base, counts[k]) for k, t in rows] + [("all", total, total / base, counts["supervoxels and similarity"])], "stage string, seconds double, share_of_producing double, rows long")
    path = fresh_path(spark, "run")
    sizes = measures.io_times(spark, {"raw": particles, "fields": store_fields.pack(held["supervoxels and similarity"], grid, ["similarity", "rise_velocity"])}, path)
    stored = measures.storage(spark, f"{path}/raw", f"{path}/fields", particles.count(), P.STEPS["rise"], stride, 5)
    return {"result": result, "io": sizes, "storage": stored}


@workload("E15")
def e15(spark, sf_dir, parts: tuple[int, ...] = (1, 2, 4), **_) -> Tables:
    """Seconds of the clustering by number of tasks at once; labels are the same however many there are. Cores are swept by bench.py."""
    grid = GRID
    field = store(density.density_field(density.histogram(bed(spark, sf_dir, grid), grid), grid), "field")
    rows = []
    for p in parts:
        t = time.perf_counter()
        labels = store(supervoxel.slic(field.repartition(p, "step"), grid)[0], "labels")
        rows.append((p, time.perf_counter() - t, labels.agg(F.sum(F.xxhash64("step", "voxel", "cluster").cast("decimal(38,0)"))).first()[0]))
    return {"result": spark.createDataFrame(rows, "tasks int, seconds double, labels decimal(38,0)")}


@workload("E16")
def e16(spark, sf_dir, **_) -> Tables:
    """In situ against writing raw particles, reading them back and computing then: the fields are the same, time isn't."""
    grid = GRID
    particles = bed(spark, sf_dir, grid)
    goal = fitted(spark, particles, grid)
    path = fresh_path(spark, "raw")

    def timed(make: Callable[[], DataFrame]) -> tuple[DataFrame, float]:
        t = time.perf_counter()
        return store(make(), "fields"), time.perf_counter() - t

    now, seconds = timed(lambda: pipeline.in_situ(particles, grid, goal).fields)
    write = measures.io_times(spark, {"raw": particles}, path).first()["seconds"]
    read = measures.seconds(spark.read.parquet(f"{path}/raw"))
    after, later = timed(lambda: pipeline.from_raw(f"{path}/raw", grid, goal, spark).fields)
    spread, parallel = timed(lambda: pipeline.from_raw(f"{path}/raw", grid, goal, spark, parallelism=8).fields)
    differ = now.exceptAll(after).count() + now.exceptAll(spread).count()
    return {"result": spark.createDataFrame([("in situ", seconds, 0), ("post hoc: write", write, 0), ("post hoc: read", read, 0), ("post hoc: compute", later, differ), ("post hoc: compute in parallel", parallel, differ)], "stage string, seconds double, rows_that_differ long")}


@workload("E17")
def e17(spark, sf_dir, stride: int = 2, checkpoint: int = 5, **_) -> Tables:
    """Seconds and bytes of storing raw particles, checkpoints and fields."""
    grid = GRID
    particles = store(bed(spark, sf_dir, grid), "particles")
    goal = fitted(spark, particles, grid)
    fields = pipeline.in_situ(particles, grid, goal, stride=stride).fields
    outputs = {"raw": pipeline.accessed(particles, stride=stride), "checkpoint": baselines.strided(particles, checkpoint), "fields": store_fields.pack(fields, grid, ["similarity", "rise_velocity"])}
    return {"result": measures.io_times(spark, outputs, fresh_path(spark, "io"))}


@workload("E18")
def e18(spark, sf_dir, **_) -> Tables:
    """Layers of the scene around the largest bubble of the first step."""
    r = run_of(spark, sf_dir)
    seed = r.traits.where("step = 0").orderBy(F.desc("voxels"), "bubble").first()["bubble"]
    scene = explore.scene(r.voxels, track.trace(r.edges, 0, seed), r.bsf)
    return {"result": scene.groupBy("layer", "step").agg(F.count(F.lit(1)).alias("voxels")), "scene": scene}


@workload("E19")
def e19(spark, sf_dir, **_) -> Tables:
    """Boxes link a hollow bubble with the one inside it; true overlap doesn't. On extracted bubbles and on the planted ones."""
    r = run_of(spark, sf_dir, "shapes")
    planted = components.label(P.truth(spark, "shapes", GRID), GRID)
    out = []
    for name, voxels in (("extracted", r.voxels), ("planted", planted)):
        edges = store(track.overlaps(voxels), "edges")
        boxes = store(baselines.box_overlaps(traits.describe(voxels, GRID)), "boxes")
        false = boxes.join(edges.select("step", "src", "dst"), ["step", "src", "dst"], "left_anti")
        out += [df.agg(F.count(F.lit(1)).alias("n")).select(F.lit(name).alias("bubbles"), F.lit(k).alias("links"), "n") for k, df in (("boxes", boxes), ("overlap", edges), ("boxes only", false))]
    return {"result": reduce(DataFrame.unionByName, out)}


@workload("E20")
def e20(spark, sf_dir, rounds: int = 5, **_) -> Tables:
    """Distance computations of local and of global clustering, per round, all steps together."""
    r = run_of(spark, sf_dir)
    k = 1
    for n in supervoxel.lattice(GRID, (3, 3, 3)):
        k *= n
    everywhere = baselines.kmeans(r.field, GRID, k, max_iter=rounds)[1]
    side = lambda df, name: df.where(F.col("iteration") <= rounds).groupBy("iteration").agg(F.sum("distances").alias("distances")).select(F.lit(name).alias("method"), "iteration", "distances")
    return {"result": side(r.report, "local").unionByName(side(everywhere, "global"))}


def images_of(spark: SparkSession, sf_dir: str, path: str) -> str:
    """Writes the image database of a run below `path` and returns where."""
    r = run_of(spark, sf_dir)
    imagedb.write(imagedb.render(r.voxels, r.bsf, GRID), r.traits, path)
    return path
