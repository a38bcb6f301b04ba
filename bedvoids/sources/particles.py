"""Particles from the given tables, and beds with planted voids whose true voxels are known."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions.grid import GridSpec, bed_grid
from .shared import table

BED_TOP = 0.85
KEEP = 8


def bed_columns() -> dict[str, Column]:
    """Position and velocity of a lineitem row. Discrete columns get exact dithers so that bins don't alias."""
    y = F.lit(10.0) - F.abs(F.lit(10.0) - F.abs(F.round(F.col("l_discount") * 100) - F.lit(0.5) + F.col("l_partkey") % 64 / F.lit(64.0)))
    return {
        "x": F.col("l_extendedprice"),
        "y": y,
        "z": F.col("l_quantity") - F.lit(1.0) + F.col("l_orderkey") % 64 / F.lit(64.0),
        "vx": F.round(F.col("l_tax") * 100) - F.lit(4.0),
        "vy": (F.col("l_linenumber") % 3 - 1).cast("double"),
        "vz": F.lit(0.0),
    }


_COLUMNS = ["l_orderkey", "l_partkey", "l_suppkey", "l_linenumber", "l_extendedprice", "l_quantity", "l_discount", "l_tax"]


def slice_by_date(spark: SparkSession, sf_dir: str, period: str = "year") -> DataFrame:
    """Rows of lineitem, one step for each year or quarter."""
    step = F.year("l_shipdate") - 1995
    if period == "quarter":
        step = step * 4 + F.quarter("l_shipdate") - 1
    return table(spark, sf_dir, "lineitem").select(step.cast("int").alias("step"), *[c.alias(k) for k, c in bed_columns().items()])


def order_bed(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Orders as particles: a bed of other density."""
    priority = F.substring("o_orderpriority", 1, 1).cast("double")
    return table(spark, sf_dir, "orders").select(
        (F.year("o_orderdate") - 1995).cast("int").alias("step"),
        F.col("o_totalprice").alias("x"),
        (priority - F.lit(1.0) + F.col("o_orderkey") % 64 / F.lit(64.0)).alias("y"),
        (F.col("o_custkey") % 50 + F.col("o_orderkey") % 64 / F.lit(64.0)).alias("z"),
        F.when(F.col("o_orderstatus") == "F", 1.0).when(F.col("o_orderstatus") == "P", -1.0).otherwise(0.0).alias("vx"),
        F.lit(0.0).alias("vy"),
        F.lit(0.0).alias("vz"),
    )


EVENT_VELOCITY = {"click": 2.0, "view": 1.0, "signup": 0.0, "purchase": -1.0, "error": -2.0}


def event_columns(cap: float | None = 200.0) -> dict[str, Column]:
    speed = F.create_map(*[F.lit(v) for kv in EVENT_VELOCITY.items() for v in kv])
    return {
        "step": F.datediff(F.to_date("ts"), F.lit("2024-01-01").cast("date")).cast("int"),
        "x": F.least(F.col("value"), F.lit(cap)) if cap is not None else F.col("value"),
        "y": F.hour("ts").cast("double"),
        "z": F.col("user_id").cast("double"),
        "vx": F.element_at(speed, F.col("event_type")),
        "vy": F.lit(0.0),
        "vz": F.lit(0.0),
    }


def event_bed(spark: SparkSession, sf_dir: str, cap: float | None = 200.0) -> DataFrame:
    return table(spark, sf_dir, "events").select(*[c.alias(k) for k, c in event_columns(cap).items()])


def event_grid(n: tuple[int, int, int] = (20, 6, 15)) -> GridSpec:
    return GridSpec((0.0, 0.0, 0.0), (200.0, 24.0, 150.0), n)


def vector_bed(spark: SparkSession, sf_dir: str) -> DataFrame:
    v = lambda i: F.col("embedding")[i].cast("double")
    return table(spark, sf_dir, "embeddings").select(F.lit(0).alias("step"), v(0).alias("x"), v(1).alias("y"), v(2).alias("z"), v(3).alias("vx"), F.col("label"))


def ensemble_bed(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The dated bed with a member of an ensemble: the region of the customer who ordered."""
    lines = table(spark, sf_dir, "lineitem").select((F.year("l_shipdate") - 1995).cast("int").alias("step"), "l_orderkey", *[c.alias(k) for k, c in bed_columns().items()])
    orders = table(spark, sf_dir, "orders", ["o_orderkey", "o_custkey"])
    customers = table(spark, sf_dir, "customer", ["c_custkey", "c_nationkey"])
    nations = table(spark, sf_dir, "nation", ["n_nationkey", "n_regionkey"])
    regions = table(spark, sf_dir, "region", ["r_regionkey", "r_name"])
    places = nations.join(F.broadcast(regions), F.col("n_regionkey") == F.col("r_regionkey"))  # 25 nations, 5 regions
    out = lines.join(orders, F.col("l_orderkey") == F.col("o_orderkey")).join(customers, F.col("o_custkey") == F.col("c_custkey")).join(F.broadcast(places), F.col("c_nationkey") == F.col("n_nationkey"))
    return out.select("step", *bed_columns(), F.col("r_name").alias("member"))


def material_bed(spark: SparkSession, sf_dir: str) -> DataFrame:
    """The dated bed with material, diameter and supplier's nation of each particle."""
    lines = table(spark, sf_dir, "lineitem").select((F.year("l_shipdate") - 1995).cast("int").alias("step"), "l_partkey", "l_suppkey", *[c.alias(k) for k, c in bed_columns().items()])
    parts = table(spark, sf_dir, "part", ["p_partkey", "p_type", "p_size"])
    suppliers = table(spark, sf_dir, "supplier", ["s_suppkey", "s_nationkey"])
    out = lines.join(parts, F.col("l_partkey") == F.col("p_partkey")).join(suppliers, F.col("l_suppkey") == F.col("s_suppkey"))
    return out.select("step", *bed_columns(), F.col("p_type").alias("material"), F.col("p_size").alias("diameter"), F.col("s_nationkey").alias("origin"))


# Scenes: centre (x, y, z) and radii at step t, in shares of the bed; life as first and last step.
SCENES: dict[str, list] = {
    "rise": [
        ("grow", 0, 10, lambda t: (0.14 + 0.03 * t + 0.002 * t * t, 0.5, 0.15, 0.085 + 0.004 * t, 0.30, 0.085 + 0.004 * t)),
        ("low", 0, 10, lambda t: (0.12 + 0.06 * min(t, 5) + 0.025 * max(0, t - 5), 0.5, 0.48, 0.08, 0.30, 0.08)),
        ("high", 0, 10, lambda t: (0.42 + 0.025 * t, 0.5, 0.48, 0.08, 0.30, 0.08)),
        ("split_left", 0, 10, lambda t: (0.12 + 0.045 * t, 0.5, 0.79 - 0.017 * max(0, t - 2), 0.08, 0.30, 0.08)),
        ("split_right", 0, 10, lambda t: (0.12 + 0.045 * t, 0.5, min(0.81 + 0.012 * max(0, t - 2), 0.92), 0.08, 0.30, 0.08)),
    ],
    "shapes": [
        ("small", 0, 11, lambda t: (0.20 + 0.03 * t, 0.5, 0.10, 0.06, 0.25, 0.06)),
        ("late", 4, 8, lambda t: (0.25 + 0.04 * t, 0.5, 0.35, 0.085, 0.30, 0.085)),
        ("hugger", 0, 11, lambda t: (0.40, 0.5, 0.75, 0.16, 0.40, 0.16)),
        ("pearl", 0, 11, lambda t: (0.48, 0.5, 0.75, 0.05, 0.25, 0.05)),
    ],
}
#: Taken out of a void again: name -> ellipsoid.
CUTS = {"hugger": (0.47, 0.5, 0.75, 0.12, 0.60, 0.10)}
STEPS = {"rise": 11, "shapes": 12}
_VOID = "void string, step int, x0 double, y0 double, z0 double, rx double, ry double, rz double, cx double, cy double, cz double, crx double, cry double, crz double"


def void_rows(scene: str, steps: int | None = None) -> list[tuple]:
    """One row for each void and step; where nothing is cut out, the cut's radii lie far away."""
    none = (9.0, 9.0, 9.0, 1.0, 1.0, 1.0)
    return [(name, t, *(round(float(v), 9) for v in at(t)), *CUTS.get(name, none)) for name, first, last, at in SCENES[scene] for t in range(first, min(last, (steps or STEPS[scene]) - 1) + 1)]


def _ball(x: str, y: str, z: str, rx: str, ry: str, rz: str, grid: GridSpec) -> Column:
    total = None
    for i, (c, r) in enumerate(((x, rx), (y, ry), (z, rz))):
        d = ((F.col(("ix", "iy", "iz")[i]) + F.lit(0.5)) / F.lit(float(grid.n[i])) - F.col(c)) / F.col(r)
        total = d * d if total is None else total + d * d
    return total


def truth(spark: SparkSession, scene: str = "rise", grid: GridSpec | None = None) -> DataFrame:
    """step, voxel, ix, iy, iz of every planted void voxel below the top of the bed."""
    grid = grid or bed_grid()
    voids = spark.createDataFrame(void_rows(scene), _VOID)
    lattice = spark.range(grid.voxels).select(F.col("id").alias("voxel"), *[c.alias(k) for k, c in grid.indices("id").items()])
    lattice = lattice.where((F.col("ix") + F.lit(0.5)) / F.lit(float(grid.n[0])) < F.lit(BED_TOP))
    inside = (_ball("x0", "y0", "z0", "rx", "ry", "rz", grid) <= 1) & (_ball("cx", "cy", "cz", "crx", "cry", "crz", grid) > 1)
    return lattice.join(F.broadcast(voids), inside).select("step", "voxel", "ix", "iy", "iz").distinct()  # some dozen voids


def planted_bed(spark: SparkSession, sf_dir: str, scene: str = "rise", grid: GridSpec | None = None, keep: int = KEEP, source: DataFrame | None = None, steps: int | None = None, wakes: bool = False) -> DataFrame:
    """The rows of lineitem at each step, without most of those in a void and all above the bed.

    Removal is by voxel, so the true voxels are exact. `wakes` sets the velocity beside, below and above voids.
    """
    grid = grid or bed_grid()
    rows = source if source is not None else table(spark, sf_dir, "lineitem", _COLUMNS).select("l_suppkey", *[c.alias(k) for k, c in bed_columns().items()])
    steps = steps or STEPS[scene]
    gone = truth(spark, scene, grid).groupBy("voxel").agg(F.collect_set("step").alias("gone"))
    at = rows.where(grid.inside()).select("*", grid.voxel(*[grid.bins()[c] for c in ("ix", "iy", "iz")]).alias("voxel"))
    at = at.where((F.floor(F.col("voxel") / (grid.n[1] * grid.n[2])) + F.lit(0.5)) / F.lit(float(grid.n[0])) < F.lit(BED_TOP))
    # as many rows as voxels that ever are in a void
    at = at.join(F.broadcast(gone), "voxel", "left")
    all_steps = F.sequence(F.lit(0), F.lit(steps - 1))
    stays = F.when(F.col("gone").isNull() | (F.col("l_suppkey") % keep == 0), all_steps).otherwise(F.array_except(all_steps, F.col("gone")))
    out = at.select(F.explode(stays).alias("step"), "x", "y", "z", "vx", "vy", "vz", "voxel")
    if wakes:
        out = out.join(F.broadcast(motion(spark, scene, grid)), ["step", "voxel"], "left").withColumn("vx", F.coalesce("v_set", "vx"))
    return out.select("step", "x", "y", "z", "vx", "vy", "vz")


def void_voxels() -> type:
    """A table function of (step, centre, radii, cut's centre and radii, bins): the voxels of a void; for small inputs."""
    from pyspark.sql.functions import udtf

    @udtf(returnType="step int, voxel bigint, ix int, iy int, iz int")
    class VoidVoxels:
        def eval(self, step: int, x0: float, y0: float, z0: float, rx: float, ry: float, rz: float, cx: float, cy: float, cz: float, crx: float, cry: float, crz: float, nx: int, ny: int, nz: int):
            def ball(ix: int, iy: int, iz: int, c: tuple, r: tuple) -> float:
                a, b, g = (((i + 0.5) / float(n) - p) / q for i, n, p, q in zip((ix, iy, iz), (nx, ny, nz), c, r, strict=True))
                return a * a + b * b + g * g

            for ix in range(nx):
                if (ix + 0.5) / nx < BED_TOP:
                    for iy in range(ny):
                        for iz in range(nz):
                            if ball(ix, iy, iz, (x0, y0, z0), (rx, ry, rz)) <= 1 and ball(ix, iy, iz, (cx, cy, cz), (crx, cry, crz)) > 1:
                                yield step, (ix * ny + iy) * nz + iz, ix, iy, iz

    return VoidVoxels


def motion(spark: SparkSession, scene: str, grid: GridSpec) -> DataFrame:
    """step, voxel, v_set: velocity of the particles beside (sinking), right below (fast) and right above voids."""
    voids = spark.createDataFrame(void_rows(scene), _VOID)
    lattice = spark.range(grid.voxels).select(F.col("id").alias("voxel"), *[c.alias(k) for k, c in grid.indices("id").items()])
    dx = (F.col("ix") + F.lit(0.5)) / F.lit(float(grid.n[0])) - F.col("x0")
    dz = F.abs((F.col("iz") + F.lit(0.5)) / F.lit(float(grid.n[2])) - F.col("z0"))
    wake = (dx >= -F.col("rx") - 0.1) & (dx < -F.col("rx")) & (dz <= F.col("rz"))
    above = (dx > F.col("rx")) & (dx <= F.col("rx") + 0.1) & (dz <= F.col("rz"))
    side = (F.abs(dx) <= F.col("rx")) & (dz > F.col("rz")) & (dz <= F.col("rz") + 0.1)
    speed = F.when(wake, 3.0).when(above, 1.0).when(side, -2.0)
    return lattice.join(F.broadcast(voids), speed.isNotNull()).groupBy("step", "voxel").agg(F.max(speed).alias("v_set"))
