"""Headline queries at $BENCH_SF_DIR on local[$BENCH_CPUS]; prints one line of JSON."""

from __future__ import annotations

import json
import os
import time

SF_DIR = os.environ.get("BENCH_SF_DIR", "/root/testdata/sf0.1")
CPUS = os.environ.get("BENCH_CPUS", "8")


def supervoxel_seconds(n: tuple[int, int, int]) -> float:
    """Clustering one field of counts of that many bins, on one core."""
    import numpy as np

    from bedvoids.operators.supervoxel import cluster_arrays

    field = np.random.default_rng(1).poisson(16, n)
    t = time.perf_counter()
    cluster_arrays(field, (3, 3, 3), 0.3, 20)
    return round(time.perf_counter() - t, 2)


def main() -> None:
    from pyspark.sql import SparkSession
    from pyspark.sql import functions as F

    from bedvoids.functions.grid import bed_grid
    from bedvoids.operators import density, segment, target
    from bedvoids.plans import pipeline, workloads
    from bedvoids.sources.shared import bytes_of, fresh_path, importable, store

    spark = (
        SparkSession.builder.master(f"local[{CPUS}]")
        .config("spark.sql.shuffle.partitions", CPUS)
        .config("spark.sql.session.timeZone", "UTC")
        .config("spark.driver.memory", "8g")
        .config("spark.ui.enabled", "false")
        .config("spark.ui.showConsoleProgress", "false")
        .getOrCreate()
    )
    spark.sparkContext.setLogLevel("ERROR")
    importable(spark)
    took: dict[str, float] = {}

    def timed(name: str, f):
        t = time.perf_counter()
        out = f()
        took[name] = round(time.perf_counter() - t, 3)
        return out

    def run(df):
        df.write.format("noop").mode("overwrite").save()

    def in_situ(n: tuple[int, int, int], steps: int, tag: str) -> dict[str, float]:
        """Seconds of the stages of a run, as the published tables name them."""
        grid = bed_grid(n)
        particles = workloads.bed(spark, SF_DIR, grid, steps=steps)
        goal = workloads.fitted(spark, particles, grid)
        made = {}
        timed(f"produce_particles{tag}", lambda: run(particles))
        made["hist"] = timed(f"density_and_velocity{tag}", lambda: store(density.histogram(particles, grid), "hist"))
        made["fields"] = timed(f"supervoxels_and_similarity{tag}", lambda: store(pipeline.of_histogram(made["hist"], grid, goal).fields, "fields"))
        return {"grid": grid, "particles": particles, "goal": goal, **made}

    steps = 10
    run(workloads.bed(spark, SF_DIR, bed_grid((64, 8, 64)), steps=1).limit(1000))  # first use of the session
    in_situ((24, 6, 24), 1, "_first")
    made = in_situ((64, 8, 64), steps, "")
    grid, bsf = made["grid"], made["fields"]
    field = pipeline.of_histogram(made["hist"], grid, made["goal"]).density
    timed("bubbles_and_tracks", lambda: run(pipeline.post_hoc(bsf, grid, min_voxels=8).tracks))
    timed("target", lambda: target.fit_target(field, workloads.void_box(grid), 0))
    timed("segment", lambda: run(segment.by_similarity(bsf)))
    timed("threshold_sweep", lambda: run(segment.sweep(bsf, [0.88, 0.9, 0.92, 0.94, 0.96]).groupBy("threshold", "step").agg(F.count(F.lit(1)))))
    published = in_situ((128, 16, 128), 8, "_128x16x128")
    raw, stored = f"{fresh_path(spark, 'bench')}/raw", f"{fresh_path(spark, 'bench')}/fields"
    published["particles"].write.parquet(raw)
    published["fields"].select("step", F.col("similarity").cast("float"), F.col("rise_velocity").cast("float")).write.parquet(stored)
    n_raw = published["particles"].count()
    storage = {"raw_bytes_per_particle": round(bytes_of(spark, raw) / n_raw, 1), "field_share_of_raw": round(bytes_of(spark, stored) / bytes_of(spark, raw), 4)}
    one_core = supervoxel_seconds((128, 16, 128))
    try:
        from bedvoids.llm import queries as llm
    except ImportError:
        llm = None
    if llm:
        for name, f in llm.QUERIES.items():
            timed(name, lambda f=f: run(f(spark, SF_DIR)))
    total = took["density_and_velocity"] + took["supervoxels_and_similarity"]
    rows = made["particles"].count()
    more = {"particles": rows, "particles_per_second": round(rows / total), "seconds_per_step": round(total / steps, 3), "seconds_per_step_128x16x128": round((took["density_and_velocity_128x16x128"] + took["supervoxels_and_similarity_128x16x128"]) / 8, 3), "supervoxels_of_a_step_128x16x128_on_one_core": one_core, "share_of_producing": round(total / took["produce_particles"], 2), **storage}
    print(json.dumps({"metric": f"in situ seconds for {steps} steps (density, supervoxels, similarity)", "value": round(total, 3), "unit": "sec", "queries": took, "sf": SF_DIR.rstrip("/").rsplit("sf", 1)[-1], **more}))
    spark.stop()


if __name__ == "__main__":
    main()
