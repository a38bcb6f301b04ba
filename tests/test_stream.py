import pytest
from pyspark.sql import functions as F

from bedvoids.functions.grid import Target, bed_grid
from bedvoids.operators import components, density, relational, track
from bedvoids.plans import pipeline
from bedvoids.sources import particles as P
from bedvoids.sources.shared import table
from bedvoids.streaming import stream as S


def rows(df):
    return sorted(map(tuple, df.collect()), key=lambda r: tuple((v is None, str(v)) for v in r))


@pytest.fixture(scope="module")
def days(spark, sf, tmp_path_factory):
    """Events as a file for each day, oldest first, and then one of a far later day that closes all windows."""
    path = str(tmp_path_factory.mktemp("events"))
    e = table(spark, sf, "events").where("ts < timestamp_ntz'2024-01-09'").withColumn("day", F.to_date("ts"))
    for d in [r.day for r in e.select("day").distinct().orderBy("day").collect()]:
        e.where(F.col("day") == F.lit(d)).drop("day").coalesce(1).write.mode("append").parquet(path)
    last = e.drop("day").limit(1).withColumn("ts", F.expr("timestamp_ntz'2024-03-01 00:00:00'"))
    last.coalesce(1).write.mode("append").parquet(path)
    return path, e.drop("day").withColumn("ts", F.col("ts").cast("timestamp"))


def run(spark, df, tmp_path, name):
    q = S.finished(df, str(tmp_path / name), str(tmp_path / f"{name}-state"))
    q.awaitTermination()
    return spark.read.parquet(str(tmp_path / name))


@pytest.mark.parametrize("kind", ["tumbling", "sliding", "session"])
def test_windows_equal_batch(spark, days, tmp_path, kind):
    path, batch = days
    got = run(spark, S.event_windows(S.events(spark, path, 100), kind), tmp_path, kind).where("start < timestamp'2024-02-01'")
    keys = {"tumbling": [F.window("ts", "1 day").alias("w")], "sliding": [F.window("ts", "1 day", "6 hours").alias("w")], "session": [F.session_window("ts", "30 minutes").alias("w"), "user_id"]}[kind]
    want = batch.groupBy(*keys).agg(F.count(F.lit(1)).alias("n")).select("w.start", "w.end", "n")
    assert rows(got.select("start", "end", "n")) == rows(want)


def test_histogram_equals_batch_and_restarts(spark, days, tmp_path):
    path, batch = days
    grid = P.event_grid()
    particles = lambda df: df.select("ts", *[c.alias(k) for k, c in P.event_columns().items()])
    for _ in range(2):  # the second run finds nothing new
        got = run(spark, S.histogram_stream(particles(S.events(spark, path, 2)), grid), tmp_path, "hist")
    want = density.histogram(particles(batch).drop("ts"), grid)
    first = batch.agg(F.min(F.col("ts").cast("long") / 86400)).first()[0]
    assert rows(got.where("step < 19780").select((F.col("step") - 19723).alias("step"), "ix", "iy", "iz", "n", "sum_vx")) == rows(want)
    assert first >= 19723


def test_late_rows_are_dropped(spark, sf, tmp_path):
    e = table(spark, sf, "events").where("ts < timestamp_ntz'2024-01-13'").withColumn("late", F.col("event_id") % 20 == 0).withColumn("sent", F.to_date("ts") + F.when(F.col("late"), 4).otherwise(0))
    path = str(tmp_path / "in")
    for d in [r.sent for r in e.select("sent").distinct().orderBy("sent").collect()]:
        e.where(F.col("sent") == F.lit(d)).drop("sent", "late").coalesce(1).write.mode("append").parquet(path)
    got = run(spark, S.event_windows(S.events(spark, path, 1), "tumbling", late="1 day"), tmp_path, "late")
    on_time = e.where("not late").groupBy(F.to_date("ts").alias("d")).agg(F.count(F.lit(1)).alias("n"))
    want = {r.d: r.n for r in on_time.collect()}
    seen = {r.start.date(): r.n for r in got.collect()}
    assert seen and all(want[d] == n for d, n in seen.items() if d.day < 9)


def test_resent_rows_count_once(spark, days, tmp_path):
    path, batch = days
    twice = S.events(spark, path, 100).union(S.events(spark, path, 100))
    got = run(spark, S.once_each(twice), tmp_path, "once")
    assert got.select("event_id").distinct().count() == got.count() == batch.select("event_id").distinct().count()


def test_fields_step_by_step(spark, tmp_path):
    grid = bed_grid((12, 4, 12))
    particles = P.planted_bed(spark, "/root/testdata/sf0.001", "rise", grid, steps=3)
    goal = Target(0.3, 0.5, 9)
    S.batches(particles, str(tmp_path / "in"))
    source = spark.readStream.schema(particles.schema).option("maxFilesPerTrigger", 1).parquet(str(tmp_path / "in"))
    S.in_situ_stream(source, grid, goal, str(tmp_path / "out"), str(tmp_path / "state")).awaitTermination()
    got = spark.read.parquet(str(tmp_path / "out")).select("step", "voxel", F.round("similarity", 9))
    want = pipeline.in_situ(particles, grid, goal).fields.select("step", "voxel", F.round("similarity", 9))
    assert rows(got) == rows(want)


def test_online_edges(spark, tmp_path):
    grid = bed_grid()
    labels = components.label(P.truth(spark, "rise", grid).where("step < 4"), grid).withColumn("tile", (F.col("voxel") % 5).cast("int"))
    S.batches(labels, str(tmp_path / "in"))
    source = spark.readStream.schema(labels.schema).option("maxFilesPerTrigger", 1).parquet(str(tmp_path / "in"))
    got = run(spark, S.online_edges(source), tmp_path, "edges").groupBy("step", "src", "dst").agg(F.sum("inter").alias("inter"))
    assert rows(got) == rows(track.overlaps(labels).select("step", "src", "dst", "inter"))


def test_joins_of_streams(spark, days, tmp_path):
    path, batch = days
    kinds = spark.createDataFrame([("click", 1), ("view", 2)], "event_type string, code int")
    got = run(spark, S.with_material(S.events(spark, path, 100), kinds, "event_type"), tmp_path, "static")
    assert got.where("code is not null").count() >= batch.where("event_type in ('click', 'view')").count()
    a, b = S.events(spark, path, 100).select("event_id", "ts"), S.events(spark, path, 100).select("event_id", "ts", "value")
    both = S.with_velocities(a, b).select("p.event_id", "v.value")
    assert run(spark, both, tmp_path, "both").count() >= batch.count()


def test_accessed_steps(spark):
    p = spark.range(40).select(F.col("id").cast("int").alias("step"))
    assert [r.step for r in pipeline.accessed(p, 12, 20, 10).orderBy("step").collect()] == [12, 22]
    assert pipeline.accessed(p, stride=10).count() == 4


def test_general_operators(spark):
    left = spark.createDataFrame([(1, 5), (1, 12), (2, 3)], "k int, t int")
    right = spark.createDataFrame([(1, 4, "a"), (1, 10, "b"), (2, 9, "c")], "k int, t int, v string")
    assert rows(relational.asof_join(left, right, "t", ["k"]).select("k", "t", "v")) == [(1, 12, "b"), (1, 5, "a"), (2, 3, None)]
    lattice = spark.range(4).select(F.col("id").cast("int").alias("k"))
    assert relational.densify(spark.createDataFrame([(1, 2.0)], "k int, v double"), ["k"], lattice, {"v": 0.0}).agg(F.sum("v")).first()[0] == 2.0
    a = spark.createDataFrame([(0.0, 0.0), (5.0, 5.0)], "x double, y double")
    b = spark.createDataFrame([(0.5, 0.9), (1.1, 0.0), (5.0, 4.0)], "p double, q double")
    assert relational.bucketed_range_join(a, b, ["x", "y"], ["p", "q"], [1.0, 1.0], [2.0, 2.0]).count() == 2
    assert relational.cube_counts(left, ["k"]).count() == 3 and relational.rollup_counts(left, ["k"]).count() == 3
    assert relational.top_k(left.withColumnRenamed("k", "bubble"), "t", 1).first().t == 12
