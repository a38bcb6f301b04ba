"""Tables in, intermediate tables out: what every executor sees and no lost executor takes along."""

from __future__ import annotations

import atexit
import os
import tempfile
import uuid
from collections.abc import Iterator
from contextlib import contextmanager
from pathlib import Path
from urllib.parse import unquote

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

_OWN: list[str] = []
#: Paths made inside each `scratch` that is open.
_SCRATCH: list[list[str]] = []


def importable(spark: SparkSession) -> None:
    """Lets Python workers that share this machine's files import this package, wherever the driver was started.

    On a cluster whose executors don't have it, submit it with --py-files.
    """
    root = str(Path(__file__).resolve().parents[2])
    env = spark.sparkContext.environment
    have = env.get("PYTHONPATH", "")
    if root not in have.split(os.pathsep):
        env["PYTHONPATH"] = os.pathsep.join(filter(None, (have, root)))


def table(spark: SparkSession, sf_dir: str, name: str, cols: list[str] | None = None, where: Column | None = None) -> DataFrame:
    df = spark.read.parquet(f"{sf_dir}/{name}.parquet")
    df = df.where(where) if where is not None else df
    return df.select(*cols) if cols else df


def shared_dir(spark: SparkSession) -> str:
    """The folder in spark.checkpoint.dir; a temporary one only where it is unset (local tests)."""
    place = spark.conf.get("spark.checkpoint.dir", None) or spark.sparkContext.getConf().get("spark.checkpoint.dir")
    if not place:
        if not spark.sparkContext.master.startswith("local["):
            raise ValueError("set spark.checkpoint.dir to a folder that all executors share")
        if not _OWN:
            _OWN.append(tempfile.mkdtemp(prefix="bedvoids-"))
        place = _OWN[0]
    return place.rstrip("/")


def drop(spark: SparkSession, path: str) -> None:
    """Removes what lies at a path, in whatever store Spark writes to."""
    try:
        place = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(path)
        place.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(place, True)
    except Exception:  # the session may be gone at exit
        pass


def fresh_path(spark: SparkSession, name: str) -> str:
    path = f"{shared_dir(spark)}/bedvoids/{name}-{uuid.uuid4().hex}"
    atexit.register(drop, spark, path)
    if _SCRATCH:
        _SCRATCH[-1].append(path)
    return path


@contextmanager
def scratch(spark: SparkSession) -> Iterator[None]:
    """Intermediate tables made inside are removed at its end; what has to stay is written to a path from outside."""
    _SCRATCH.append([])
    try:
        yield
    finally:
        for path in _SCRATCH.pop():
            drop(spark, path)


def store(df: DataFrame, name: str) -> DataFrame:
    """Cuts the lineage: a Parquet table in the shared folder."""
    path = fresh_path(df.sparkSession, name)
    df.write.parquet(path)
    return df.sparkSession.read.schema(df.schema).parquet(path)


def discard(df: DataFrame) -> None:
    """Removes a table that `store` returned, once nothing reads it any more."""
    for path in {unquote(file.rsplit("/", 1)[0]) for file in df.inputFiles()}:
        drop(df.sparkSession, path)


def bytes_of(spark: SparkSession, path: str) -> int:
    """Bytes below a path, in whatever store Spark reads it from."""
    place = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(path)
    return place.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).getContentSummary(place).getLength()


def asof(left: DataFrame, right: DataFrame, on: str, by: list[str]) -> DataFrame:
    """Each row of `left` with the row of `right` of the same `by` that has the greatest `on` not above its own.

    One shuffle by the keys: both sides stand in one sorted sequence, and the last row of `right` is carried on.
    """
    from pyspark.sql import Window

    cols = [c for c in right.columns if c not in (on, *by)]
    pack = F.struct(F.col(on).alias(f"{on}_right"), *cols)
    both = left.withColumn("_side", F.lit(1)).withColumn("_row", F.struct(*left.columns)).select(*by, on, "_side", "_row", F.lit(None).cast(right.select(pack.alias("r")).schema["r"].dataType).alias("_right"))
    other = right.withColumn("_side", F.lit(0)).select(*by, on, "_side", F.lit(None).cast(both.schema["_row"].dataType).alias("_row"), pack.alias("_right"))
    w = Window.partitionBy(*by).orderBy(on, "_side").rowsBetween(Window.unboundedPreceding, 0)
    return both.unionByName(other).withColumn("_right", F.last("_right", ignorenulls=True).over(w)).where("_side = 1").select("_row.*", "_right.*")
