"""A reader of raw step files: one file a step, as a simulation dumps them, read in parallel file by file."""

from __future__ import annotations

import re
from collections.abc import Iterator
from pathlib import Path

import numpy as np
import pyarrow as pa
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition
from pyspark.sql.types import StructType

SCHEMA = "step int, x double, y double, z double, vx double, vy double, vz double"
_NAMES = ("x", "y", "z", "vx", "vy", "vz")


class StepFile(InputPartition):
    def __init__(self, path: str, step: int):
        self.path, self.step = path, step


class StepReader(DataSourceReader):
    def __init__(self, options: dict):
        self.path, self.stride = options["path"], int(options.get("stride", 1))

    def partitions(self) -> list[StepFile]:
        """Files that the stride leaves out are never opened."""
        found = ((p, re.fullmatch(r"step_(\d+)\.npy", p.name)) for p in sorted(Path(self.path).iterdir()))
        return [StepFile(str(p), int(m[1])) for p, m in found if m and int(m[1]) % self.stride == 0]

    def read(self, partition: StepFile) -> Iterator[pa.RecordBatch]:
        rows = np.load(partition.path, mmap_mode="r")
        for i in range(0, len(rows), 1 << 16):
            part = rows[i : i + (1 << 16)]
            cols = [pa.array(np.full(len(part), partition.step, np.int32)), *(pa.array(np.ascontiguousarray(part[:, k], float)) for k in range(6))]
            yield pa.RecordBatch.from_arrays(cols, names=["step", *_NAMES])


class StepFileSource(DataSource):
    """format("step_files"): files step_<number>.npy of rows x, y, z, vx, vy, vz in a folder that all executors share."""

    @classmethod
    def name(cls) -> str:
        return "step_files"

    def schema(self) -> str:
        return SCHEMA

    def reader(self, schema: StructType) -> StepReader:
        return StepReader(self.options)


def write_step(path: str, step: int, rows: np.ndarray) -> None:
    """One step as a producer would leave it: written beside, then moved into place."""
    place = Path(path, f"step_{step}.npy")
    place.parent.mkdir(parents=True, exist_ok=True)
    with place.with_suffix(".tmp").open("wb") as f:
        np.save(f, np.asarray(rows, float))
    place.with_suffix(".tmp").replace(place)
