"""What the operators of this subpackage share: reading, Arrow row buffers, written steps."""

from __future__ import annotations

import os
import sys
from collections.abc import Callable, Iterator
from pathlib import Path

import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from fairlink.sources import steps

#: Rows that an operator turns into Python objects at a time; Arrow batches themselves hold at
#: most spark.sql.execution.arrow.maxBytesPerBatch bytes.
SLICE_ROWS = 256


def _importable(spark: SparkSession) -> None:
    """Lets Python workers find this package where it is not installed."""
    root, own = str(Path(__file__).resolve().parents[2]), spark.sparkContext.environment
    if root not in own.get("PYTHONPATH", ""):
        own["PYTHONPATH"] = os.pathsep.join(filter(None, [own.get("PYTHONPATH"), root]))


def documents(spark: SparkSession, sf_dir: str) -> DataFrame:
    _importable(spark)
    return spark.read.parquet(f"{sf_dir}/documents.parquet")


def pages(spark: SparkSession, sf_dir: str) -> DataFrame:
    _importable(spark)
    return spark.read.parquet(f"{sf_dir}/pages.parquet")


_kept: dict = {}


def give_back() -> None:
    """Returns freed memory to the system; a worker process outlives its tasks, and holds it else."""
    if sys.platform == "linux":
        import ctypes

        trim = getattr(ctypes.CDLL(None), "malloc_trim", None)
        if trim:
            trim(0)


def kept(key, make: Callable):
    """What a worker process keeps from task to task: that of one operator at a time."""
    if key not in _kept:
        _kept.clear()
        give_back()
        _kept[key] = make()
    return _kept[key]


def slices(batches: Iterator[pa.RecordBatch], *names: str) -> Iterator[tuple[list, ...]]:
    """The named columns of every batch as Python lists of at most SLICE_ROWS values."""
    for batch in batches:
        columns = [batch.column(batch.schema.get_field_index(n)) for n in names]
        for at in range(0, batch.num_rows, SLICE_ROWS):
            yield tuple(c.slice(at, SLICE_ROWS).to_pylist() for c in columns)


class RowBuffer:
    """Collects rows and hands them out as Arrow batches of a fixed schema."""

    def __init__(self, schema: pa.Schema, rows: int = 4096):
        self.schema, self.rows, self.data = schema, rows, []

    def add(self, row: tuple) -> None:
        self.data.append(row)

    def full(self) -> bool:
        return len(self.data) >= self.rows

    def take(self) -> pa.RecordBatch:
        columns = list(zip(*self.data, strict=True)) or [[] for _ in self.schema]
        self.data = []
        return pa.record_batch([pa.array(c, f.type) for c, f in zip(columns, self.schema, strict=True)], schema=self.schema)


def durable(df: DataFrame) -> DataFrame:
    """Writes the rows as a table in the folder that the cluster names, and reads them from there.

    That cuts the lineage: lost executors repeat nothing before it. The folder is in spark.checkpoint.dir, or in the
    warehouse where that is unset, never on one machine of a cluster, and goes when the session's process ends.
    """
    return steps.written(df, "fairlink")


def text_or_empty(name: str = "text"):
    return F.coalesce(F.col(name), F.lit(""))
