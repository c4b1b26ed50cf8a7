"""What all operators of this subpackage share: Arrow helpers and the tables of a data folder."""

from __future__ import annotations

import ctypes
import functools
from collections.abc import Callable, Iterable, Iterator

import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from corpusbwt.session import ship


def table(spark: SparkSession, sf_dir: str, name: str, *columns: str) -> DataFrame:
    """A given table, by the columns that an operator uses: extra columns, whatever their names, don't get in its way."""
    ship(spark)
    return spark.read.parquet(f"{sf_dir}/{name}.parquet").select(*columns)


def texts_of(column: pa.Array | pa.ChunkedArray) -> list[str]:
    """Python strings of a column; a null text is an empty one."""
    return [x or "" for x in column.to_pylist()]


def trimmed(run: Callable[[Iterator], Iterator]) -> Callable[[Iterator], Iterator]:
    """``run`` for a task, after which its worker gives free memory back: workers live on beside the stages that follow."""

    @functools.wraps(run)
    def wrapped(batches: Iterator) -> Iterator:
        yield from run(batches)
        pa.default_memory_pool().release_unused()
        try:
            ctypes.CDLL(None).malloc_trim(0)
        except (AttributeError, OSError):  # another C library
            return

    return wrapped


def batch_of(schema: pa.Schema, columns: Iterable) -> pa.RecordBatch:
    arrays = [c if isinstance(c, pa.Array) else pa.array(c, f.type) for c, f in zip(columns, schema, strict=True)]
    return pa.RecordBatch.from_arrays(arrays, schema=schema)


def null_safe(left: DataFrame, right: DataFrame, *pairs: tuple[str, str]):
    """An equality condition on column pairs that also matches nulls; still an equi-join for the planner."""
    out = F.lit(True)
    for a, b in pairs:
        out = out & left[a].eqNullSafe(right[b])
    return out
