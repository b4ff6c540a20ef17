"""Session helpers shared by the operators of this subpackage."""

from __future__ import annotations

import ctypes
import functools
import gc
from collections.abc import Callable, Iterator

import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.pandas.types import to_arrow_schema
from pyspark.sql.types import StructType

from ..session import scratch


def settle(df: DataFrame) -> DataFrame:
    """Cut the lineage of ``df`` with a reliable checkpoint in the shared folder.

    The folder is the session's ``spark.checkpoint.dir``. Only where that is
    unset, as in tests on one machine, a temporary folder is taken.
    """
    context = df.sparkSession.sparkContext
    if context.getCheckpointDir() is None:
        context.setCheckpointDir(scratch(df.sparkSession))
    return df.checkpoint(eager=True)


def release(spark: SparkSession) -> None:
    """Let Spark delete shuffle files and checkpoints nobody refers to any more."""
    gc.collect()
    spark.sparkContext._jvm.System.gc()


def partitions(spark: SparkSession) -> int:
    """Number of shuffle partitions of the session: buckets scale with it."""
    return max(1, int(spark.conf.get("spark.sql.shuffle.partitions")))


def join_hot(left: DataFrame, right: DataFrame, key: str, rows: int) -> DataFrame:
    """Inner join by ``key`` that splits hot keys.

    ``right`` has one row a key with the number ``n`` of its rows in ``left``,
    which has ``rows`` in all. Keys with over a thousandth of them are 999 at
    most: their rows are broadcast, so ``left`` is not dealt by them.
    """
    hot = F.broadcast(right.where(F.col("n") * 1000 > rows))
    cold = left.join(F.broadcast(hot.select(key)), key, "left_anti").join(right.where(F.col("n") * 1000 <= rows), key)
    return left.join(hot, key).unionByName(cold)


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def _trim() -> None:
    gc.collect()
    pa.default_memory_pool().release_unused()
    try:
        ctypes.CDLL("libc.so.6").malloc_trim(0)
    except (OSError, AttributeError):  # another C library: nothing to trim
        pass


def lean(run: Callable[[Iterator], Iterator]) -> Callable[[Iterator], Iterator]:
    """A pass over batches that hands memory back when it ends: Python workers outlive their tasks."""

    @functools.wraps(run)
    def passed(batches):
        try:
            yield from run(batches)
        finally:
            _trim()

    return passed


def map_frames(df: DataFrame, run: Callable[[Iterator[pd.DataFrame]], Iterator[pd.DataFrame]], schema: str) -> DataFrame:
    """``mapInPandas`` whose long columns are nullable integers.

    Spark turns a long column with a null into floats, which merge ids beyond
    2**53; here an id stays exact beside a null one.
    """
    given = to_arrow_schema(StructType.fromDDL(schema))

    def passed(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        frames = (b.to_pandas(types_mapper={pa.int64(): pd.Int64Dtype()}.get) for b in batches)
        for out in run(frames):
            yield pa.RecordBatch.from_pandas(out, given, preserve_index=False)

    return df.mapInArrow(passed, schema)
