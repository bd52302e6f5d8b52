"""Shared storage for intermediate tables, memory of Python workers, and small expression helpers."""

from __future__ import annotations

import ctypes
import functools
import gc

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from certsel.sources.staging import discard, fresh_path

__all__ = ["WORD", "discard", "settle", "staged", "table", "text_or_empty", "tidy"]
WORD = r"[^\x20\x09-\x0D]+"


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def staged(df: DataFrame, label: str) -> tuple[DataFrame, str]:
    """Write df once to the shared folder and read it back: lineage is cut, and a lost executor costs no recomputation."""
    spark = df.sparkSession
    path = fresh_path(spark, label)
    df.write.parquet(path)
    return spark.read.schema(df.schema).parquet(path), path


def settle(spark: SparkSession) -> None:
    """Give back the shuffle files of plans that have run.  They stay until the driver collects its garbage, which an idle driver rarely does."""
    gc.collect()
    spark._jvm.System.gc()


def tidy(run):
    """A function over Arrow batches that gives its memory back at the end.  Workers are used again by later stages, so what they keep adds up."""

    @functools.wraps(run)
    def tidied(batches):
        import pyarrow as pa

        pa.set_memory_pool(pa.system_memory_pool())
        try:
            yield from run(batches)
        finally:
            gc.collect()
            trim = getattr(ctypes.CDLL(None), "malloc_trim", None)  # of the GNU library
            if trim:
                trim(0)

    return tidied


def text_or_empty(c: Column | str) -> Column:
    return F.coalesce(F.col(c) if isinstance(c, str) else c, F.lit(""))
