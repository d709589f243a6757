"""Shared pieces of the training-data operators: tables, scratch tables, prefix sums."""

from __future__ import annotations

import atexit
import ctypes
import gc
import os
import re
import sys
import tempfile
import uuid
from collections.abc import Callable, Iterator
from functools import wraps

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

#: A word of the contracts: a run of anything but ASCII white space (fixed value).
WORD = r"[^\x20\x09-\x0D]+"
ASCII_SPACE = " \t\n\x0b\f\r"

_made: list[tuple[SparkSession, str]] = []


def table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def scratch(spark: SparkSession, label: str) -> str:
    """A fresh path in the folder all executors share (``spark.checkpoint.dir``).

    Where that is unset, a temporary folder serves if the driver and its executors are one process (``local``); on
    a cluster no folder is known to be shared then, which is an error.
    """
    base = spark.sparkContext.getConf().get("spark.checkpoint.dir") or spark.conf.get("spark.checkpoint.dir", None)
    if not base:
        if not re.match(r"local($|\[)", spark.sparkContext.master):
            raise RuntimeError("set spark.checkpoint.dir to a folder that the driver and all executors share")
        base = "file://" + os.path.join(tempfile.gettempdir(), "chronoweave-scratch")
    path = f"{base.rstrip('/')}/{label}-{uuid.uuid4().hex}"
    _made.append((spark, path))
    return path


def stored(df: DataFrame, label: str, parallel: int | None = None) -> DataFrame:
    """Write ``df`` to a shared scratch table and read it back: cuts the lineage, survives lost executors."""
    spark = df.sparkSession
    path = scratch(spark, label)
    schema = df.schema
    df.write.parquet(path)
    return spark.read.schema(schema).parquet(path)


@atexit.register
def _sweep() -> None:
    for spark, path in _made:
        try:
            jvm = spark.sparkContext._jvm
            p = jvm.org.apache.hadoop.fs.Path(path)
            p.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(p, True)
        except Exception:  # the session may be gone already
            return


def unique_ids(docs: DataFrame) -> bool:
    """Whether ``doc_id`` is a whole number that no two rows share; only ids are shuffled to find out."""
    ids = docs.select(F.col("doc_id").cast("long").alias("i")).groupBy("i").agg(F.count(F.lit(1)).alias("n"))
    return ids.filter("n > 1 OR i IS NULL").limit(1).isEmpty()


def identified(docs: DataFrame, name: str = "__row") -> DataFrame:
    """``docs`` with a number in ``name`` that no two rows share: ``doc_id`` where it is one, else a stored copy is numbered.

    The copy is written because a row's number must not change when it is read again.
    """
    if unique_ids(docs):
        return docs.withColumn(name, F.col("doc_id").cast("long"))
    return stored(docs.withColumn(name, F.monotonically_increasing_id()), "identified")


class Memo(dict):
    """What ``make`` gave for the keys met, up to about ``limit`` bytes; emptied when full. Long keys are not kept."""

    def __init__(self, make: Callable, limit: int = 32 << 20, longest: int = 256) -> None:
        self.make, self.limit, self.longest, self.held = make, limit, longest, 0

    def __missing__(self, key):
        value = self.make(key)
        if len(key) <= self.longest:
            self.held += 104 + sys.getsizeof(key) + sys.getsizeof(value)
            if self.held > self.limit:
                self.clear()
                self.held = 0
            self[key] = value
        return value


def slices(batch: pa.RecordBatch, text: int, rows: int = 512, size: int = 1 << 20) -> Iterator[pa.RecordBatch]:
    """A batch in slices of at most ``rows`` rows and ``size`` bytes of column ``text``; a longer text is a slice of its own."""
    ends = np.cumsum(pc.fill_null(pc.binary_length(batch.column(text)), 0).to_numpy(zero_copy_only=False), dtype=np.int64)
    at = 0
    while at < batch.num_rows:
        past = int(ends[at - 1]) if at else 0
        stop = min(at + rows, max(at + 1, int(np.searchsorted(ends, past + size, "right"))))
        yield batch.slice(at, stop - at)
        at = stop


def frugal(run: Callable) -> Callable:
    """An Arrow task that gives its memory back at its end: Python workers live on and serve later tasks."""

    @wraps(run)
    def whole(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        try:
            yield from run(batches)
        finally:
            gc.collect()
            pa.default_memory_pool().release_unused()
            try:
                ctypes.CDLL("libc.so.6").malloc_trim(0)
            except (OSError, AttributeError):  # another C library
                pass

    return whole


def word_count(text: Column) -> Column:
    """Words of a text, null counting as none."""
    return F.coalesce(F.regexp_count(text, F.lit(WORD)), F.lit(0)).cast("long")


def running(df: DataFrame, group: list[str], order: list[str], bucket: Column, sums: dict[str, str], rank: str | None = None) -> DataFrame:
    """Exclusive running sums (``sums``: new column -> summed column) and rank, in ``bucket`` then ``order`` within ``group``.

    Two levels, so no group is ever sorted by one task: sums per (group, bucket) come first, their running
    totals are taken over the few buckets of a group, and rows are ordered only within their bucket.
    ``bucket`` must be monotone in the wanted order; ``order`` must be a total order within a bucket.
    """
    df = df.withColumn("__b", bucket)
    one = {"__n": F.count(F.lit(1))} | {f"__s_{k}": F.sum(v) for k, v in sums.items()}
    per = df.groupBy(*group, "__b").agg(*[v.alias(k) for k, v in one.items()])
    before = Window.partitionBy(*group).orderBy("__b").rowsBetween(Window.unboundedPreceding, -1)
    ids = [*group, "__b"]
    per = per.select(*[F.col(c).alias(f"__k{i}") for i, c in enumerate(ids)], *[F.coalesce(F.sum(k).over(before), F.lit(0)).alias(f"{k}0") for k in one])
    on = F.lit(True)
    for i, c in enumerate(ids):
        on = on & F.col(c).eqNullSafe(F.col(f"__k{i}"))
    out = df.join(per, on).drop(*[f"__k{i}" for i in range(len(ids))])
    inner = Window.partitionBy(*group, "__b").orderBy(*order)
    past = inner.rowsBetween(Window.unboundedPreceding, -1)
    for k, v in sums.items():
        out = out.withColumn(k, (F.col(f"__s_{k}0") + F.coalesce(F.sum(v).over(past), F.lit(0))).cast("long"))
    if rank:
        out = out.withColumn(rank, (F.col("__n0") + F.row_number().over(inner) - 1).cast("long"))
    return out.drop("__b", "__n0", *[f"__s_{k}0" for k in sums])
