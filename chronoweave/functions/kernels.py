"""The seek kernels as grouped Arrow functions: common children of sorted lists, common ranges of time levels."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..operators.leapfrog import intersect, intersect_time


def _common_children(lists: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        t = pa.Table.from_batches(list(batches))
        key, child = t.column("key").to_numpy(zero_copy_only=False), t.column("child").to_numpy()
        names = sorted(set(key))
        if len(names) == lists:
            yield pa.RecordBatch.from_arrays([pa.array(intersect([np.sort(child[key == k]) for k in names]), pa.int64())], ["child"])

    return run


def intersected(rows: DataFrame, lists: int, stretch: int = 1 << 20) -> DataFrame:
    """Children that all ``lists`` keys of (key, child) have, by cyclic seeks; stretches of numbers are intersected apart."""
    dealt = rows.withColumn("part", F.floor(F.col("child") / stretch))
    return dealt.groupBy("part").applyInArrow(_common_children(lists), "child long")


def _common_ranges(lists: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        t = pa.Table.from_batches(list(batches))
        key, label = t.column("key").to_numpy(zero_copy_only=False), t.column("label").to_numpy(zero_copy_only=False)
        a, b = t.column("a").to_numpy(), t.column("b").to_numpy()
        order = np.lexsort((a, label.astype(str), key.astype(str)))
        out: list[tuple] = []
        edge = np.flatnonzero(np.concatenate(([True], key[order][1:] != key[order][:-1], [True])))
        for lo, hi in zip(edge[:-1], edge[1:], strict=True):
            mine = order[lo:hi]
            names = sorted(set(label[mine]))
            if len(names) == lists:
                ranges = [list(zip(a[m].tolist(), b[m].tolist(), strict=True)) for m in (mine[label[mine] == n] for n in names)]
                out += [(key[mine[0]], x, y) for x, y in intersect_time(ranges, int(a[mine].min()), int(b[mine].max()))]
        if out:
            k, x, y = zip(*out, strict=True)
            yield pa.RecordBatch.from_arrays([pa.array(k, pa.string()), pa.array(x, pa.int64()), pa.array(y, pa.int64())], ["key", "a", "b"])

    return run


def common_ranges(level: DataFrame, key: str, label: str, lists: int, parts: int = 64) -> DataFrame:
    """(key, a, b) in microseconds: the common parts of the time levels (start, stop) of all ``lists`` labels below each key."""
    us = lambda c: F.unix_micros(F.col(c).cast("timestamp"))
    rows = level.select(F.col(key).alias("key"), F.col(label).alias("label"), us("start").alias("a"), us("stop").alias("b"), F.pmod(F.xxhash64(key), F.lit(parts)).alias("part"))
    return rows.groupBy("part").applyInArrow(_common_ranges(lists), "key string, a long, b long").withColumnRenamed("key", key)
