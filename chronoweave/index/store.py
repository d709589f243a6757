"""A stored temporal graph: coalesced edges laid out for pruning, label statistics, dictionary, timeline and matrices.

Queries on a stored graph read the edges they need: scans name the label's class and, for a least duration, the classes
of length, which are folders; least-children orders come from a few rows of statistics instead of a pass over the edges.
"""

from __future__ import annotations

import atexit
import json
import os
import re
import tempfile
import uuid
from contextlib import contextmanager
from dataclasses import dataclass, replace

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..model.graph import EDGE, TemporalGraph, coalesce_edges
from ..model.query import Const, PatternQuery, TimeVar
from ..operators.overlap import bucket_bounds
from ..plans.stats import label_stats
from . import tries

#: Parts of equal numbers of starts whose bounds a store keeps for time-first plans.
BOUNDS = 256

_made: list[tuple[SparkSession, str]] = []


def shared_folder(spark: SparkSession, label: str) -> str:
    """A fresh path that all executors share, gone when Python ends: below ``spark.checkpoint.dir``; a temporary one only in local mode."""
    base = spark.sparkContext.getConf().get("spark.checkpoint.dir") or spark.conf.get("spark.checkpoint.dir", None)
    if not base:
        if not re.match(r"local($|\[)", spark.sparkContext.master):
            raise RuntimeError("set spark.checkpoint.dir to a folder that the driver and all executors share")
        base = "file://" + os.path.join(tempfile.gettempdir(), "chronoweave-store")
    path = f"{base.rstrip('/')}/{label}-{uuid.uuid4().hex}"
    _made.append((spark, path))
    return path


@atexit.register
def _sweep() -> None:
    for spark, path in _made:
        try:
            p = spark.sparkContext._jvm.org.apache.hadoop.fs.Path(path)
            p.getFileSystem(spark.sparkContext._jsc.hadoopConfiguration()).delete(p, True)
        except Exception:  # the session may be gone already
            return


def laid_out(g: TemporalGraph, edges: DataFrame, labels: int, merge: bool) -> DataFrame:
    """Edges with ``label_class`` (a hash of the label) and ``length_class`` (log2 of the length in time units), dealt by range of
    label class, label, object and subject. A triple's edges lie together, so ``merge`` puts their intervals together without another shuffle."""
    keys = ("label_class", "p", "o", "s")
    edges = edges.withColumn("p", F.when(F.col("ts") < F.col("te"), F.col("p")).otherwise(F.col("s")))  # always p; a literal label would be dropped from the ranges' keys
    rows = edges.withColumn("label_class", F.pmod(F.xxhash64("p"), F.lit(labels)).cast("int")).repartitionByRange(*keys)
    rows = coalesce_edges(rows, keys) if merge else rows
    length = F.floor(F.log2(g.length(F.col("ts"), F.col("te")).cast("double"))).cast("int")
    return rows.select(*EDGE, "label_class", length.alias("length_class"))


@contextmanager
def swept(spark: SparkSession):
    """Each query that runs meanwhile leaves no shuffle files behind when it ends, where Spark can do that."""
    key = "spark.sql.classic.shuffleDependency.fileCleanup.enabled"
    before = spark.conf.get(key, None)
    spark.conf.set(key, "true")
    try:
        yield
    finally:
        spark.conf.unset(key) if before is None else spark.conf.set(key, before)


def save(g: TemporalGraph, path: str, orders: tuple[str, ...] = ("otps",), labels: int = 16, pack: bool = False, events_each: int = 1 << 20) -> None:
    """Writes the graph and what queries need beside it; matrices for ``orders``, dictionary and timeline only if ``pack``.

    Edges of a label class are dealt by range of label, object and subject, so hot labels and hubs spread over many files, sorted within.
    Intervals that are not merged yet are merged behind that one shuffle; edges that come in parts without a label in
    common are written a part at a time, and the shuffle of one is gone before the next begins.
    """
    with swept(g.frame.sparkSession):
        _save(g, path, orders, labels, pack, events_each)


def _save(g: TemporalGraph, path: str, orders: tuple[str, ...], labels: int, pack: bool, events_each: int) -> None:
    spark, merge = g.frame.sparkSession, g.loose is not None
    for part in (g.parts or (g.loose,)) if merge else (g.frame,):
        rows = laid_out(g, part, labels, merge)
        rows.sortWithinPartitions("label_class", "length_class", "p", "o", "ts").write.partitionBy("label_class", "length_class").mode("append").parquet(f"{path}/edges")
    held = replace(g, frame=spark.read.schema(rows.schema).parquet(f"{path}/edges").select(*EDGE), loose=None, parts=None)
    label_stats(held).write.parquet(f"{path}/stats")
    width = 0
    if pack:  # matrices speak in numbers
        held.dictionary().write.parquet(f"{path}/dictionary")
        held.timeline().write.parquet(f"{path}/timeline")
        index = tries.build(held, orders, True, events_each)
        width = index.width
        for o, m in index.matrices.items():
            m.write.parquet(f"{path}/matrix/{o}")
    starts = bucket_bounds(held.frame.select("ts"), "ts", BOUNDS)
    note = json.dumps({"starts": starts, "time_type": g.time_type, "labels": labels, "orders": list(orders) if pack else [], "width": width})
    spark.range(1, numPartitions=1).select(F.lit(note).alias("note")).write.text(f"{path}/note")


@dataclass(frozen=True)
class Store:
    """A stored graph: ``graph`` for every route, and matrices for windows."""

    graph: TemporalGraph
    path: str
    width: int
    orders: tuple[str, ...]

    def _read(self, name: str) -> DataFrame:
        return self.graph.frame.sparkSession.read.parquet(f"{self.path}/{name}")

    def ticks(self, lo: object, hi: object | None = None) -> tuple[int, int] | None:
        """First and last tick of the instants of [lo, hi), or the tick of ``lo`` alone; None where nothing has begun."""
        line, g = self._read("timeline"), self.graph
        a = F.max(F.when(F.col("at") <= g.instant(lo), F.col("tick")))
        b = a if hi is None else F.max(F.when(F.col("at") < g.instant(hi), F.col("tick")))
        row = line.agg(a.alias("a"), b.alias("b")).first()
        if row["b"] is None:
            return None
        return (0 if row["a"] is None else row["a"]), row["b"]

    def triples(self, mode: str, lo: object, hi: object | None = None, order: str | None = None) -> DataFrame:
        """(s, p, o) that exist at ``lo`` (``at``), at some (``any``) or every (``all``) instant of [lo, hi), from the matrices alone."""
        order = order or self.orders[0]
        span = self.ticks(lo, hi)
        before = span is not None and mode == "all" and self._read("timeline").agg(F.min("at") > self.graph.instant(lo)).first()[0]
        if span is None or before:
            return self.graph.frame.select("s", "p", "o").limit(0)
        ids = tries.matrix_window(self._read(f"matrix/{order}"), order, self.width, *span, "all" if mode == "all" else "any")
        for c in ("s", "p", "o"):
            d = self._read("dictionary").select(F.col("id").alias(c), F.col("term").alias(f"{c}_"))
            ids = ids.join(d, c).drop(c).withColumnRenamed(f"{c}_", c)
        return ids.select("s", "p", "o")


def open_store(spark: SparkSession, path: str) -> Store:
    note = json.loads(spark.read.text(f"{path}/note").first()[0])
    stats = [r.asDict() for r in spark.read.parquet(f"{path}/stats").collect()]
    g = TemporalGraph(spark.read.parquet(f"{path}/edges"), note["time_type"], note["labels"], tuple(stats), tuple(note["starts"]))
    return Store(g, path, note["width"], tuple(note["orders"]))


def by_matrix(q: PatternQuery, store: Store, mode: str, lo: object, hi: object | None = None) -> DataFrame:
    """Bindings of a pattern over what the matrices say exists at an instant or in a window."""
    from ..operators.solve import timeless

    if any(isinstance(p.t, Const) for p in q.patterns):
        raise ValueError("the window stands for the time of every pattern")
    return timeless(q.with_time(TimeVar("t")), store.triples(mode, lo, hi), store.graph)
