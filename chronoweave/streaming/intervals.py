"""Event streams to temporal edges, live counts, overlap joins and delta evaluation."""

from __future__ import annotations

from collections.abc import Iterator

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.streaming.state import GroupState, GroupStateTimeout

from ..model.graph import EDGE, TemporalGraph, coalesce_edges
from ..model.query import PatternQuery
from ..operators.pairwise import finish, scan

EVENT = "event_id long, ts timestamp, user_id long, event_type string, value double, props string"
STOP = "user_id long, k int, ts timestamp, nk int, nts timestamp"


def event_stream(spark: SparkSession, path: str, files_per_trigger: int = 1) -> DataFrame:
    """Files of events as a stream; instants become zoned timestamps, which watermarks need."""
    raw = spark.readStream.schema(EVENT.replace("ts timestamp", "ts timestamp_ntz")).option("maxFilesPerTrigger", files_per_trigger).parquet(path)
    return raw.withColumn("ts", F.col("ts").cast("timestamp"))


def _close_trips(key: tuple, frames: Iterator[pd.DataFrame], state: GroupState) -> Iterator[pd.DataFrame]:
    """Holds each user's open stop; every event closes it and opens the next."""
    rows = pd.concat(list(frames)).sort_values(["ts", "event_id"])
    last = state.get if state.exists else None
    out = []
    for at, k in zip(rows["ts"], rows["k"], strict=True):
        us = int(at.value // 1000)
        if last is not None and us >= last[1]:
            out.append((key[0], last[0], pd.Timestamp(last[1], unit="us"), int(k), at))
        if last is None or us >= last[1]:
            last = (int(k), us)
    if last is not None:
        state.update(last)
    yield pd.DataFrame(out, columns=["user_id", "k", "ts", "nk", "nts"])


def trips(events: DataFrame, delay: str | None = None) -> DataFrame:
    """Closed trip edges: one row for each pair of consecutive stops of a user. Works on streams and tables.

    Events later than the watermark are dropped; events out of order within one micro-batch are sorted.
    """
    stops = events.withColumn("k", F.get_json_object("props", "$.k").cast("int")).select("event_id", "user_id", "ts", "k")
    if stops.isStreaming:
        if delay:
            stops = stops.withWatermark("ts", delay)
        return stops.groupBy("user_id").applyInPandasWithState(_close_trips, STOP, "k int, us long", "append", GroupStateTimeout.NoTimeout)
    from pyspark.sql import Window

    w = Window.partitionBy("user_id").orderBy("ts", "event_id")
    return stops.select("user_id", "k", "ts", F.lead("k").over(w).alias("nk"), F.lead("ts").over(w).alias("nts")).filter("nts IS NOT NULL")


def live_counts(events: DataFrame, at: str, width: str, slide: str | None = None) -> DataFrame:
    """Events in tumbling or sliding windows."""
    w = F.window(at, width, slide) if slide else F.window(at, width)
    return events.groupBy(w.alias("w")).agg(F.count(F.lit(1)).alias("n")).select(F.col("w.start").alias("w_from"), F.col("w.end").alias("w_to"), "n")


def sessions(events: DataFrame, at: str, key: str, gap: str) -> DataFrame:
    return events.groupBy(F.session_window(at, gap).alias("w"), key).agg(F.count(F.lit(1)).alias("n")).select(key, F.col("w.start").alias("w_from"), F.col("w.end").alias("w_to"), "n")


def overlap_stream_join(left: DataFrame, right: DataFrame, on: str, longest: str, delay: str = "1 hour") -> DataFrame:
    """Edges (on, ts, te) of two streams that overlap. ``longest`` bounds an edge's length and so the state kept."""
    if left.isStreaming:
        left, right = left.withWatermark("ts", delay), right.withWatermark("ts", delay)
    a = left.select(F.col(on).alias("key"), F.col("s").alias("x"), F.col("ts").alias("a_ts"), F.col("te").alias("a_te"))
    b = right.select(F.col(on).alias("b_key"), F.col("s").alias("y"), F.col("ts").alias("b_ts"), F.col("te").alias("b_te"))
    near = (F.col("b_ts") >= F.col("a_ts") - F.expr(f"INTERVAL {longest}")) & (F.col("b_ts") <= F.col("a_ts") + F.expr(f"INTERVAL {longest}"))
    out = a.join(b, (F.col("key") == F.col("b_key")) & near & (F.col("a_ts") < F.col("b_te")) & (F.col("b_ts") < F.col("a_te")))
    return out.select("key", "x", "y", F.greatest("a_ts", "b_ts").alias("t_from"), F.least("a_te", "b_te").alias("t_to"))


def delta_solve(q: PatternQuery, old: TemporalGraph, new: TemporalGraph) -> DataFrame:
    """Solutions that use at least one new edge: for each pattern i, new edges there, both kinds before, old ones after."""
    both = old.of(old.frame.unionByName(new.frame))
    out = None
    for i in range(len(q.patterns)):
        acc, bound = None, set()
        for j in range(len(q.patterns)):
            part = scan(q, j, new if j == i else both if j < i else old)
            vs = q.patterns[j].variables
            shared = [v for v in vs if v in bound]
            acc = part if acc is None else (acc.join(part, shared) if shared else acc.crossJoin(part))
            bound |= set(vs)
        got = finish(acc, q, old)
        out = got if out is None else out.unionByName(got)
    return out


def once(df: DataFrame, key: str, at: str, delay: str) -> DataFrame:
    """Drops repeats of a key within the watermark."""
    return df.withWatermark(at, delay).dropDuplicatesWithinWatermark([key]) if df.isStreaming else df.dropDuplicates([key])


def with_late(events: DataFrame, at: str, horizon: str) -> DataFrame:
    """Adds ``late``: the event is older than the horizon behind its arrival (``arrived``)."""
    return events.withColumn("late", F.col(at) < F.col("arrived") - F.expr(f"INTERVAL {horizon}"))


def divert_late(events: DataFrame, at: str, horizon: str) -> tuple[DataFrame, DataFrame]:
    """(rows on time, late rows) by ``with_late``: late ones go to a sink of their own, before anything with state could drop them."""
    told = with_late(events, at, horizon)
    return told.filter("NOT late").drop("late"), told.filter("late").drop("late")


def solve_batches(q: PatternQuery, base: TemporalGraph, out: str):
    """A ``foreachBatch`` sink of new edges: writes the solutions that each batch adds to the base and all earlier batches.

    Batches and their edges carry the batch number, so a batch that is run again replaces itself.
    """

    def sink(batch: DataFrame, number: int) -> None:
        spark = batch.sparkSession
        batch.select(*EDGE).write.mode("overwrite").parquet(f"{out}-edges/batch={number}")
        seen = spark.read.schema(batch.select(*EDGE).schema.add("batch", "long")).parquet(f"{out}-edges")
        old = base.of(base.frame.select(*EDGE).unionByName(seen.filter(F.col("batch") < number).select(*EDGE)))
        delta_solve(q, old, base.of(seen.filter(F.col("batch") == number).select(*EDGE))).write.mode("overwrite").parquet(f"{out}/batch={number}")

    return sink


def apply_events(base_path: str):
    """A ``foreachBatch`` sink of edge changes (s, p, o, ts, te, op): appends each batch as a delta run.

    Runs carry the batch number, so a batch that is run again replaces itself.
    """

    def sink(batch: DataFrame, number: int) -> None:
        batch.select(*EDGE, "op").write.mode("overwrite").parquet(f"{base_path}/run={number}")

    return sink


def current(spark: SparkSession, base: DataFrame, base_path: str) -> DataFrame:
    """The base with all delta runs applied in order: the last word on a (s, p, o, ts, te) counts."""
    from pyspark.sql import Window

    runs = spark.read.parquet(base_path)
    w = Window.partitionBy(*EDGE).orderBy(F.desc("run"))
    rows = base.select(*EDGE, F.lit("insert").alias("op"), F.lit(-1).alias("run")).unionByName(runs.select(*EDGE, "op", "run"))
    last = rows.withColumn("__r", F.row_number().over(w)).filter("__r = 1 AND op = 'insert'")
    return coalesce_edges(last.select(*EDGE))


def compact(spark: SparkSession, base: DataFrame, base_path: str, out: str) -> None:
    """Merges base and delta runs into a new base."""
    current(spark, base, base_path).write.mode("overwrite").parquet(out)
