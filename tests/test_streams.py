"""Streams that run: files arrive, queries start, stop, start again, and end with what the batch gives."""

import pytest
from pyspark.sql import functions as F

from chronoweave.model.graph import EDGE, TemporalGraph
from chronoweave.model.query import parse
from chronoweave.operators import solve
from chronoweave.sources.graphs import graph
from chronoweave.sources.tables import load
from chronoweave.streaming import intervals as stream

SF = "/root/testdata/sf0.001"


@pytest.fixture()
def arriving(spark, tmp_path):
    """Events in six files by time; the function lets some of them arrive."""
    events = load(spark, SF, "events").orderBy("ts", "event_id").toPandas()
    folder = tmp_path / "events"
    folder.mkdir()
    size = -(-len(events) // 6)

    def arrive(*numbers):
        for i in numbers:
            spark.createDataFrame(events[i * size : (i + 1) * size], load(spark, SF, "events").schema).coalesce(1).write.mode("append").parquet(f"file://{folder}")

    arrive.path, arrive.events = f"file://{folder}", events
    return arrive


def run(df, out, check, mode="append"):
    q = df.writeStream.format("parquet").option("path", out).option("checkpointLocation", check).outputMode(mode).trigger(availableNow=True).start()
    q.awaitTermination(240)
    assert q.exception() is None
    return q


def test_trips_over_a_restart(spark, arriving, tmp_path):
    out, check = f"file://{tmp_path}/trips", f"file://{tmp_path}/check"
    arriving(0, 1, 2)
    run(stream.trips(stream.event_stream(spark, arriving.path, 1), "30 days"), out, check)
    half = spark.read.parquet(out).count()
    arriving(3, 4, 5)
    run(stream.trips(stream.event_stream(spark, arriving.path, 1), "30 days"), out, check)
    got = spark.read.parquet(out)
    want = stream.trips(load(spark, SF, "events"))
    key = lambda df: sorted((r["user_id"], r["k"], r["ts"], r["nk"], r["nts"]) for r in df.withColumns({c: F.col(c).cast("timestamp_ntz") for c in ("ts", "nts")}).collect())
    assert 0 < half < got.count() and key(got) == key(want)


def test_late_rows_are_diverted_and_counted(spark, arriving, tmp_path):
    arriving(0, 1, 2, 3, 4, 5)
    late = F.expr("event_id % 10 = 3")
    events = stream.event_stream(spark, arriving.path, 6).withColumn("arrived", F.col("ts") + F.when(late, F.expr("INTERVAL 3 HOURS")).otherwise(F.expr("INTERVAL 1 MINUTE")))
    on_time, behind = stream.divert_late(events, "ts", "1 hour")
    run(on_time.select("event_id"), f"file://{tmp_path}/on", f"file://{tmp_path}/c1")
    run(behind.select("event_id"), f"file://{tmp_path}/late", f"file://{tmp_path}/c2")
    ids = {int(i) for i in arriving.events["event_id"]}
    assert {r[0] for r in spark.read.parquet(f"file://{tmp_path}/late").collect()} == {i for i in ids if i % 10 == 3}
    assert {r[0] for r in spark.read.parquet(f"file://{tmp_path}/on").collect()} == {i for i in ids if i % 10 != 3}


def test_windows_in_every_output_mode_and_dedup(spark, arriving, tmp_path):
    arriving(0, 1, 2, 3, 4, 5)
    arriving(2)  # again
    base = lambda: stream.event_stream(spark, arriving.path, 3)
    want = {(r["w_from"], r["n"]) for r in stream.live_counts(load(spark, SF, "events").withColumn("ts", F.col("ts").cast("timestamp")), "ts", "1 day").collect()}
    for mode in ("complete", "update"):
        once = stream.once(base(), "event_id", "ts", "40 days") if mode == "update" else base().dropDuplicates(["event_id"])
        counts = stream.live_counts(once, "ts", "1 day") if mode == "complete" else once.select("event_id", "ts")
        q = counts.writeStream.format("memory").queryName(f"counts_{mode}").outputMode("complete" if mode == "complete" else "append").trigger(availableNow=True).start()
        q.awaitTermination(240)
        rows = spark.table(f"counts_{mode}")
        if mode == "complete":
            assert {(r["w_from"], r["n"]) for r in rows.collect()} == want
        else:
            assert rows.count() == rows.select("event_id").distinct().count() == len(arriving.events)
    closed = stream.live_counts(base().withWatermark("ts", "1 hour"), "ts", "1 day")
    run(closed, f"file://{tmp_path}/closed", f"file://{tmp_path}/c3")
    assert 0 < spark.read.parquet(f"file://{tmp_path}/closed").count() <= len(want)


def test_overlapping_edges_of_two_streams(spark, tmp_path):
    rows = [("a", "k", 1, 5), ("b", "k", 4, 9), ("c", "k", 9, 12), ("d", "m", 2, 30), ("e", "m", 29, 31)]
    day = lambda c: F.expr(f"TIMESTAMP '2024-01-01' + make_dt_interval({c})")
    df = spark.createDataFrame(rows, "s string, o string, x int, y int").select("s", "o", day("x").alias("ts"), day("y").alias("te"))
    for name in ("l", "r"):
        df.coalesce(1).write.parquet(f"file://{tmp_path}/{name}")
    read = lambda n: spark.readStream.schema(df.schema).parquet(f"file://{tmp_path}/{n}")
    run(stream.overlap_stream_join(read("l"), read("r"), "o", "40 DAYS"), f"file://{tmp_path}/out", f"file://{tmp_path}/check")
    got = {(r["x"], r["y"]) for r in spark.read.parquet(f"file://{tmp_path}/out").collect()}
    assert got == {(r["x"], r["y"]) for r in stream.overlap_stream_join(df, df, "o", "40 DAYS").collect()} == {(x, x) for x in "abcde"} | {("a", "b"), ("b", "a"), ("d", "e"), ("e", "d")}


def test_delta_runs_of_a_stream_and_their_compaction(spark, tmp_path):
    base = spark.createDataFrame([("a", "p", "b", 1, 5), ("b", "p", "c", 2, 9)], "s string, p string, o string, ts long, te long")
    steps = [[("c", "p", "a", 3, 4, "insert"), ("a", "p", "b", 1, 5, "delete")], [("a", "p", "b", 1, 6, "insert")], [("c", "p", "a", 3, 4, "delete"), ("c", "p", "a", 3, 7, "insert")]]
    schema = "s string, p string, o string, ts long, te long, op string"
    folder, runs, check = f"file://{tmp_path}/changes", f"{tmp_path}/runs", f"file://{tmp_path}/check"
    for i, rows in enumerate(steps):
        spark.createDataFrame(rows, schema).coalesce(1).write.mode("append").parquet(folder)
        q = spark.readStream.schema(schema).parquet(folder).writeStream.foreachBatch(stream.apply_events(f"file://{runs}")).option("checkpointLocation", check).trigger(availableNow=True).start()
        q.awaitTermination(240)
    want = {("b", "p", "c", 2, 9), ("a", "p", "b", 1, 6), ("c", "p", "a", 3, 7)}
    assert {tuple(r) for r in stream.current(spark, base, f"file://{runs}").collect()} == want
    stream.compact(spark, base, f"file://{runs}", f"file://{tmp_path}/new")
    assert {tuple(r) for r in spark.read.parquet(f"file://{tmp_path}/new").select(*EDGE).collect()} == want


def test_new_edges_against_the_graph_in_a_stream(spark, tmp_path):
    g = graph(spark, SF, "SHIP")
    cut = F.lit("2000-01-01").cast("timestamp_ntz")
    old, new = g.of(g.frame.filter(F.col("ts") < cut)), g.frame.filter(F.col("ts") >= cut)
    q = parse("?x ships_R ?z @t ; ?y ships_A ?z @t")
    folder, out = f"file://{tmp_path}/new", f"file://{tmp_path}/answers"
    new.coalesce(1).write.parquet(folder)
    sink = stream.solve_batches(q, old, out)
    s = spark.readStream.schema(new.schema).parquet(folder).writeStream.foreachBatch(sink).option("checkpointLocation", f"file://{tmp_path}/check").trigger(availableNow=True).start()
    s.awaitTermination(240)
    got = spark.read.parquet(out).select("x", "z", "y", "t_from", "t_to")
    before = solve.solve(q, old, "JF")
    want = solve.solve(q, TemporalGraph(g.frame, g.time_type), "JF").select(*got.columns).exceptAll(before.select(*got.columns))
    assert sorted(map(str, got.collect())) == sorted(map(str, want.collect()))
