"""Times, wins, space, work and bounds."""

from __future__ import annotations

import threading
import time
from collections.abc import Callable

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..index.store import shared_folder
from ..index.tries import IndexHandle, build, plain, quads
from ..model.graph import TemporalGraph
from ..model.query import PatternQuery
from ..operators import cells
from ..operators.results import ends
from ..plans import bounds
from ..plans import order as plan

TIMING = "qid int, strategy string, ms double, rows long, timed_out boolean"


def describe(g: TemporalGraph) -> DataFrame:
    """N, U, T and labels of a graph, and the share of its most common label."""
    ends_ = g.frame.select(F.explode(F.array("ts", "te")).alias("at")).agg(F.countDistinct("at").alias("t"))
    terms = g.universe().agg(F.count(F.lit(1)).alias("u"))
    labels = g.frame.groupBy("p").agg(F.count(F.lit(1)).alias("k")).agg(F.sum("k").alias("n"), F.count(F.lit(1)).alias("labels"), F.max("k").alias("top_label"))
    return labels.crossJoin(terms).crossJoin(ends_).select("n", "u", "t", "labels", "top_label")


def expansion_size(g: TemporalGraph) -> DataFrame:
    """Rows of the point expansion, from ranks alone."""
    line = g.timeline()
    e = g.frame
    for c in ("ts", "te"):
        e = e.join(line.select(F.col("at").alias(c), F.col("tick").alias(f"{c}_tick")), c)
    return e.agg(F.sum(F.col("te_tick") - F.col("ts_tick")).cast("long").alias("points"))


def timed(run: Callable[[], DataFrame], limit: int | None = None, timeout: float | None = None) -> tuple[float, int, bool]:
    """(ms, rows, timed out) of counting a query's answers; a timer cancels the job group at the timeout."""
    began = time.perf_counter()
    try:
        df = run()
        spark = df.sparkSession
        group = f"timed-{id(df)}"
        spark.sparkContext.setJobGroup(group, "timed query", interruptOnCancel=True)
        timer = threading.Timer(timeout, lambda: spark.sparkContext.cancelJobGroup(group)) if timeout else None
        if timer:
            timer.start()
        try:
            n = (df.limit(limit) if limit else df).count()
        finally:
            if timer:
                timer.cancel()
        return (time.perf_counter() - began) * 1000, n, False
    except Exception as e:
        if timeout and "cancel" in str(e).lower():
            return timeout * 1000, 0, True
        raise


def boxplot(times: DataFrame) -> DataFrame:
    """Whiskers, quartiles and mean of each strategy."""
    q = F.percentile("ms", F.array(*[F.lit(x) for x in (0.0, 0.25, 0.5, 0.75, 1.0)]))
    return times.groupBy("strategy").agg(q.alias("q"), F.avg("ms").alias("mean")).select("strategy", *[F.col("q")[i].alias(n) for i, n in enumerate(("lower", "q1", "median", "q3", "upper"))], "mean")


def wins(times: DataFrame) -> DataFrame:
    """For each pair of strategies, the queries on which the first is faster; a column a rival."""
    a, b = times.alias("a"), times.alias("b")
    pairs = a.join(b, (F.col("a.qid") == F.col("b.qid")) & (F.col("a.strategy") != F.col("b.strategy")))
    return pairs.groupBy(F.col("a.strategy").alias("strategy")).pivot("b.strategy").agg(F.count_if(F.col("a.ms") < F.col("b.ms")))


def best(times: DataFrame) -> DataFrame:
    """Mean of the query-wise least time."""
    return times.groupBy("qid").agg(F.min("ms").alias("ms")).agg(F.avg("ms").alias("best_mean"))


def space(index: IndexHandle, n: int) -> DataFrame:
    """Bits and bytes of packed matrices for each order, per edge, and each order's share."""
    out = None
    for order, m in index.matrices.items():
        part = m.agg(F.sum(F.octet_length("b") + F.octet_length("e")).alias("bytes"), F.sum(F.when(F.col("level") == 0, F.col("n"))).alias("updates")).select(F.lit(order).alias("order"), "bytes", "updates")
        out = part if out is None else out.unionByName(part)
    total = out.agg(F.sum("bytes").alias("all"))
    return out.crossJoin(F.broadcast(total)).select("order", "bytes", "updates", (F.col("bytes") / n).alias("bytes_per_edge"), (F.col("bytes") / F.col("all")).alias("share"))


def table_space(g: TemporalGraph, orders: tuple[str, ...] = ("otps",)) -> DataFrame:
    """(kind, bytes, bytes_per_edge): stored tables of numbered edges in temporal orders, of the plain index in its
    orders, and the yardstick of five 32-bit numbers an edge."""
    spark = g.frame.sparkSession
    n = g.frame.count()
    path = shared_folder(spark, "space")
    numbered = TemporalGraph(g.encoded().withColumnsRenamed({"ts_tick": "ts", "te_tick": "te"}), "bigint")
    tables = {f"temporal {o}": quads(numbered, o) for o in orders} | {f"plain {o}": t for o, t in plain(g).items()}
    rows = [("packed 5 x 32 bit", 20 * n)]
    for kind, t in tables.items():
        where = f"{path}/{kind.replace(' ', '-')}"
        t.write.parquet(where)
        p = spark._jvm.org.apache.hadoop.fs.Path(where)
        rows.append((kind, p.getFileSystem(spark._jsc.hadoopConfiguration()).getContentSummary(p).getLength()))
    return spark.createDataFrame([(k, b, b / max(1, n)) for k, b in rows], "kind string, bytes long, bytes_per_edge double")


def matrix_bits(g: TemporalGraph, prefix_len: int, width: int) -> DataFrame:
    """Bits of all matrices below prefixes of a length: 2 * b * width for each of the two updates an edge makes."""
    b = 3 - prefix_len
    return g.frame.agg((F.count(F.lit(1)) * 2 * 2 * b * width).cast("long").alias("bits"))


def build_time(g: TemporalGraph, fractions: tuple[float, ...] = (0.25, 0.5, 1.0), orders: tuple[str, ...] = ("tspo", "ptso")) -> list[dict]:
    """Microseconds an edge to build and count the index on growing shares of the edges (by a hash of the triple)."""
    out = []
    for f in fractions:
        part = g.of(g.frame.filter(F.pmod(F.xxhash64("s", "p", "o"), F.lit(1000)) < int(1000 * f)))
        n = part.frame.count()
        began = time.perf_counter()
        index = build(part, orders)
        for t in [*index.tables.values(), *index.matrices.values()]:
            t.write.format("noop").mode("overwrite").save()
        s = time.perf_counter() - began
        out.append({"fraction": f, "edges": n, "s": s, "us_per_edge": s * 1e6 / max(1, n)})
    return out


def work(q: PatternQuery, g: TemporalGraph, strategy: str, cells_: int = 16) -> DataFrame:
    """Rows proposed and answers found by the local multiway evaluation, whatever the clock says."""
    q = plan.normalise(q)
    stats = plan.statistics(q, g)
    return cells.run(q, g, plan.greedy(q, stats, strategy), cells_, work=True, prune=strategy != "JF").agg(F.sum("proposals").cast("long").alias("proposals"), F.sum("answers").cast("long").alias("answers"))


def bound_ratio(q: PatternQuery, g: TemporalGraph, answers: int) -> float:
    """Answers (as bindings) over the bound from the distinct triples of each pattern."""
    row = bounds.sizes(q, g, "triples").first()
    top = bounds.agm(q, [row[f"n{i}"] for i in range(len(q.patterns))], times=False)
    return answers / top if top else 0.0


def range_columns(q: PatternQuery) -> list[str]:
    return [c for t in q.times for c in ends(t)]
