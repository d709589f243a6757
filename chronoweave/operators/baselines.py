"""Baselines: the expansion to points, the event sweep, the window join and the explicit clause table."""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from ..model.graph import TemporalGraph
from ..model.query import Const, OrderClause, PatternQuery, TimeVar
from ..plans.order import pattern_filter
from .cells import local_tables
from .leapfrog import Tables
from .overlap import bucket_bounds, bucket_of, spread
from .pairwise import run as pairwise
from .pairwise import scan
from .reduced import join_tree, reduce
from .results import canonicalise, ends


def point_expand(g: TemporalGraph) -> DataFrame:
    """(s, p, o, tick): a row for each edge and instant in its interval. Quadratic at worst; for small graphs only."""
    line = g.timeline()
    e = g.frame
    for c in ("ts", "te"):
        e = e.join(line.select(F.col("at").alias(c), F.col("tick").alias(f"{c}_tick")), c)
    return e.select("s", "p", "o", F.explode(F.sequence("ts_tick", F.col("te_tick") - 1)).alias("tick"))


def expanded(q: PatternQuery, g: TemporalGraph) -> DataFrame:
    """The query as plain equi-joins on the point expansion; ticks are put together to ranges at the end."""
    big = point_expand(g)
    acc, bound = None, set()
    for i, p in enumerate(q.patterns):
        if isinstance(p.t, Const):
            raise ValueError("give constant instants as clauses")
        keep, seen = pattern_filter(p, g)
        part = big.filter(keep).select(*[F.col(c).alias(v) for v, c in seen.items()], F.col("tick").alias(f"__{p.t.name}"))
        if acc is None:
            acc = part
        else:
            shared = [c for c in part.columns if c in bound]
            acc = acc.join(part, shared) if shared else acc.crossJoin(part)
        bound |= set(part.columns)
    acc = acc.distinct()
    for c in q.clauses:
        if not (isinstance(c.left, TimeVar) and isinstance(c.right, TimeVar)) or c.offset:
            raise ValueError("the expansion takes clauses between time variables")
        a, b = F.col(f"__{c.left.name}"), F.col(f"__{c.right.name}")
        acc = acc.filter(a < b if c.strict else a <= b)
    if len(q.times) != 1:
        return acc
    t = q.times[0]
    a, b = ends(t)
    w = Window.partitionBy(*q.nodes).orderBy(f"__{t}")
    runs = acc.withColumn("__g", F.col(f"__{t}") - F.row_number().over(w)).groupBy(*q.nodes, "__g").agg(F.min(f"__{t}").alias("__a"), (F.max(f"__{t}") + 1).alias("__b"))
    line = g.timeline()
    runs = runs.join(line.select(F.col("tick").alias("__a"), F.col("at").alias(a)), "__a").join(line.select(F.col("tick").alias("__b"), F.col("at").alias(b)), "__b")
    return runs.select(*q.nodes, a, b)


def _snapshots(q: PatternQuery, names: list[str], order: list[str]):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        table = pa.Table.from_batches(list(batches))
        lo, hi = table.column("lo")[0].as_py(), table.column("hi")[0].as_py()
        tables, terms = local_tables(table, q)
        cuts = np.unique(np.concatenate([*tables.starts, *tables.stops, [lo, hi]]))
        cuts = cuts[(cuts >= lo) & (cuts <= hi)]
        for a, b in zip(cuts[:-1], cuts[1:], strict=True):  # the whole pattern anew whenever the edge set changes
            live = [(x <= a) & (y > a) for x, y in zip(tables.starts, tables.stops, strict=True)]
            if not all(m.any() for m in live):
                continue
            now = Tables(q, [{v: c[m] for v, c in cols.items()} for cols, m in zip(tables.cols, live, strict=True)], [x[m] for x, m in zip(tables.starts, live, strict=True)], [y[m] for y, m in zip(tables.stops, live, strict=True)], tables.base)
            rows, n = {}, 1
            for v in order:
                rows, n = now.bind(rows, n, v)
            if n:
                yield pa.RecordBatch.from_arrays([*[pa.array(terms[rows[v]]) for v in q.nodes], pa.array(np.full(n, a)), pa.array(np.full(n, b))], names)

    return run


def sweep(q: PatternQuery, g: TemporalGraph, units: int = 1, buckets: int | None = None) -> DataFrame:
    """Event sweep for one shared time variable: the pattern on the snapshot of every elementary interval.

    The axis is cut into buckets, edges are copied to the buckets they touch, and ranges that go on over a cut or
    an event are put together again; ranges shorter than ``units`` are dropped. A cyclic pattern is solved a variable at a
    time; of an acyclic one, edges that no solution can use are dropped by semi-joins first, so fewer events are swept.
    """
    t = q.times[0]
    scans = [scan(q, i, g) for i in range(len(q.patterns))]
    if join_tree(q) is not None:
        scans = reduce(q, scans)
    bounds = bucket_bounds(g.frame.select("ts"), "ts", buckets)
    r = g.frame.agg(F.min("ts").alias("a"), F.max("te").alias("b")).withColumns({"a": g.length(g.instant(0), F.col("a")) if g.whole else F.unix_micros(F.col("a").cast("timestamp")), "b": g.length(g.instant(0), F.col("b")) if g.whole else F.unix_micros(F.col("b").cast("timestamp"))}).first()
    scale = 1 if g.whole else 1_000_000
    inner = [int(round(x * scale)) for x in bounds]
    edges = F.array(*[F.lit(int(x)).cast("long") for x in [r["a"] or 0, *inner, r["b"] or 0]])
    out = None
    for i, p in enumerate(q.patterns):
        vs = p.variables
        part = spread(scans[i], f"__ts{i}", f"__te{i}", bounds)
        a, b = F.col(f"__ts{i}"), F.col(f"__te{i}")
        if not g.whole:
            a, b = F.unix_micros(a.cast("timestamp")), F.unix_micros(b.cast("timestamp"))
        part = part.select("__bucket", F.lit(i).alias("i"), *[(F.col(vs[k]) if k < len(vs) else F.lit(None).cast("string")).alias(f"v{k}") for k in range(3)], a.cast("long").alias("a"), b.cast("long").alias("b"))
        out = part if out is None else out.unionByName(part)
    out = out.withColumn("lo", edges[F.col("__bucket")]).withColumn("hi", edges[F.col("__bucket") + 1])
    a, b = ends(t)
    schema = ", ".join([f"`{v}` string" for v in q.nodes] + [f"`{a}` long", f"`{b}` long"])
    got = out.groupBy("__bucket").applyInArrow(_snapshots(q, [*q.nodes, a, b], q.nodes), schema)
    got = canonicalise(got, q.nodes, t).filter(F.col(b) - F.col(a) >= units)
    return got if g.whole else got.withColumns({c: F.timestamp_micros(c).cast(g.time_type) for c in (a, b)})


def window_join(q: PatternQuery, g: TemporalGraph, lo: object, hi: object) -> DataFrame:
    """Fixed-order pairwise overlap join of the edges that touch the closed window [lo, hi]."""
    t = q.patterns[0].t
    q = q.with_clauses(OrderClause(Const(lo), t), OrderClause(t, Const(hi)))
    return pairwise(q, g, [t.name, *q.nodes])


def clause_table(g: TemporalGraph) -> DataFrame:
    """All pairs of instants (w1 <= w2): the relation that stands for a clause in the proof; quadratic, for tiny timelines."""
    line = g.timeline()
    return line.select(F.col("at").alias("w1"), F.col("tick").alias("a")).join(line.select(F.col("at").alias("w2"), F.col("tick").alias("b")), F.col("a") <= F.col("b")).select("w1", "w2")


__all__ = ["bucket_of", "clause_table", "expanded", "point_expand", "sweep", "window_join"]
