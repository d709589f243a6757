"""A temporal graph: edges (s, p, o) valid over half-open intervals [ts, te), without redundant tuples."""

from __future__ import annotations

from dataclasses import dataclass, field
from functools import cached_property

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .ranks import ranked

EDGE = ["s", "p", "o", "ts", "te"]


def coalesce_edges(df: DataFrame, keys: tuple[str, ...] = ("s", "p", "o")) -> DataFrame:
    """Merges overlapping and touching intervals of equal triples: one shuffle and one sort, no shuffle where the edges lie by ``keys``
    already. Keys beyond the triple depend on it and stay as columns."""
    from pyspark.sql import Window

    w = Window.partitionBy(*keys).orderBy("ts", "te")
    reach = F.max("te").over(w.rowsBetween(Window.unboundedPreceding, -1))
    marked = df.filter(F.col("ts") < F.col("te")).withColumn("__reach", reach)
    marked = marked.withColumn("__new", F.col("__reach").isNull() | (F.col("ts") > F.col("__reach")))
    begun = F.last(F.when(F.col("__new"), F.col("ts")), ignorenulls=True).over(w.rowsBetween(Window.unboundedPreceding, 0))
    ends = marked.withColumns({"__begun": begun, "__end": F.coalesce(F.lead("__new").over(w), F.lit(True))}).filter("__end")
    return ends.select("s", "p", "o", F.col("__begun").alias("ts"), F.greatest("te", "__reach").alias("te"), *[k for k in keys if k not in EDGE])


def validate(df: DataFrame) -> tuple[DataFrame, DataFrame]:
    """(edges, rejects): an edge has no null and ends after it starts."""
    ok = F.col("ts") < F.col("te")
    for c in EDGE:
        ok = ok & F.col(c).isNotNull()
    ok = F.coalesce(ok, F.lit(False))
    return df.filter(ok), df.filter(~ok)


@dataclass(frozen=True)
class TemporalGraph:
    """Edges in original terms and instants; ranks and ids are derived only where a method needs them."""

    frame: DataFrame
    time_type: str
    #: Of a stored graph: number of label classes its folders have, and its rows of label statistics.
    labels: int = 0
    stats: tuple | None = field(default=None, compare=False)
    #: Of a stored graph: inner bounds of many parts of equal numbers of starts, as seconds or whole numbers.
    starts: tuple | None = field(default=None, compare=False)
    #: The edges before equal triples' intervals were merged, for estimates that need not wait for that shuffle.
    loose: DataFrame | None = field(default=None, compare=False)
    #: Those edges in parts that have no label in common, so that a store can be written a part at a time.
    parts: tuple[DataFrame, ...] | None = field(default=None, compare=False)

    @classmethod
    def from_edges(cls, df: DataFrame, s: str = "s", p: str = "p", o: str = "o", ts: str = "ts", te: str = "te", coalesce: bool = True) -> TemporalGraph:
        edges = df.select(*[F.col(c).cast("string").alias(n) for c, n in ((s, "s"), (p, "p"), (o, "o"))], F.col(ts).alias("ts"), F.col(te).alias("te"))
        edges = validate(edges)[0]
        kind = edges.schema["ts"].dataType.simpleString()
        return cls(coalesce_edges(edges) if coalesce else edges, kind, loose=edges if coalesce else None)

    @property
    def whole(self) -> bool:
        """Instants are whole numbers."""
        return self.time_type in ("int", "bigint", "smallint", "tinyint")

    def instant(self, value: object) -> Column:
        return F.lit(value) if self.whole else F.lit(str(value)).cast(self.time_type)

    def shift(self, at: Column, units: int) -> Column:
        """``at`` moved by time units: whole numbers, microseconds for timestamps, days for dates."""
        if units == 0:
            return at
        if self.whole:
            return at + F.lit(units)
        if self.time_type == "date":
            return F.date_add(at, units)
        return at + F.expr(f"make_dt_interval(0, 0, 0, CAST({units} / 1000000 AS DECIMAL(18, 6)))")

    def edges(self) -> DataFrame:
        return self.frame

    def of(self, frame: DataFrame) -> TemporalGraph:
        """Other edges with the same kind of time."""
        return TemporalGraph(frame, self.time_type)

    def part(self, keep: Column) -> TemporalGraph:
        """The edges that meet a condition; folders and statistics stay in use."""
        return TemporalGraph(self.frame.filter(keep), self.time_type, self.labels, self.stats, self.starts)

    def in_folder(self, label: str) -> Column:
        """Condition that a stored graph's edges of a label lie in its folder; no condition otherwise."""
        return F.col("label_class") == F.pmod(F.xxhash64(F.lit(label)), F.lit(self.labels)).cast("int") if self.labels else F.lit(True)

    def snapshot(self, t: object) -> DataFrame:
        at = self.instant(t)
        return self.frame.filter((F.col("ts") <= at) & (F.col("te") > at)).select("s", "p", "o")

    def touching(self, t1: object, t2: object) -> DataFrame:
        return self.frame.filter((F.col("ts") < self.instant(t2)) & (F.col("te") > self.instant(t1)))

    def touch(self, t1: object, t2: object) -> DataFrame:
        return self.touching(t1, t2).select("s", "p", "o").distinct()

    def persist_over(self, t1: object, t2: object) -> DataFrame:
        return self.frame.filter((F.col("ts") <= self.instant(t1)) & (F.col("te") >= self.instant(t2))).select("s", "p", "o")

    def ever(self) -> DataFrame:
        return self.frame.select("s", "p", "o").distinct()

    def at_least(self, units: int) -> TemporalGraph:
        long = self.length(F.col("ts"), F.col("te")) >= units
        if self.labels and units >= 1:  # shorter classes are not read
            long = long & (F.col("length_class") >= int(units).bit_length() - 1)
        return self.part(long)

    def length(self, a: Column, b: Column) -> Column:
        """b - a in time units, as a whole number."""
        if self.whole:
            return (b - a).cast("long")
        if self.time_type == "date":
            return F.datediff(b, a).cast("long")
        return F.unix_micros(b.cast("timestamp")) - F.unix_micros(a.cast("timestamp"))

    def transient(self, span: tuple | None = None) -> TemporalGraph:
        """Without the edges that are valid over the whole timeline."""
        if span is None:
            b = self.frame.agg(F.min("ts").alias("a"), F.max("te").alias("b"))
            return self.of(self.frame.crossJoin(F.broadcast(b)).filter((F.col("ts") > F.col("a")) | (F.col("te") < F.col("b"))).select(*EDGE))
        return self.of(self.frame.filter((F.col("ts") > self.instant(span[0])) | (F.col("te") < self.instant(span[1]))))

    def union(self, other: TemporalGraph) -> TemporalGraph:
        return self.of(coalesce_edges(self.frame.unionByName(other.frame)))

    def _sweep(self, other: TemporalGraph, keep) -> TemporalGraph:
        """Set algebra on point sets: running covers of both graphs along each triple's instants."""
        from pyspark.sql import Window

        events = None
        for side, g in (("x", self), ("y", other)):
            for at, sign in (("ts", 1), ("te", -1)):
                e = g.frame.select("s", "p", "o", F.col(at).alias("at"), F.lit(sign if side == "x" else 0).alias("x"), F.lit(sign if side == "y" else 0).alias("y"))
                events = e if events is None else events.union(e)
        per = events.groupBy("s", "p", "o", "at").agg(F.sum("x").alias("x"), F.sum("y").alias("y"))
        w = Window.partitionBy("s", "p", "o").orderBy("at")
        run = w.rowsBetween(Window.unboundedPreceding, 0)
        runs = per.select("s", "p", "o", F.col("at").alias("ts"), F.lead("at").over(w).alias("te"), F.sum("x").over(run).alias("x"), F.sum("y").over(run).alias("y"))
        return self.of(coalesce_edges(runs.filter(keep & F.col("te").isNotNull()).select(*EDGE)))

    def minus(self, other: TemporalGraph) -> TemporalGraph:
        return self._sweep(other, (F.col("x") > 0) & (F.col("y") == 0))

    def intersect(self, other: TemporalGraph) -> TemporalGraph:
        return self._sweep(other, (F.col("x") > 0) & (F.col("y") > 0))

    def universe(self) -> DataFrame:
        return self.frame.select(F.explode(F.array("s", "p", "o")).alias("term")).distinct()

    @cached_property
    def _times(self) -> DataFrame:
        return self.frame.select(F.explode(F.array("ts", "te")).alias("at")).distinct()

    def timeline(self) -> DataFrame:
        """(tick, at): instants with their rank, by parts of the axis and one count a part."""
        return ranked(self._times, "at", "tick")

    def dictionary(self) -> DataFrame:
        """(id, term): one universe for nodes and labels."""
        return ranked(self.universe(), "term", "id")

    def encoded(self) -> DataFrame:
        """(s, p, o, ts_tick, te_tick) as numbers."""
        d, out = self.dictionary(), self.frame
        for c in ("s", "p", "o"):
            out = out.join(d.select(F.col("id").alias(f"{c}_id"), F.col("term").alias(c)), c)
        t = self.timeline()
        for c in ("ts", "te"):
            out = out.join(t.select(F.col("tick").alias(f"{c}_tick"), F.col("at").alias(c)), c)
        return out.select(F.col("s_id").alias("s"), F.col("p_id").alias("p"), F.col("o_id").alias("o"), "ts_tick", "te_tick")

    def decode(self, encoded: DataFrame) -> DataFrame:
        d, t, out = self.dictionary(), self.timeline(), encoded
        for c in ("s", "p", "o"):
            out = out.join(d.select(F.col("id").alias(c), F.col("term").alias(f"{c}_term")), c).drop(c).withColumnRenamed(f"{c}_term", c)
        for c in ("ts", "te"):
            out = out.join(t.select(F.col("tick").alias(f"{c}_tick"), F.col("at").alias(c)), f"{c}_tick").drop(f"{c}_tick")
        return out.select(*EDGE)

    def floor(self, instants: DataFrame, at: str = "at") -> DataFrame:
        """Each instant with ``floor``, the last instant of the timeline that is not later (null before the first).

        An as-of join over buckets: the greatest instant up to a bucket's start comes from one row a bucket.
        """
        from ..operators.overlap import asof

        return asof(instants, self._times.withColumnRenamed("at", "floor"), [], at, "floor")

    def register(self, name: str) -> None:
        self.frame.createOrReplaceTempView(name)
