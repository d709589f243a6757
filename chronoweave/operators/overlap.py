"""Joins on time: overlap with and without an equi key, point in interval, as-of, elementary buckets."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..model.ranks import literals, part_of


def bucket_bounds(df: DataFrame, at: str, buckets: int | None = None, rows_each: int = 100_000) -> list:
    """Inner bounds of about equal numbers of starts; without ``buckets`` as many as keep a bucket at ``rows_each`` starts,
    from 8 to 4,096. One value a bound reaches the driver."""
    if buckets is None:
        buckets = min(4096, max(8, -(-df.count() // rows_each)))
    share = [i / buckets for i in range(1, buckets)]
    kind = df.schema[at].dataType.simpleString()
    num = F.col(at).cast("timestamp").cast("double") if kind.startswith("timestamp") else F.col(at).cast("double")
    got = df.agg(F.percentile_approx(num, share, max(2000, 4 * buckets)).alias("q")).first()["q"] if share else []
    return sorted(set(got or []))


def graph_bounds(g, buckets: int) -> list:
    """Inner bounds of a graph's starts: of a stored graph as many as are wanted of those it keeps, else from its edges."""
    if g.starts:
        return sorted({g.starts[len(g.starts) * i // buckets] for i in range(1, buckets)})
    return bucket_bounds(g.frame.select("ts"), "ts", buckets)


def bucket_of(at: Column, bounds: list, kind: str) -> Column:
    """Number of bounds not later than the instant, looked up in two steps."""
    num = at.cast("timestamp").cast("double") if kind.startswith("timestamp") else at.cast("double")
    return part_of(num, [float(b) for b in bounds], "double")


def spread(df: DataFrame, ts: str, te: str, bounds: list, name: str = "__bucket") -> DataFrame:
    """One copy of each interval in every bucket that it touches."""
    kind = df.schema[ts].dataType.simpleString()
    last = bucket_of(F.col(te), bounds, kind)
    # an interval that ends on a bound does not reach into that bucket
    num = F.col(te).cast("timestamp").cast("double") if kind.startswith("timestamp") else F.col(te).cast("double")
    on = F.exists(literals([float(b) for b in bounds], "double").cast("array<double>"), lambda b: b == num)
    return df.withColumn(name, F.explode(F.sequence(bucket_of(F.col(ts), bounds, kind), last - on.cast("int"))))


def overlap_join(left: DataFrame, right: DataFrame, on: list[str], lrange: tuple[str, str], rrange: tuple[str, str], buckets: int | None = None) -> DataFrame:
    """Rows whose half-open ranges meet. Columns of both sides stay; ``on`` columns appear once.

    With an equi key the overlap is a residual of the hash or merge join. Without one, both sides are spread over
    time buckets, joined on the bucket, and a pair counts in the bucket that holds the later start, so none doubles.
    """
    meet = (F.col(lrange[0]) < F.col(rrange[1])) & (F.col(rrange[0]) < F.col(lrange[1]))
    if on:
        r = right
        for c in on:
            r = r.withColumnRenamed(c, f"__r_{c}")
        cond = meet
        for c in on:
            cond = cond & (F.col(c) == F.col(f"__r_{c}"))
        return left.join(r, cond).drop(*[f"__r_{c}" for c in on])
    bounds = bucket_bounds(left.select(F.col(lrange[0]).alias("at")).union(right.select(F.col(rrange[0]).alias("at"))), "at", buckets)
    kind = left.schema[lrange[0]].dataType.simpleString()
    a, b = spread(left, *lrange, bounds, "__lb"), spread(right, *rrange, bounds, "__rb")
    owner = bucket_of(F.greatest(lrange[0], rrange[0]), bounds, kind) == F.col("__lb")
    return a.join(b, (F.col("__lb") == F.col("__rb")) & meet).filter(owner).drop("__lb", "__rb")


def point_join(points: DataFrame, at: str, intervals: DataFrame, ts: str, te: str, buckets: int | None = None) -> DataFrame:
    """Each point with the intervals that hold it: a bucket equi-join with the test as residual."""
    bounds = bucket_bounds(intervals.select(F.col(ts).alias("at")), "at", buckets)
    kind = intervals.schema[ts].dataType.simpleString()
    a = points.withColumn("__lb", bucket_of(F.col(at), bounds, kind))
    return a.join(spread(intervals, ts, te, bounds, "__rb"), (F.col("__lb") == F.col("__rb")) & (F.col(ts) <= F.col(at)) & (F.col(te) > F.col(at))).drop("__lb", "__rb")


def asof(left: DataFrame, right: DataFrame, on: list[str], at: str, stamp: str, buckets: int | None = None) -> DataFrame:
    """Each left row with the greatest ``stamp`` of the right side that is not later than ``at``.

    Without a key the axis is cut into buckets: the last stamp of all earlier buckets is carried over by a window
    over one row a bucket, and the merge within a bucket is a window over that bucket alone.
    """
    from pyspark.sql import Window

    bounds = bucket_bounds(right.select(F.col(stamp).alias("at")), "at", buckets)
    kind = right.schema[stamp].dataType.simpleString()
    l = left.withColumn("__b", bucket_of(F.col(at), bounds, kind))  # noqa: E741
    r = right.select(*on, F.col(stamp), bucket_of(F.col(stamp), bounds, kind).alias("__b"))
    last = r.groupBy(*on, "__b").agg(F.max(stamp).alias("__last"))
    grid = last.filter(F.col("__b") < len(bounds)).select(*on, F.explode(F.sequence(F.col("__b") + 1, F.lit(len(bounds)))).alias("__b"), "__last").groupBy(*on, "__b").agg(F.max("__last").alias("__carry"))
    rows = l.select("*", F.col(at).alias("__at"), F.lit(None).cast(right.schema[stamp].dataType).alias("__stamp"), F.lit(1).alias("__left"))
    marks = r.select(*[F.col(c) if c in (*on, "__b") else F.lit(None).cast(l.schema[c].dataType).alias(c) for c in l.columns], F.col(stamp).alias("__at"), F.col(stamp).alias("__stamp"), F.lit(0).alias("__left"))
    w = Window.partitionBy(*on, "__b").orderBy("__at", "__left").rowsBetween(Window.unboundedPreceding, 0)
    merged = rows.unionByName(marks).withColumn("__in", F.max("__stamp").over(w)).filter("__left = 1")
    out = merged.join(F.broadcast(grid) if not on else grid, [*on, "__b"], "left")
    return out.withColumn(stamp, F.coalesce("__in", "__carry")).drop("__b", "__at", "__stamp", "__left", "__in", "__carry")
