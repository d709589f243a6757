"""Version queries: listing matches and their ranges in a window, differences and logs of changes, sizes over time."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..model.graph import TemporalGraph
from ..model.query import PatternQuery
from ..model.ranks import running
from ..plans.order import pattern_filter


def list_matches(q: PatternQuery, g: TemporalGraph, t1: object, t2: object) -> DataFrame:
    """Triples of a single pattern that exist at some instant of [t1, t2)."""
    keep, _ = pattern_filter(q.patterns[0], g)
    return g.touching(t1, t2).filter(keep).select("s", "p", "o").distinct()


def list_ranges(q: PatternQuery, g: TemporalGraph, t1: object, t2: object, as_array: bool = False) -> DataFrame:
    """Maximal validity ranges of each match, clipped to the window."""
    keep, _ = pattern_filter(q.patterns[0], g)
    out = g.touching(t1, t2).filter(keep).select("s", "p", "o", F.greatest("ts", g.instant(t1)).alias("t_from"), F.least("te", g.instant(t2)).alias("t_to"))
    if not as_array:
        return out
    return out.groupBy("s", "p", "o").agg(F.array_sort(F.collect_list(F.struct("t_from", "t_to"))).alias("ranges"))


def changes(g: TemporalGraph, t1: object, t2: object) -> DataFrame:
    """Inserts (+1) and deletes (-1) with t1 <= instant < t2."""
    e = g.frame.select("s", "p", "o", F.col("ts").alias("at"), F.lit(1).alias("sign")).union(g.frame.select("s", "p", "o", "te", F.lit(-1)))
    return e.filter((F.col("at") >= g.instant(t1)) & (F.col("at") < g.instant(t2)))


def diff(g: TemporalGraph, t1: object, t2: object) -> DataFrame:
    """Triples added or removed from the version at t1 to that at t2: linear in the events of (t1, t2].

    A triple that comes and goes within the window has no net change and is left out.
    """
    a, b = g.instant(t1), g.instant(t2)
    e = g.frame.select("s", "p", "o", F.col("ts").alias("at"), F.lit(1).alias("sign")).union(g.frame.select("s", "p", "o", "te", F.lit(-1)))
    net = e.filter((F.col("at") > a) & (F.col("at") <= b)).groupBy("s", "p", "o").agg(F.sum("sign").alias("net"))
    return net.filter("net <> 0").select("s", "p", "o", F.when(F.col("net") > 0, "added").otherwise("removed").alias("change"))


def snapshot_sizes(g: TemporalGraph) -> DataFrame:
    """(at, live): number of edges from each instant on.

    Net changes are summed for each instant first; the running sum is taken in parts of the time axis on top of the parts' totals.
    """
    e = g.frame.select(F.col("ts").alias("at"), F.lit(1).alias("d")).union(g.frame.select("te", F.lit(-1)))
    net = e.groupBy("at").agg(F.sum("d").alias("d"))
    return running(net, [], ["at"], {"live": "d"}).select("at", "live")
