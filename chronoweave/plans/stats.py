"""Fan-out statistics of the permutations: how many children the nodes of each prefix have."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..model.graph import TemporalGraph

#: prefix -> next component, for prefixes of one and two components.
PREFIXES = [(a, b) for a in ("s", "p", "o") for b in ("s", "p", "o") if a != b] + [("sp", "o"), ("so", "p"), ("po", "s")]


def fanout(g: TemporalGraph, prefixes: list[tuple[str, str]] | None = None, exact: bool = True) -> DataFrame:
    """(prefix, nodes, children, widest): one aggregate a prefix; sketches instead of exact counts at scale."""
    count = F.countDistinct if exact else F.approx_count_distinct
    base, out = g.ever(), None
    for a, b in prefixes or PREFIXES:
        part = base.groupBy(*a).agg(count(F.col(b)).alias("k")).agg(F.count(F.lit(1)).alias("nodes"), F.sum("k").cast("long").alias("children"), F.max("k").alias("widest"))
        part = part.select(F.lit(f"{a}>{b}").alias("prefix"), "nodes", "children", "widest")
        out = part if out is None else out.unionByName(part)
    return out


def label_stats(g: TemporalGraph) -> DataFrame:
    """(p, rows, subjects, objects, pairs, length, span, instants): what least-children needs to know of each label.

    One pass with sketches for distinct counts, one row a label; ``span`` and ``instants`` are the label's own.
    """
    e = g.frame
    length = g.length(F.col("ts"), F.col("te"))
    per = e.groupBy("p").agg(
        F.count(F.lit(1)).alias("rows"), F.approx_count_distinct("s").alias("subjects"), F.approx_count_distinct("o").alias("objects"),
        F.approx_count_distinct(F.struct("s", "o")).alias("pairs"),
        F.avg(length).alias("length"), F.min("ts").alias("first"), F.max("te").alias("last"), F.approx_count_distinct("ts").alias("instants"),
    )
    return per.select("p", "rows", "subjects", "objects", "pairs", "length", g.length(F.col("first"), F.col("last")).alias("span"), "instants")
