"""SQL functions, Arrow functions and table functions over temporal graphs."""

from __future__ import annotations

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.types import ArrayType, LongType, StructField, StructType

from ..model.graph import TemporalGraph
from ..model.query import TimeVar, Var, parse

RANGES = ArrayType(StructType([StructField("from", LongType()), StructField("to", LongType())]))


def register(spark: SparkSession, g: TemporalGraph, name: str) -> None:
    """The graph as a view, the interval predicates as SQL functions, the seek as a table function."""
    g.register(name)
    kind = g.time_type.upper()
    spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION overlaps(a {kind}, b {kind}, c {kind}, d {kind}) RETURNS BOOLEAN RETURN a < d AND c < b")
    spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION valid_at(a {kind}, b {kind}, t {kind}) RETURNS BOOLEAN RETURN a <= t AND t < b")
    spark.udtf.register("seek_children", seek_children)
    spark.udtf.register("seek_below", seek_below)
    spark.udtf.register("pattern", pattern)


class _Seek:
    """Least value >= x of each partition's sorted children, by binary search."""

    def __init__(self) -> None:
        self.values: list[int] = []
        self.x = 0

    def eval(self, row, x: int) -> None:
        self.values.append(row["child"])
        self.x = x

    def terminate(self):
        v = np.unique(np.array(self.values, np.int64))
        i = int(np.searchsorted(v, self.x))
        if i < len(v):
            yield (int(v[i]),)


seek_children = F.udtf(_Seek, returnType="child long")


class _SeekBelow(_Seek):
    """The same for each partition of a table (p, child); the label comes with the answer."""

    def eval(self, row, x: int) -> None:
        super().eval(row, x)
        self.p = row["p"]

    def terminate(self):
        for (child,) in super().terminate():
            yield self.p, child


seek_below = F.udtf(_SeekBelow, returnType="p string, child long")


class _Pattern:
    """The quads and clauses of a pattern in text form, one row each."""

    def eval(self, text: str):
        q = parse(text)
        say = lambda x: f"?{x.name}" if isinstance(x, Var) else f"@{x.name}" if isinstance(x, TimeVar) else str(x.value)
        for i, p in enumerate(q.patterns):
            yield "quad", i, say(p.s), say(p.p), say(p.o), say(p.t), 0, False
        for i, c in enumerate(q.clauses):
            yield "clause", i, say(c.left), None, say(c.right), None, c.offset, c.strict


pattern = F.udtf(_Pattern, returnType="kind string, place int, s string, p string, o string, t string, shift long, strict boolean")


def solve_view(spark: SparkSession, text: str, view: str, into: str, **options) -> DataFrame:
    """Solutions of a pattern text over an edge view (s, p, o, ts, te), also as a view of their own for further SQL."""
    from ..operators.solve import solve

    edges = spark.table(view)
    out = solve(text, TemporalGraph(edges, edges.schema["ts"].dataType.simpleString()), **options)
    out.createOrReplaceTempView(into)
    return out


def interval_relation(a: Column, b: Column, c: Column, d: Column) -> Column:
    """Which of the thirteen relations holds between [a, b) and [c, d)."""
    return (
        F.when(b < c, "before").when(d < a, "after").when(b == c, "meets").when(d == a, "met_by")
        .when((a == c) & (b == d), "equals").when((a == c) & (b < d), "starts").when((a == c) & (b > d), "started_by")
        .when((b == d) & (a > c), "finishes").when((b == d) & (a < c), "finished_by")
        .when((a > c) & (b < d), "during").when((a < c) & (b > d), "contains")
        .when(a < c, "overlaps").otherwise("overlapped_by")
    )


def _pairs(x) -> np.ndarray:
    return np.array([(r["from"], r["to"]) for r in (x if x is not None else ())], np.int64).reshape(-1, 2)


@F.pandas_udf(RANGES)
def interval_intersect(x: pd.Series, y: pd.Series) -> pd.Series:
    """Common parts of two sorted lists of disjoint ranges."""
    out = []
    for a, b in zip(x, y, strict=True):
        p, q = _pairs(a), _pairs(b)
        lo, hi = np.maximum(p[:, None, 0], q[None, :, 0]), np.minimum(p[:, None, 1], q[None, :, 1])
        keep = lo < hi
        out.append([{"from": int(u), "to": int(v)} for u, v in sorted(zip(lo[keep].tolist(), hi[keep].tolist(), strict=True))])
    return pd.Series(out)


def interval_intersect_sql(x: Column, y: Column) -> Column:
    """The same as built-in functions."""
    cut = F.flatten(F.transform(x, lambda a: F.transform(F.filter(y, lambda b: (a["from"] < b["to"]) & (b["from"] < a["to"])), lambda b: F.struct(F.greatest(a["from"], b["from"]).alias("from"), F.least(a["to"], b["to"]).alias("to")))))
    return F.array_sort(cut)


@F.pandas_udf(RANGES)
def coalesce_ranges(ts: pd.Series, te: pd.Series) -> list:
    """Aggregate: the union of intervals as sorted disjoint ranges."""
    order = np.lexsort((te.to_numpy(), ts.to_numpy()))
    a, b = ts.to_numpy()[order], te.to_numpy()[order]
    reach = np.maximum.accumulate(b)
    fresh = np.concatenate(([True], a[1:] > reach[:-1]))
    first = np.flatnonzero(fresh)
    last = np.append(first[1:], len(a)) - 1
    return [{"from": int(a[i]), "to": int(reach[j])} for i, j in zip(first, last, strict=True)]


def merge_intersect(left: DataFrame, right: DataFrame, key: str) -> DataFrame:
    """Common children of two child tables under each key, a merge of two sorted groups (reference kernel)."""

    def both(x: pa.Table, y: pa.Table) -> pa.Table:
        k = (x if x.num_rows else y).column(key)[0].as_py()
        got = np.intersect1d(x.column("child").to_numpy().astype(str), y.column("child").to_numpy().astype(str))
        return pa.table({key: pa.array([k] * len(got), pa.string()), "child": pa.array(got.tolist(), pa.string())})

    return left.groupBy(key).cogroup(right.groupBy(key)).applyInArrow(both, f"{key} string, child string")


def solutions_as_map(df: DataFrame, nodes: list[str]) -> DataFrame:
    """A solution as one map from variable to term; other columns stay."""
    pairs = [x for v in nodes for x in (F.lit(v), F.col(v))]
    return df.select(F.create_map(*pairs).alias("solution"), *[c for c in df.columns if c not in nodes])


__all__ = ["coalesce_ranges", "interval_intersect", "interval_intersect_sql", "interval_relation", "merge_intersect", "register", "solutions_as_map"]
