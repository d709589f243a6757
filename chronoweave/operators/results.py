"""Solutions: ranges of time variables, order clauses, canonical form, counts without expansion."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from ..model.graph import TemporalGraph
from ..model.query import PatternQuery, TimeVar


def ends(t: str) -> tuple[str, str]:
    return f"{t}_from", f"{t}_to"


def _most(f, cols: list[Column]) -> Column:
    return cols[0] if len(cols) == 1 else f(*cols)


def apply_clauses(df: DataFrame, q: PatternQuery, g: TemporalGraph) -> DataFrame:
    """Tightens the ranges by all clauses until nothing can move (once a time variable, plus one), keeps non-empty ones.

    The first variable bound is not restricted by the second, which then stays on its side of the clause.
    """
    if q.unsatisfiable:
        return df.filter(F.lit(False))
    for _ in range(len(q.times)) if q.clauses else ():
        moves: dict[str, list[Column]] = {}
        for c in q.clauses:
            less = c.offset - (1 if c.strict else 0)
            if isinstance(c.left, TimeVar) and isinstance(c.right, TimeVar):
                moves.setdefault(f"{c.right.name}_from", []).append(g.shift(F.col(f"{c.left.name}_from"), -less))
                moves.setdefault(f"{c.left.name}_to", []).append(g.shift(F.col(f"{c.right.name}_to"), less))
            elif isinstance(c.left, TimeVar):
                moves.setdefault(f"{c.left.name}_to", []).append(g.shift(g.instant(c.right.value), less + 1))
            elif isinstance(c.right, TimeVar):
                moves.setdefault(f"{c.right.name}_from", []).append(g.shift(g.instant(c.left.value), -less))
        df = df.withColumns({k: _most(F.greatest if k.endswith("_from") else F.least, [F.col(k), *v]) for k, v in moves.items()})
    keep = F.lit(True)
    for t in q.times:
        a, b = ends(t)
        keep = keep & (F.col(a) < F.col(b))
    return df.filter(keep)


def canonicalise(df: DataFrame, keys: list[str], t: str = "t") -> DataFrame:
    """Merges overlapping and touching ranges of equal bindings."""
    a, b = ends(t)
    w = Window.partitionBy(*keys).orderBy(a, b)
    reach = F.max(b).over(w.rowsBetween(Window.unboundedPreceding, -1))
    marked = df.withColumn("__new", (reach.isNull() | (F.col(a) > reach)).cast("int"))
    grouped = marked.withColumn("__g", F.sum("__new").over(w.rowsBetween(Window.unboundedPreceding, 0)))
    return grouped.groupBy(*keys, "__g").agg(F.min(a).alias(a), F.max(b).alias(b)).drop("__g")


def points(df: DataFrame, g: TemporalGraph, t: str = "t") -> DataFrame:
    """Expanded form: one row for each instant of the timeline in a range."""
    from .overlap import point_join

    a, b = ends(t)
    at = g.timeline().select(F.col("at").alias(t))
    return point_join(at, t, df, a, b).drop(a, b)


def count_points(df: DataFrame, g: TemporalGraph, t: str = "t") -> DataFrame:
    """Number of expanded solutions, from the ranks of the ends alone."""
    a, b = ends(t)
    line = g.timeline()
    x = df.join(line.select(F.col("at").alias(a), F.col("tick").alias("__x")), a).join(line.select(F.col("at").alias(b), F.col("tick").alias("__y")), b)
    return x.agg(F.coalesce(F.sum(F.col("__y") - F.col("__x")), F.lit(0)).cast("long").alias("points"))


def count_pairs(df: DataFrame, g: TemporalGraph, first: str = "t1", second: str = "t2", ordered: bool = True) -> DataFrame:
    """Number of expanded solutions of two time variables, ``first`` not after ``second`` if ``ordered``, from ranks alone.

    A row stands for the instants (i, j) with i in [a, b) and j in [c, d). Those i below c meet all j; of the others each meets
    the j from itself on, which is an arithmetic series.
    """
    line, x = g.timeline(), df
    for k, col in zip("abcd", [*ends(first), *ends(second)], strict=True):
        x = x.join(line.select(F.col("at").alias(col), F.col("tick").alias(f"__{k}")), col)
    a, b, c, d = (F.col(f"__{k}") for k in "abcd")
    below = F.greatest(F.least(b, c) - a, F.lit(0)) * (d - c)
    lo, hi = F.greatest(a, c), F.least(b, d)
    series = F.when(lo < hi, ((hi - lo) * ((d - lo) + (d - hi + 1)) / 2).cast("long")).otherwise(0)
    pairs = below + series if ordered else (b - a) * (d - c)
    return x.agg(F.coalesce(F.sum(pairs), F.lit(0)).cast("long").alias("points"))


def as_arrays(df: DataFrame, keys: list[str], t: str = "t") -> DataFrame:
    """All ranges of a binding in one sorted array."""
    a, b = ends(t)
    return df.groupBy(*keys).agg(F.array_sort(F.collect_list(F.struct(F.col(a).alias("from"), F.col(b).alias("to")))).alias("ranges"))
