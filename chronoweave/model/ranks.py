"""Order-preserving parts with bounds taken once, and ranks and running sums over them.

Range partitions of an exchange sample their bounds anew whenever they are computed, so two branches of a plan, or a
task that is run again, can disagree on them. Here the bounds are values read before the plan is made: the values
of least hash are a uniform sample that depends on the data alone.
"""

from __future__ import annotations

import math

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F


def split_points(values: DataFrame, column: str, parts: int | None = None, each: int = 32) -> list:
    """Bounds of about equally many values: at most ``parts`` - 1 of them, from ``each`` sampled values a part."""
    parts = parts or int(values.sparkSession.conf.get("spark.sql.shuffle.partitions"))
    drawn = values.select(F.col(column).alias("v")).filter("v IS NOT NULL").orderBy(F.xxhash64("v"), "v").limit(each * parts)
    got = sorted(r["v"] for r in drawn.collect())
    return sorted({got[len(got) * i // parts] for i in range(1, parts)}) if got else []


def _literal(value: object, kind: str) -> Column:
    plain = kind in ("string", "tinyint", "smallint", "int", "bigint", "double")
    return F.lit(value).cast(kind) if plain or value is None else F.lit(str(value)).cast(kind)


def literals(values: list, kind: str) -> Column:
    """An array of constants; doubles are parsed from one text, as a call a constant is slow for hundreds of them."""
    if kind == "double" and values and all(map(math.isfinite, values)):
        return F.expr(f"array({', '.join(f'{float(v)!r}D' for v in values)})")
    return F.array(*[_literal(v, kind) for v in values])


def part_of(at: Column, points: list, kind: str) -> Column:
    """Number of bounds that are not later than the value, looked up in two steps of about the root of their number."""
    if not points:
        return F.lit(0)
    width = math.isqrt(len(points) - 1) + 1 if len(points) > 1 else 1
    every, heads = literals(points, kind), literals(points[::width], kind)
    passed = lambda a: F.size(F.filter(a, lambda b: b <= at))
    first = F.greatest(passed(heads) - 1, F.lit(0)) * width
    found = F.transform(F.array(first), lambda f: f + passed(F.slice(every, f + 1, F.lit(width))))[0]
    return F.coalesce(found, F.lit(0))  # never null, so no filter on it is inferred below windows


def ranked(values: DataFrame, column: str, rank: str) -> DataFrame:
    """(rank, column): dense ranks from 0 of distinct values. A part's values are ordered among themselves; the parts'
    counts, one number each, reach the driver and give the offsets."""
    return running(values.select(column), [], [column], {}, row="__row").select((F.col("__row") - 1).alias(rank), column)


def running(df: DataFrame, group: list[str], order: list[str], sums: dict[str, str], row: str | None = None, follow: str | None = None) -> DataFrame:
    """Inclusive running sums (new column -> summed one) in the order of ``order`` within ``group``, in parts of its first column.

    ``row`` numbers the rows from 1; ``follow`` is the next row's first order column (null behind the last). No group is
    sorted by one task, only its rows of a part. Totals of the parts are a few numbers on the driver where there is no
    group; with groups they are joined, and windows over them see a row for each part of a group.
    """
    lead = order[0]
    kind = df.schema[lead].dataType.simpleString()
    points = split_points(df, lead)
    dealt = df.withColumn("__p", part_of(F.col(lead), points, kind))
    per = dealt.groupBy(*group, "__p").agg(F.count(F.lit(1)).alias("__n"), F.min(lead).alias("__first"), *[F.sum(c).alias(f"__s_{k}") for k, c in sums.items()])
    inner = Window.partitionBy(*group, "__p").orderBy(*order)
    run = inner.rowsBetween(Window.unboundedPreceding, 0)
    out = dealt.withColumns({f"__x_{k}": F.sum(c).over(run) for k, c in sums.items()} | {"__row": F.row_number().over(inner), "__lead": F.lead(lead).over(inner)})
    names = ["__n", *[f"__s_{k}" for k in sums]]
    if group:
        parts = Window.partitionBy(*group).orderBy("__p")
        past = parts.rowsBetween(Window.unboundedPreceding, -1)
        base = per.select(*[F.col(c).alias(f"__g{i}") for i, c in enumerate(group)], F.col("__p").alias("__q"), F.lead("__first").over(parts).alias("__next"), *[F.coalesce(F.sum(c).over(past), F.lit(0)).alias(f"__b{c}") for c in names])
        on = F.col("__p") == F.col("__q")
        for i, c in enumerate(group):
            on = on & (F.col(c) == F.col(f"__g{i}"))
        out = out.join(base, on)
        before, after = {c: F.col(f"__b{c}") for c in names}, F.col("__next")
    else:
        rows = {r["__p"]: r for r in per.collect()}
        total = {c: [0] for c in names}
        for i in range(len(points) + 1):
            for c in names:
                total[c].append(total[c][-1] + (rows[i][c] or 0 if i in rows else 0))
        firsts = [next((rows[j]["__first"] for j in range(i + 1, len(points) + 1) if j in rows), None) for i in range(len(points) + 1)]
        before = {c: F.array(*[F.lit(int(v)).cast("long") for v in total[c]])[F.col("__p")] for c in names}
        after = F.array(*[_literal(v, kind) for v in firsts])[F.col("__p")]
    made = [(F.col(f"__x_{k}") + before[f"__s_{k}"]).cast("long").alias(k) for k in sums]
    if row:
        made.append((F.col("__row") + before["__n"]).cast("long").alias(row))
    if follow:
        made.append(F.coalesce(F.col("__lead"), after).alias(follow))
    return out.select(*df.columns, *made)
