"""Pattern evaluation as a chain of joins in a chosen binding order, time anywhere in it."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..model.graph import TemporalGraph
from ..model.query import Const, PatternQuery, TimeVar
from ..plans.order import pattern_filter, pattern_order, time_position
from .overlap import bucket_of, graph_bounds, spread
from .results import apply_clauses, ends


def scan(q: PatternQuery, i: int, g: TemporalGraph) -> DataFrame:
    """Edges that match pattern ``i``: its variables as columns, and its interval as ``__ts{i}``, ``__te{i}``."""
    keep, seen = pattern_filter(q.patterns[i], g)
    df = g.frame.filter(keep)
    df = _bounded(df, q, i, g)
    return df.select(*[F.col(c).alias(v) for v, c in seen.items()], F.col("ts").alias(f"__ts{i}"), F.col("te").alias(f"__te{i}"))


def _bounded(df: DataFrame, q: PatternQuery, i: int, g: TemporalGraph) -> DataFrame:
    """Constant bounds of the pattern's time variable, as scan filters; what is left of an edge is its part within them."""
    t = q.patterns[i].t
    for c in q.clauses:
        if c.left == t and isinstance(t, TimeVar) and not isinstance(c.right, TimeVar):
            stop = g.shift(g.instant(c.right.value), c.offset + (0 if c.strict else 1))
            df = df.filter(F.col("ts") < stop).withColumn("te", F.least("te", stop))
        if c.right == t and isinstance(t, TimeVar) and not isinstance(c.left, TimeVar):
            start = g.shift(g.instant(c.left.value), -c.offset + (1 if c.strict else 0))
            df = df.filter(F.col("te") > start).withColumn("ts", F.greatest("ts", start))
    return df


def finish(df: DataFrame, q: PatternQuery, g: TemporalGraph) -> DataFrame:
    """Ranges of the time variables from the patterns' intervals, then clauses, then the solution columns."""
    for t in q.times:
        own = [i for i, p in enumerate(q.patterns) if p.t == TimeVar(t) and f"__ts{i}" in df.columns]
        a, b = ends(t)
        if own:
            lo, hi = [F.col(f"__ts{i}") for i in own], [F.col(f"__te{i}") for i in own]
            df = df.withColumn(a, lo[0] if len(lo) == 1 else F.greatest(*lo)).withColumn(b, hi[0] if len(hi) == 1 else F.least(*hi))
        else:  # only in clauses: ranges over the timeline
            df = df.crossJoin(F.broadcast(g.frame.agg(F.min("ts").alias(a), F.max("te").alias(b))))
    df = apply_clauses(df, q, g)
    return df.select(*q.nodes, *[c for t in q.times for c in ends(t)])


def fold(acc: DataFrame, i: int, into: int | None) -> DataFrame:
    """Takes pattern ``i``'s interval into that of ``into``, the first pattern of its time variable, so that rows carry
    one range a time variable however many patterns have it. None: nothing later looks at it."""
    if into is not None:
        acc = acc.withColumns({f"__ts{into}": F.greatest(f"__ts{into}", f"__ts{i}"), f"__te{into}": F.least(f"__te{into}", f"__te{i}")})
    return acc.drop(f"__ts{i}", f"__te{i}")


def few(q: PatternQuery, i: int, g: TemporalGraph, most: int = 100_000) -> bool:
    """Whether a stored graph's label statistics show that pattern ``i`` matches at most so many edges."""
    if g.stats is None:
        return False
    label = q.patterns[i].p
    return sum(r["rows"] for r in g.stats if not isinstance(label, Const) or r["p"] == str(label.value)) <= most


def mean_lengths(q: PatternQuery, g: TemporalGraph) -> int:
    """How many times the mean length of the edges that the patterns' labels have, by a stored graph's statistics, goes into its time span."""
    labels = {str(p.p.value) if isinstance(p.p, Const) else None for p in q.patterns}
    mine = [r for r in g.stats if None in labels or r["p"] in labels]
    length = sum(r["rows"] * (r["length"] or 0) for r in mine) / max(1, sum(r["rows"] for r in mine))
    return int(max((r["span"] or 0 for r in mine), default=0) / length) if length else 1


def meets(q: PatternQuery, g: TemporalGraph, i: int, j: int) -> Column | None:
    """What clauses between the time variables of patterns ``i`` and ``j`` ask of their intervals; None if nothing."""
    on = None
    for c in q.clauses:
        for a, b in ((i, j), (j, i)):
            if isinstance(c.left, TimeVar) and isinstance(c.right, TimeVar) and c.left != c.right and q.patterns[a].t == c.left and q.patterns[b].t == c.right:
                test = F.col(f"__ts{a}") < g.shift(F.col(f"__te{b}"), c.offset - (1 if c.strict else 0))
                on = test if on is None else on & test
    return on


def keyed(q: PatternQuery, patterns: list[int]) -> bool:
    """Whether each pattern in this order shares a node with those before it."""
    bound = set(q.patterns[patterns[0]].variables)
    for i in patterns[1:]:
        if not bound & set(q.patterns[i].variables):
            return False
        bound |= set(q.patterns[i].variables)
    return True


def pinned(q: PatternQuery) -> object | None:
    """The one instant, a unit of time long, that clauses with a constant leave to the time variable of all patterns; None if there is none."""
    times = {p.t for p in q.patterns}
    if len(times) != 1 or not isinstance(t := times.pop(), TimeVar) or q.times != [t.name]:
        return None
    plain = [c for c in q.clauses if not c.strict and not c.offset]
    lows = [c.left.value for c in plain if isinstance(c.left, Const) and c.right == t]
    return next((c.right.value for c in plain if c.left == t and isinstance(c.right, Const) and c.right.value in lows), None)


def dealt(df: DataFrame, g: TemporalGraph) -> DataFrame:
    """A first pattern's edges, dealt to as many tasks as the joins behind it should have."""
    spark = g.frame.sparkSession
    return df.repartition(max(4 * spark.sparkContext.defaultParallelism, int(spark.conf.get("spark.sql.shuffle.partitions"))))


def unfused(df: DataFrame, v: str) -> DataFrame:
    """The same rows. ``v`` goes through a function that Spark does not fuse: fused joins hold all rows that one row of their input
    leads to, with copies of each, before anything reads them, so their fan-outs multiply in memory."""
    return df.withColumn(v, F.when(F.exists(F.array(v), lambda x: x.isNotNull()), F.col(v)))


def paths(q: PatternQuery, i: int, j: int, parts: dict[int, DataFrame], sizes: dict, most: int = 300_000) -> DataFrame | None:
    """The joined edges of two patterns; None if there are more than ``most``, which is counted (once for patterns alike) and not estimated."""
    names: dict[str, int] = {}
    kind = tuple(x if isinstance(x, Const) else names.setdefault(x.name, len(names)) for k in (i, j) for _, x in q.patterns[k].terms)
    on = [v for v in parts[i].columns if v in parts[j].columns]
    if kind not in sizes:
        a, b = (parts[k].select(*on, *[F.lit(float(k == n)).alias(c) for c, n in (("__a", i), ("__b", j))]) for k in (i, j))
        each = a.unionByName(b).groupBy(*on).agg(F.sum("__a").alias("__a"), F.sum("__b").alias("__b"))
        sizes[kind] = each.agg(F.sum(F.col("__a") * F.col("__b"))).first()[0] or 0
    return parts[i].join(F.broadcast(parts[j]), on) if sizes[kind] <= most else None


def at_instant(q: PatternQuery, g: TemporalGraph, todo: list[int], at: object) -> DataFrame:
    """Solutions at one instant, by broadcast joins: each edge that is left is live there and its range within the clauses is that
    instant, so joins are on nodes alone. A pattern that binds a node and the next one, if that leads from the node back to bound ones, are joined
    with each other first (``paths``), so that no row is made that the second would drop. No more than two joins that bind a node are fused. If the
    last join binds nodes, its edges are joined as one list for each of the nodes it shares, and the lists are expanded at the end: rows are made
    once, by no join."""
    parts = {i: scan(q, i, g).drop(f"__ts{i}", f"__te{i}") for i in todo}
    steps, bound, sizes, left = [], set(), {}, list(todo)
    while left:
        i = left.pop(0)
        part, vs = parts[i], set(parts[i].columns)
        new = vs - bound
        if bound and new and left and new < (vs2 := set(parts[left[0]].columns)) and vs2 - new <= bound:
            if (both := paths(q, i, left[0], parts, sizes)) is not None:
                part, vs = both, vs | vs2
                left.pop(0)
        steps.append((part, vs & bound, new))
        bound |= vs
    fan = [n for n, (_, _, new) in enumerate(steps) if n and new]
    cut = {fan[k] for k in range(len(fan) - 2, 0, -2)}
    acc = dealt(steps[0][0], g)
    for n, (part, shared, new) in enumerate(steps[1:], 1):
        shared = [v for v in part.columns if v in shared]
        listed = n == len(steps) - 1 and bool(new)
        if listed:
            part = part.groupBy(*shared).agg(F.collect_list(F.struct(*[v for v in part.columns if v in new])).alias("__list"))
        acc = (unfused(acc, shared[0]) if n in cut else acc).join(F.broadcast(part), shared)
        if listed:
            acc = acc.select(*[c for c in acc.columns if c != "__list"], F.inline("__list"))
    first, t = todo[0], g.instant(at)
    return finish(acc.withColumns({f"__ts{first}": t.cast(g.time_type), f"__te{first}": g.shift(t, 1).cast(g.time_type)}), q, g)


def run(q: PatternQuery, g: TemporalGraph, order: list[str], buckets: int = 16, hint: str | None = None, prune: bool = True, scans: list[DataFrame] | None = None, cut_time: bool = True) -> DataFrame:
    """Solutions, one row for each combination of edges.

    A time variable that the order binds before a pattern's last node variable makes that pattern's join an
    overlap join; one bound first of all cuts the time axis into buckets, which lead every join key (without ``cut_time``
    only where some join has no shared node as its key). With a time
    variable at the end, ``prune`` still tests overlap in every join; without it (strict join-first) overlap is left to the last step.
    Patterns that a stored graph's statistics show to match few edges are broadcast. Where all are, buckets cost no shuffle: patterns
    of one time variable then have them whatever the order, about as long as a mean edge, and at least ``buckets`` of them; at a
    single instant they need none (``at_instant``).
    """
    at = time_position(q, order)
    first = [t for t in q.times if at[t] == 0 and any(p.t == TimeVar(t) for p in q.patterns)]
    lead = first[0] if len(first) == 1 and len(q.patterns) > 1 else None
    if not cut_time and keyed(q, pattern_order(q, order)):
        lead = None
    acc, bound, holds = None, set(), {}
    todo = pattern_order(q, order)
    small = {i: hint is None and few(q, i, g) for i in todo}
    if prune and scans is None and len(todo) > 1 and all(small.values()) and len({p.t for p in q.patterns}) == 1 and isinstance(q.patterns[0].t, TimeVar):
        if (instant := pinned(q)) is not None and keyed(q, todo):
            return at_instant(q, g, todo, instant)
        lead, buckets = q.patterns[0].t.name, max(buckets, min(256, mean_lengths(q, g)))
    bounds = graph_bounds(g, buckets) if lead else []
    for i in todo:
        part, t = scan(q, i, g) if scans is None else scans[i], q.patterns[i].t
        mine = lead is not None and t == TimeVar(lead)
        if mine:  # __s is the bucket of the start, __b each bucket that the edge touches
            part = part.withColumn(f"__s{i}", bucket_of(F.col(f"__ts{i}"), bounds, g.time_type))
            part = spread(part, f"__ts{i}", f"__te{i}", bounds, f"__b{i}")
        vs = q.patterns[i].variables
        if acc is None:
            acc = part
            if len(todo) > 1 and all(small.values()):  # nothing is shuffled after this, so the first edges alone decide on the number of tasks
                acc = dealt(acc, g)
        else:
            shared = [v for v in vs if v in bound]
            for v in shared:
                part = part.withColumnRenamed(v, f"__{v}_{i}")
            on = F.lit(True)
            for v in shared:
                on = on & (F.col(v) == F.col(f"__{v}_{i}"))
            peer = holds.get(t)
            if mine and peer is not None:
                on = on & (F.col(f"__b{peer}") == F.col(f"__b{i}"))
            early = isinstance(t, TimeVar) and (prune or at[t.name] < len(q.nodes))
            if peer is not None and (early or not shared):
                on = on & (F.col(f"__ts{peer}") < F.col(f"__te{i}")) & (F.col(f"__ts{i}") < F.col(f"__te{peer}"))
            tested = [m for j in holds.values() if prune and (m := meets(q, g, i, j)) is not None]
            for m in tested:
                on = on & m
            part = part.hint(hint) if hint else F.broadcast(part) if small[i] else part
            acc = acc.join(part, on).drop(*[f"__{v}_{i}" for v in shared], *([f"__b{i}"] if mine and peer is not None else []))
        bound |= set(vs)
        if not isinstance(t, TimeVar):
            acc = fold(acc, i, None)
        elif t in holds:
            acc = fold(acc, i, holds[t])
            if mine:
                acc = acc.withColumn(f"__s{holds[t]}", F.greatest(f"__s{holds[t]}", f"__s{i}")).drop(f"__s{i}")
        else:
            holds[t] = i
    if lead:  # a row counts in the bucket in which the latest of its edges starts
        i = holds[TimeVar(lead)]
        acc = acc.filter(F.col(f"__s{i}") == F.col(f"__b{i}")).drop(f"__b{i}", f"__s{i}")
    return finish(acc, q, g)
