"""Variable-at-a-time evaluation with DataFrames: extend from the smallest child list, then intersect by semi-joins."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..model.graph import TemporalGraph
from ..model.query import Const, PatternQuery, TimeVar
from .pairwise import finish, fold, meets, scan


def step(rows: DataFrame | None, parts: dict[int, DataFrame], q: PatternQuery, v: str, bound: list[str]) -> DataFrame:
    """All extensions of the bindings by ``v``.

    Every pattern with ``v`` gives the number of children below its bound prefix; the least of them proposes its
    children, the other patterns then keep what they have too.
    """
    using = [i for i in parts if v in q.patterns[i].variables]
    tables = {i: parts[i].select(*[b for b in q.patterns[i].variables if b in bound], v).distinct() for i in using}
    if rows is None:
        first = using[0]
        out = tables[first]
        for i in using[1:]:
            out = out.join(tables[i], v, "left_semi") if v in tables[i].columns else out
        return out
    anchored = [i for i in using if len(tables[i].columns) > 1]
    if not anchored:
        out = rows.crossJoin(tables[using[0]])
        anchored, rest = [], using[1:]
    elif len(anchored) == 1:
        on = [c for c in tables[anchored[0]].columns if c != v]
        out, rest = rows.join(tables[anchored[0]], on), [i for i in using if i != anchored[0]]
    else:
        fans = rows
        for i in anchored:
            on = [c for c in tables[i].columns if c != v]
            fans = fans.join(tables[i].groupBy(*on).agg(F.count(F.lit(1)).alias(f"__f{i}")), on)
        least = F.least(*[F.col(f"__f{i}") for i in anchored])
        pick = F.lit(anchored[-1])
        for i in reversed(anchored[:-1]):
            pick = F.when(F.col(f"__f{i}") == least, i).otherwise(pick)
        fans = fans.withColumn("__pick", pick).drop(*[f"__f{i}" for i in anchored])
        out = None
        for i in anchored:
            on = [c for c in tables[i].columns if c != v]
            part = fans.filter(F.col("__pick") == i).join(tables[i], on)
            out = part if out is None else out.unionByName(part)
        out, rest = out.drop("__pick"), using
    for i in rest:
        out = out.join(tables[i], tables[i].columns, "left_semi")
    return out


def _closed(rows: DataFrame, part: DataFrame, q: PatternQuery, g: TemporalGraph, i: int, holds: dict, prune: bool, names: list[str]) -> DataFrame:
    """Joins pattern ``i``'s edges on those of its variables that the rows have, with overlap and clauses; ``holds`` is the
    first pattern of each time variable joined so far, which keeps its range."""
    t, bound = q.patterns[i].t, [v for v in names if v in q.patterns[i].variables]
    on = F.lit(True)
    for v in bound:
        part = part.withColumnRenamed(v, f"__{v}_c")
        on = on & (F.col(v) == F.col(f"__{v}_c"))
    if isinstance(t, TimeVar) and t in holds:
        j = holds[t]
        on = on & (F.col(f"__ts{j}") < F.col(f"__te{i}")) & (F.col(f"__ts{i}") < F.col(f"__te{j}"))
    for j in holds.values():
        if prune and (m := meets(q, g, i, j)) is not None:
            on = on & m
    out = rows.join(part, on).drop(*[f"__{v}_c" for v in bound])
    if not isinstance(t, TimeVar):
        return fold(out, i, None)
    return fold(out, i, holds[t]) if t in holds else out


def completing(rows: DataFrame, parts: dict[int, DataFrame], q: PatternQuery, g: TemporalGraph, v: str, bound: list[str], whole: list[int], holds: dict) -> DataFrame:
    """Extensions by ``v`` where it completes the patterns ``whole``, each of which has a bound variable: the one with the fewest
    children below a row's prefix proposes its edges, tested for overlap as they are joined, then the others join theirs."""
    rest = [i for i in parts if v in q.patterns[i].variables and i not in whole]
    keys = {i: [b for b in q.patterns[i].variables if b in bound] for i in whole}
    if len(whole) > 1:
        for i in whole:
            rows = rows.join(parts[i].groupBy(*keys[i]).agg(F.count(F.lit(1)).alias(f"__f{i}")), keys[i])
        least = F.least(*[F.col(f"__f{i}") for i in whole])
        pick = F.lit(whole[-1])
        for i in reversed(whole[:-1]):
            pick = F.when(F.col(f"__f{i}") == least, i).otherwise(pick)
        rows = rows.withColumn("__pick", pick).drop(*[f"__f{i}" for i in whole])
    out = None
    for first in whole:
        part = rows.filter(F.col("__pick") == first).drop("__pick") if len(whole) > 1 else rows
        held, names = dict(holds), list(bound)
        for i in [first, *[j for j in whole if j != first]]:
            part = _closed(part, parts[i], q, g, i, held, True, names)
            names = [*bound, v]
            if isinstance(q.patterns[i].t, TimeVar):
                held.setdefault(q.patterns[i].t, i)
        for t, i in held.items():  # one name for a range, whichever pattern proposed
            if t not in holds and i != (to := min(j for j in whole if q.patterns[j].t == t)):
                part = part.withColumnsRenamed({f"__ts{i}": f"__ts{to}", f"__te{i}": f"__te{to}"})
        out = part if out is None else out.unionByName(part)
    for i in rest:
        table = parts[i].select(*[b for b in q.patterns[i].variables if b in bound], v).distinct()
        out = out.join(table, table.columns, "left_semi")
    return out


def narrowed(parts: dict[int, DataFrame], q: PatternQuery, g: TemporalGraph, most: int = 1_000_000) -> dict[int, DataFrame]:
    """Parts of a stored graph without the edges that selective parts rule out: a part with a constant node, or one that was narrowed itself,
    is counted, and if it is small every larger part that shares nodes keeps those that it has, by broadcast semi-joins, before anything is shuffled."""
    if g.stats is None:
        return parts
    rows = {i: sum(r["rows"] for r in g.stats if not isinstance(p.p, Const) or r["p"] == str(p.p.value)) for i, p in enumerate(q.patterns)}
    parts, left = dict(parts), set(parts)
    ready = {i for i in parts if any(isinstance(x, Const) for x in (q.patterns[i].s, q.patterns[i].o))}
    while pool := [i for i in ready & left if rows[i] <= 20 * most]:
        i = min(pool, key=lambda i: (rows[i], i))
        left.discard(i)
        rows[i] = parts[i].count()
        if rows[i] > most:
            continue
        for j in left:
            shared = [v for v in q.patterns[j].variables if v in q.patterns[i].variables]
            if shared and rows[j] > rows[i]:
                parts[j] = parts[j].join(F.broadcast(parts[i].select(*shared).distinct()), shared, "left_semi")
                ready.add(j)
    return parts


def run(q: PatternQuery, g: TemporalGraph, order: list[str], prune: bool = True) -> DataFrame:
    """Solutions, one row for each combination of edges. Intervals join as soon as a pattern's nodes are bound, or, without ``prune``, at the end if the order has its time there."""
    parts = narrowed({i: scan(q, i, g) for i in range(len(q.patterns))}, q, g)
    nodes = [v for v in order if v in q.nodes]
    last = max([order.index(v) for v in nodes], default=-1)
    late = set() if prune else {t for t in q.times if t in order and order.index(t) > last}
    rows, bound, closed, holds = None, [], [], {}

    def close(rows: DataFrame | None, i: int) -> DataFrame:
        closed.append(i)
        out = parts[i] if rows is None else _closed(rows, parts[i], q, g, i, holds, prune, [v for v in bound if v in q.patterns[i].variables])
        if isinstance(q.patterns[i].t, TimeVar):
            holds.setdefault(q.patterns[i].t, i)
        return out

    for v in nodes:
        ready = [i for i, p in enumerate(q.patterns) if i not in closed and v in p.variables and set(p.variables) <= {*bound, v} and not (isinstance(p.t, TimeVar) and p.t.name in late)]
        whole = [i for i in ready if set(q.patterns[i].variables) - {v}]
        if prune and rows is not None and whole:
            rows = completing(rows, parts, q, g, v, bound, whole, holds)
            for i in sorted(whole):
                closed.append(i)
                if isinstance(q.patterns[i].t, TimeVar):
                    holds.setdefault(q.patterns[i].t, i)
        else:
            rows = step(rows, parts, q, v, bound)
        bound.append(v)
        for i in ready:
            if i not in closed:
                rows = close(rows, i)
    for i in range(len(q.patterns)):
        if i not in closed:
            rows = close(rows, i)
    return finish(rows, q, g)
