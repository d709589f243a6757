"""Front door: evaluate a pattern query by strategy and route."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..model.graph import TemporalGraph
from ..model.query import Const, OrderClause, PatternQuery, TimeVar, parse
from ..plans import order as plan
from . import baselines, cells, generic, pairwise, reduced
from .results import canonicalise

ROUTES = ("pairwise", "generic", "reduced", "cells", "sweep", "expanded")


def connected(q: PatternQuery) -> bool:
    """Whether shared nodes, shared times and clauses hold all patterns together."""
    groups: list[set[str]] = []
    sets = [{*p.variables, *([f"@{p.t.name}"] if isinstance(p.t, TimeVar) else [])} for p in q.patterns]
    sets += [{f"@{x.name}" for x in (c.left, c.right) if isinstance(x, TimeVar)} for c in q.clauses]
    for s in filter(None, sets):
        met = [x for x in groups if x & s]
        groups = [x for x in groups if not x & s] + [s.union(*met)]
    return len(groups) <= 1


def cyclic(q: PatternQuery) -> bool:
    """Whether the patterns' variables cannot be reduced ear by ear (shared time left aside)."""
    return reduced.join_tree(q) is None


def solve(q: PatternQuery | str, g: TemporalGraph, strategy: str = "LC", route: str = "auto", order: list[str] | None = None, form: str = "ranges", limit: int | None = None, time_estimate: str = "span_over_children", cells_: int | None = None, buckets: int = 16, products: bool = False, strict: bool = False) -> DataFrame:
    """Solutions of a query.

    ``strategy`` (JF, TF, LC) or an explicit ``order`` says when variables are bound; ``route`` how: a chain of joins,
    one variable at a time, semi-joins first (acyclic patterns), one replicated shuffle, or the baselines. ``LC_adaptive``
    chooses anew for each partial binding, within cells. Joins test overlap as soon as they can; ``strict`` join-first leaves it to the
    last step (the baseline, whose joins on nodes alone outgrow the answers). Patterns that nothing connects are refused unless ``products``. ``form``: ``ranges`` (a row for each combination of
    edges), ``canonical`` (ranges of a binding merged; one time variable), ``bindings`` (nodes alone, distinct).
    """
    q, stats = plan.normalise(parse(q) if isinstance(q, str) else q), None
    if order is None:
        if strategy in ("LC", "LC_adaptive"):
            stats = plan.statistics(q, g)
            order = plan.greedy(q, stats, "LC", time_estimate)
        else:
            flat = [plan.PatternStats(1, {v: 1 for v in p.variables}, 1.0, 1) for p in q.patterns]
            order = plan.greedy(q, flat, strategy)
    if not products and not connected(q):
        raise ValueError("nothing connects some of the patterns: their product has to be asked for (products=True)")
    prune = not (strict and strategy == "JF")
    if strategy == "LC_adaptive":
        route = "cells" if route == "auto" else route
        if route != "cells":
            raise ValueError("an order for each partial binding is kept within cells only")
    if strategy == "TF" and len(q.times) > 1 and route == "pairwise":
        raise ValueError("time-first with several time variables costs the product of their timelines")
    if route == "auto":
        route = "generic" if cyclic(q) and len(q.patterns) > 3 else "pairwise"
    if route == "pairwise":
        out = pairwise.run(q, g, order, buckets, prune=prune, cut_time=strategy == "TF")
    elif route == "generic":
        out = generic.run(q, g, order, prune)
    elif route == "reduced":
        out = reduced.run(q, g, order)
    elif route == "cells":
        out = cells.run(q, g, order, cells_, prune=prune, adaptive=strategy == "LC_adaptive", sizes=[max(1, s.rows) for s in stats] if stats else None)
    elif route == "sweep":
        out = baselines.sweep(q, g, buckets=buckets)
    elif route == "expanded":
        out = baselines.expanded(q, g)
    else:
        raise ValueError(f"unknown route {route!r}; one of {ROUTES}")
    if form == "canonical":
        out = canonicalise(out, q.nodes, q.times[0])
    elif form == "bindings":
        out = out.select(*q.nodes).distinct()
    return out.limit(limit) if limit else out


def all_instants(triples: str | PatternQuery, g: TemporalGraph, **options) -> DataFrame:
    """Return-all-instants: every pattern at one shared time variable."""
    q = parse(triples) if isinstance(triples, str) else triples
    return solve(q.with_time(TimeVar("t")), g, **options)


def timeless(q: PatternQuery, triples: DataFrame, g: TemporalGraph) -> DataFrame:
    """Bindings on a plain graph of distinct triples, by joins on nodes alone."""
    frame = triples.select("s", "p", "o", g.instant(0 if g.whole else "2000-01-01").alias("ts"), g.instant(1 if g.whole else "2000-01-02").alias("te"))
    return solve(q.with_time(TimeVar("t")), g.of(frame), strategy="JF", route="pairwise", form="bindings")


def snapshot(q: PatternQuery, g: TemporalGraph, t: object) -> DataFrame:
    return timeless(q, g.snapshot(t), g)


def during_any(q: PatternQuery, g: TemporalGraph, t1: object, t2: object) -> DataFrame:
    return timeless(q, g.touch(t1, t2), g)


def during_all(q: PatternQuery, g: TemporalGraph, t1: object, t2: object) -> DataFrame:
    return timeless(q, g.persist_over(t1, t2), g)


def ever(q: PatternQuery, g: TemporalGraph) -> DataFrame:
    return timeless(q, g.ever(), g)


def within(q: PatternQuery, g: TemporalGraph, lo: object, hi: object, **options) -> DataFrame:
    """One shared instant in the closed window [lo, hi]; ranges are clipped to it."""
    t = TimeVar("t")
    return solve(q.with_time(t).with_clauses(OrderClause(Const(lo), t), OrderClause(t, Const(hi))), g, **options)


def durable(q: PatternQuery, g: TemporalGraph, units: int, **options) -> DataFrame:
    """Ranges of at least ``units`` in which all patterns hold. Shorter edges cannot take part and are dropped first."""
    q = q.with_time(TimeVar("t"))
    out = solve(q, g.at_least(units), form="canonical", **({"strategy": "JF"} | options))
    return out.filter(g.length(F.col("t_from"), F.col("t_to")) >= units)
