"""Worst-case bound of a query: the least fractional edge cover weighted by log sizes, by an exact simplex."""

from __future__ import annotations

import math
from fractions import Fraction

from pyspark.sql import functions as F

from ..model.graph import TemporalGraph
from ..model.query import PatternQuery, TimeVar
from .order import pattern_filter


def cover(vertices: list[str], edges: list[set[str]], costs: list[float]) -> tuple[list[Fraction], float]:
    """Weights x >= 0 that minimise costs . x with every vertex covered at least once.

    Solves the dual (most weight on vertices with no edge above its cost) by Bland's rule; the weights are its prices.
    """
    c = [Fraction(max(0.0, x)).limit_denominator(10**9) for x in costs]
    n, m = len(vertices), len(edges)
    rows = [[Fraction(int(v in e)) for v in vertices] + [Fraction(int(i == j)) for j in range(m)] + [c[i]] for i, e in enumerate(edges)]
    goal = [Fraction(-1)] * n + [Fraction(0)] * (m + 1)
    basis = [n + i for i in range(m)]
    while True:
        enter = next((j for j in range(n + m) if goal[j] < 0), None)
        if enter is None:
            break
        ratio = [(rows[i][-1] / rows[i][enter], basis[i], i) for i in range(m) if rows[i][enter] > 0]
        if not ratio:
            raise ValueError("a variable is in no pattern")
        i = min(ratio)[2]
        pivot = rows[i][enter]
        rows[i] = [x / pivot for x in rows[i]]
        for k in range(m):
            if k != i and rows[k][enter]:
                f = rows[k][enter]
                rows[k] = [x - f * y for x, y in zip(rows[k], rows[i], strict=True)]
        f = goal[enter]
        goal = [x - f * y for x, y in zip(goal, rows[i], strict=True)]
        basis[i] = enter
    return goal[n : n + m], float(goal[-1])


def agm(q: PatternQuery, sizes: list[int], times: bool = True) -> float:
    """Most solutions any graph with these pattern sizes can give; time variables count as vertices if ``times``."""
    if any(s <= 0 for s in sizes):
        return 0.0
    edges = [set(p.variables) | ({f"@{p.t.name}"} if times and isinstance(p.t, TimeVar) else set()) for p in q.patterns]
    vertices = sorted(set().union(*edges))
    if not vertices:
        return 1.0
    return math.exp(cover(vertices, edges, [math.log(s) for s in sizes])[1])


def sizes(q: PatternQuery, g: TemporalGraph, mode: str = "expansion"):
    """One row with the size of each pattern's relation: points of the expansion, edges, or distinct triples."""
    df = g.frame
    if mode == "expansion":
        line = g.timeline()
        for c in ("ts", "te"):
            df = df.join(line.select(F.col("at").alias(c), F.col("tick").alias(f"{c}_tick")), c)
    aggs = []
    for i, p in enumerate(q.patterns):
        keep, _ = pattern_filter(p, g)
        if mode == "expansion":
            aggs.append(F.coalesce(F.sum(F.when(keep, F.col("te_tick") - F.col("ts_tick"))), F.lit(0)).cast("long").alias(f"n{i}"))
        elif mode == "triples":
            aggs.append(F.countDistinct(F.when(keep, F.struct("s", "p", "o"))).alias(f"n{i}"))
        else:
            aggs.append(F.count(F.when(keep, 1)).alias(f"n{i}"))
    return df.agg(*aggs)
