"""Acyclic patterns: a join tree, semi-joins up and down it, then the joins themselves."""

from __future__ import annotations

from pyspark.sql import DataFrame

from ..model.graph import TemporalGraph
from ..model.query import PatternQuery
from . import pairwise


def join_tree(q: PatternQuery) -> list[tuple[int, int | None]] | None:
    """(pattern, parent) with leaves first, by removing ears: a pattern whose shared variables all lie in another one.

    The last has no parent. None if some patterns form a cycle. A pattern that shares nothing has any other one as parent.
    """
    left, out = {i: set(p.variables) for i, p in enumerate(q.patterns)}, []
    while len(left) > 1:
        for i, mine in left.items():
            shared = {v for v in mine if any(v in o for j, o in left.items() if j != i)}
            parent = next((j for j, o in left.items() if j != i and shared <= o), None)
            if parent is not None:
                out.append((i, parent))
                del left[i]
                break
        else:
            return None
    return [*out, (next(iter(left)), None)]


def reduce(q: PatternQuery, scans: list[DataFrame]) -> list[DataFrame]:
    """Each pattern's edges that can be part of a timeless solution: semi-joins from the leaves up, then down again."""
    tree = join_tree(q)
    if tree is None:
        raise ValueError("semi-joins alone do not reduce a cyclic pattern")
    parts = list(scans)

    def cut(i: int, by: int) -> None:
        on = [v for v in q.patterns[i].variables if v in q.patterns[by].variables]
        if on:
            parts[i] = parts[i].join(parts[by].select(*on).distinct(), on, "left_semi")

    for i, parent in tree:
        if parent is not None:
            cut(parent, i)
    for i, parent in reversed(tree):
        if parent is not None:
            cut(i, parent)
    return parts


def run(q: PatternQuery, g: TemporalGraph, order: list[str]) -> DataFrame:
    """Solutions of an acyclic pattern, a row for each combination of edges, from reduced scans."""
    return pairwise.run(q, g, order, scans=reduce(q, [pairwise.scan(q, i, g) for i in range(len(q.patterns))]))
