"""Shape queries: stars, chains, circles, diamond, cliques, with labels read from one embedding or given."""

from __future__ import annotations

import random
from datetime import datetime, timedelta

from pyspark.sql import functions as F

from ..model.graph import TemporalGraph
from ..model.query import Const, OrderClause, PatternQuery, QuadPattern, TimeVar, Var


def arcs(shape: str) -> list[tuple[int, int]]:
    """Directed arcs between numbered nodes. An n-star and an n-chain have n arcs, an n-circle n nodes."""
    kind, n = shape.rstrip("0123456789"), int("".join(c for c in shape if c.isdigit()) or 0)
    if kind == "star":
        return [(0, i) for i in range(1, n + 1)]
    if kind == "chain":
        return [(i, i + 1) for i in range(n)]
    if kind == "circle":
        return [(i, (i + 1) % n) for i in range(n)]
    if kind == "diamond":
        return [(0, 1), (1, 3), (0, 2), (2, 3)]
    if kind == "clique":
        return [(i, j) for i in range(n) for j in range(i + 1, n)]
    raise ValueError(f"unknown shape {shape!r}")


SHAPES = [f"{k}{n}" for k in ("star", "chain", "circle") for n in (3, 4, 5)] + ["diamond", "clique4", "clique5"]


def shape_query(shape: str, labels: list[str]) -> PatternQuery:
    t = TimeVar("t")
    return PatternQuery(tuple(QuadPattern(Var(f"x{a}"), Const(p), Var(f"x{b}"), t) for (a, b), p in zip(arcs(shape), labels, strict=True)))


def sample_labels(g: TemporalGraph, shape: str, at: object, seed: int, edges: int = 2000) -> list[str] | None:
    """Labels of one embedding of the shape among the edges live at an instant; None if a bounded sample shows none.

    The sample is ``edges`` edges in an order by hash: it picks a query, never an answer.
    """
    got = g.snapshot(at).orderBy(F.xxhash64("s", "p", "o", F.lit(seed))).limit(edges).collect()
    rng, out = random.Random(seed), {}
    for r in got:
        out.setdefault(r["s"], []).append((r["o"], r["p"]))

    def extend(i: int, nodes: dict[int, str], labels: list[str]) -> list[str] | None:
        todo = arcs(shape)
        if i == len(todo):
            return labels
        a, b = todo[i]
        starts = [nodes[a]] if a in nodes else sorted(out)
        rng.shuffle(starts)
        for s in starts:
            options = list(out.get(s, ()))
            rng.shuffle(options)
            for o, p in options:
                if b in nodes and nodes[b] != o:
                    continue
                if (done := extend(i + 1, {**nodes, a: s, b: o}, [*labels, p])) is not None:
                    return done
        return None

    return extend(0, {}, [])


def windows(lo: datetime, hi: datetime, share: float, n: int, seed: int) -> list[tuple[datetime, datetime]]:
    """Random windows that cover a share of the time span."""
    rng = random.Random(seed)
    width = (hi - lo) * share
    return [(a := lo + (hi - lo - width) * rng.random(), a + width) for _ in range(n)]


def two_times(q: PatternQuery, seed: int) -> PatternQuery:
    """Patterns at one of two instants each, both used, with ``t1 <= t2``."""
    rng = random.Random(seed)
    pick = [rng.choice(("t1", "t2")) for _ in q.patterns]
    if len(set(pick)) == 1:
        pick[rng.randrange(len(pick))] = "t2" if pick[0] == "t1" else "t1"
    patterns = tuple(QuadPattern(p.s, p.p, p.o, TimeVar(x)) for p, x in zip(q.patterns, pick, strict=True))
    return PatternQuery(patterns, (OrderClause(TimeVar("t1"), TimeVar("t2")),))


def month(lo: str = "2024-01-01", days: int = 30) -> tuple[datetime, datetime]:
    a = datetime.fromisoformat(lo)
    return a, a + timedelta(days=days)
