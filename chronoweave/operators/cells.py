"""One-round evaluation: edges are dealt to a grid of cells by shares of the join variables, each cell is solved locally."""

from __future__ import annotations

from collections.abc import Iterator
from datetime import datetime
from itertools import product

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..model.graph import TemporalGraph
from ..model.query import PatternQuery
from ..plans.order import statistics
from .leapfrog import Tables, narrow
from .pairwise import scan


def shares(q: PatternQuery, sizes: list[int], cells: int) -> dict[str, int]:
    """Whole shares of the join variables that copy the fewest rows with at most ``cells`` cells; of those, the most cells."""
    join = [v for v in q.nodes if sum(v in p.variables for p in q.patterns) > 1]
    best, cost = {v: 1 for v in join}, (float("inf"), 0, 0)
    steps = [h for h in (1, 2, 3, 4, 6, 8, 12, 16, 24, 32, 64, 128, 256, 512, 1024) if h <= cells]
    if len(join) > 3:
        steps = [h for h in steps if h & (h - 1) == 0][:6]
    for pick in product(steps, repeat=min(len(join), 5)):
        used = int(np.prod(pick)) if pick else 1
        if used > cells or used * 2 < cells and len(join):
            continue
        h = dict(zip(join, pick, strict=False)) | {v: 1 for v in join[5:]}
        copies = sum(n * np.prod([h[v] for v in join if v not in p.variables]) for n, p in zip(sizes, q.patterns, strict=True))
        if (rank := (copies, -used, max(pick, default=1))) < cost:
            best, cost = h, rank
    return best


def _load(q: PatternQuery, sizes: list[int], h: dict[str, int]) -> float:
    """Mean edges of a cell: each pattern's edges are spread over the shares of its own variables."""
    return sum(n / np.prod([h.get(v, 1) for v in p.variables]) for n, p in zip(sizes, q.patterns, strict=True))


def _micros(value: object) -> int:
    return value if isinstance(value, int) else int((value - datetime(1970, 1, 1)).total_seconds() * 1_000_000)


def dealt(q: PatternQuery, g: TemporalGraph, h: dict[str, int]) -> DataFrame:
    """(cell, i, v0, v1, v2, a, b): every pattern's edges with the cells they go to."""
    out = None
    for i, p in enumerate(q.patterns):
        df, vs = scan(q, i, g), p.variables
        a, b = F.col(f"__ts{i}"), F.col(f"__te{i}")
        if not g.whole:
            a, b = F.unix_micros(a.cast("timestamp")), F.unix_micros(b.cast("timestamp"))
        cell = F.lit(0)
        free = [v for v in h if v not in vs and h[v] > 1]
        for v in free:
            df = df.withColumn(f"__c_{v}", F.explode(F.sequence(F.lit(0), F.lit(h[v] - 1))))
        for v in h:
            at = F.lit(0) if h[v] == 1 else (F.pmod(F.xxhash64(v), F.lit(h[v])) if v in vs else F.col(f"__c_{v}"))
            cell = cell * h[v] + at.cast("int")
        cols = [F.col(vs[k]) if k < len(vs) else F.lit(None).cast("string") for k in range(3)]
        part = df.select(cell.alias("cell"), F.lit(i).alias("i"), *[c.alias(f"v{k}") for k, c in enumerate(cols)], a.cast("long").alias("a"), b.cast("long").alias("b"))
        out = part if out is None else out.unionByName(part)
    return out


def local_tables(table: pa.Table, q: PatternQuery) -> tuple[Tables, np.ndarray]:
    """Arrays of one cell; terms get numbers that hold within it."""
    i = table.column("i").to_numpy()
    flat = [np.asarray(table.column(f"v{k}").fill_null("").to_numpy(zero_copy_only=False), dtype=object) for k in range(3)]
    terms, code = np.unique(np.concatenate(flat).astype(str), return_inverse=True)
    code = code.reshape(3, -1).astype(np.int64)
    a, b = table.column("a").to_numpy(), table.column("b").to_numpy()
    cols, starts, stops = [], [], []
    for j, p in enumerate(q.patterns):
        mine = i == j
        cols.append({v: code[k][mine] for k, v in enumerate(p.variables)})
        starts.append(a[mine])
        stops.append(b[mine])
    return Tables(q, cols, starts, stops, len(terms)), terms


def _kernel(q: PatternQuery, order: list[str], names: list[str], span: tuple[int, int], work: bool, prune: bool, adaptive: bool):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        tables, terms = local_tables(pa.Table.from_batches(list(batches)), q)
        rows, n = tables.solve_adaptive(order) if adaptive else tables.solve(order, prune)
        keep = narrow(rows, q, _micros, span) if n else np.zeros(0, bool)
        got = {k: c[keep] for k, c in rows.items()} if n else {}
        size = int(keep.sum())
        if work:
            yield pa.RecordBatch.from_arrays([pa.array([tables.proposals]), pa.array([size])], ["proposals", "answers"])
        elif size:
            cols = [pa.array(terms[got[c]]) if c in q.nodes else pa.array(got[c], pa.int64()) for c in names]
            yield pa.RecordBatch.from_arrays(cols, names)

    return run


def run(q: PatternQuery, g: TemporalGraph, order: list[str], cells: int | None = None, work: bool = False, prune: bool = True, adaptive: bool = False, sizes: list[int] | None = None, rows_each: int = 2_000_000) -> DataFrame:
    """Solutions by one replicated shuffle. A result's join variables name its cell, so none is found twice.

    Each cell holds about rows * copies / cells edges and is solved in memory; without ``cells`` there are as many as keep
    that below ``rows_each``, 16 at least. ``sizes`` (edges of each pattern) decide the shares; they are counted where not
    given. ``adaptive`` gives each partial binding an order of its own.
    """
    if sizes is None:
        sizes = [max(1, s.rows) for s in statistics(q, g)]
    if cells is None:
        cells = 16
        while cells < 1 << 16 and _load(q, sizes, shares(q, sizes, cells)) > rows_each:
            cells *= 2
    h = shares(q, sizes, cells)
    times = [f"{t}_{e}" for t in q.times for e in ("from", "to")]
    names = [*q.nodes, *times]
    span = (0, 0)
    if any(not any(p.t == x for p in q.patterns) for c in q.clauses for x in (c.left, c.right) if hasattr(x, "name")):
        r = g.frame.agg(F.min("ts"), F.max("te")).first()
        span = (_micros(r[0]), _micros(r[1])) if r[0] is not None else (0, 0)
    schema = "proposals long, answers long" if work else ", ".join([f"`{v}` string" for v in q.nodes] + [f"`{c}` long" for c in times])
    out = dealt(q, g, h).groupBy("cell").applyInArrow(_kernel(q, order, names, span, work, prune, adaptive), schema)
    if work or g.whole:
        return out
    return out.withColumns({c: F.timestamp_micros(c).cast(g.time_type) for c in times})
