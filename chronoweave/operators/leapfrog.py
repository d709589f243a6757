"""Local multiway evaluation on sorted arrays: seeks, intersections, ranges, and whole patterns at once.

``intersect`` and ``intersect_time`` work on one node's children. ``Tables.solve`` binds one variable after the
other for all partial bindings together: the pattern with the fewest children proposes, the others are
looked up by binary search, so the work stays with the sum of the least fan-outs.
"""

from __future__ import annotations

import numpy as np

from ..model.query import OrderClause, PatternQuery, TimeVar, Var


def seek(values: np.ndarray, x: int) -> int | None:
    """Least value that is at least x."""
    i = int(np.searchsorted(values, x))
    return int(values[i]) if i < len(values) else None


def intersect(lists: list[np.ndarray]) -> list[int]:
    """Common values of sorted lists; each list in turn is asked for the least value not below the best so far."""
    out: list[int] = []
    if not lists or any(not len(x) for x in lists):
        return out
    at, agreed, turn = int(max(x[0] for x in lists)), 0, 0
    while True:
        found = seek(lists[turn], at)
        if found is None:
            return out
        agreed = agreed + 1 if found == at else 1
        at = found
        turn = (turn + 1) % len(lists)
        if agreed == len(lists):
            out.append(at)
            at, agreed = at + 1, 0


def intersect_time(lists: list[list[tuple[int, int]]], lo: int, hi: int, mode: str = "range") -> list[tuple[int, int]]:
    """Common parts within [lo, hi) of lists of disjoint sorted ranges: maximal ranges, or single ticks."""
    starts = [np.array([a for a, _ in x], np.int64) for x in lists]
    out: list[tuple[int, int]] = []
    at, agreed, turn, end = lo, 0, 0, hi
    while at < hi and lists:
        i = int(np.searchsorted(starts[turn], at, "right")) - 1
        if i < 0 or lists[turn][i][1] <= at:  # in a gap: the next range, if any
            i += 1
            if i >= len(lists[turn]):
                return out
        a, b = lists[turn][i]
        if a > at:
            at, agreed, end = a, 0, hi
            if at >= hi:
                return out
        agreed, end, turn = agreed + 1, min(end, b), (turn + 1) % len(lists)
        if agreed == len(lists):
            out.extend([(at, end)] if mode == "range" else [(t, t + 1) for t in range(at, end)])
            at, agreed, end = end, 0, hi
    return out


def _joint(table: list[np.ndarray], probes: list[np.ndarray], base: int) -> tuple[np.ndarray, np.ndarray]:
    """One number for each row of some columns of a table and of the same columns of probes, equal where the rows are.

    Columns hold values below ``base``. Before a product would leave 62 bits, what is there is ranked over both sides.
    The numbers times ``base`` stay below 63 bits.
    """
    n, m = (len(table[0]), len(probes[0])) if table else (0, 0)
    key, size = np.zeros(n + m, np.int64), 1
    for a, b in zip(table, probes, strict=True):
        key, size = key * base + np.concatenate((a, b)), size * base
        if size * base * base >= 1 << 62:
            kept, key = np.unique(key, return_inverse=True)
            key, size = key.astype(np.int64), max(1, len(kept))
    return key[:n], key[n:]


class Tables:
    """Edges of each pattern as arrays: a column for each variable and the interval."""

    def __init__(self, q: PatternQuery, columns: list[dict[str, np.ndarray]], starts: list[np.ndarray], stops: list[np.ndarray], base: int) -> None:
        self.q, self.cols, self.starts, self.stops, self.base = q, columns, starts, stops, max(2, base)
        self.proposals = 0

    def bind(self, rows: dict[str, np.ndarray], n: int, v: str) -> tuple[dict[str, np.ndarray], int]:
        """All extensions of the bindings by ``v``."""
        sources = []
        for i, p in enumerate(self.q.patterns):
            if v not in p.variables:
                continue
            bound = [b for b in p.variables if b in rows]
            c = self.cols[i]
            own, key = _joint([c[b] for b in bound], [rows[b] for b in bound], self.base) if bound else (np.zeros(len(c[v]), np.int64), np.zeros(n, np.int64))
            pairs = np.unique(own * self.base + c[v])  # children of each prefix, sorted and distinct
            prefix, value = pairs // self.base, pairs % self.base
            sources.append((prefix, value, key, np.searchsorted(prefix, key, "left"), np.searchsorted(prefix, key, "right")))
        width = np.stack([hi - lo for *_, lo, hi in sources])
        chooser = width.argmin(0)
        picked, values = [], []
        for k, (prefix, value, key, lo, hi) in enumerate(sources):
            mine = np.flatnonzero(chooser == k)
            size = (hi - lo)[mine]
            row = np.repeat(mine, size)
            at = np.arange(len(row)) - np.repeat(np.cumsum(size) - size, size) + np.repeat(lo[mine], size)
            got = value[at]
            keep = np.ones(len(row), bool)
            for j, (pre, val, key2, *_rest) in enumerate(sources):
                if j != k:
                    packed = pre * self.base + val
                    want = key2[row] * self.base + got
                    spot = np.minimum(np.searchsorted(packed, want), max(0, len(packed) - 1))
                    keep &= (packed[spot] == want) if len(packed) else False
            self.proposals += len(row)
            picked.append(row[keep])
            values.append(got[keep])
        row, got = np.concatenate(picked), np.concatenate(values)
        return {**{b: c[row] for b, c in rows.items()}, v: got}, len(row)

    def close(self, rows: dict[str, np.ndarray], n: int, i: int) -> tuple[dict[str, np.ndarray], int]:
        """Joins the intervals of pattern ``i`` whose variables are all bound, and narrows its time variable."""
        vs = self.q.patterns[i].variables
        key, mine = _joint([self.cols[i][v] for v in vs], [rows[v] for v in vs], self.base) if vs else (np.zeros(len(self.starts[i]), np.int64), np.zeros(n, np.int64))
        order = np.argsort(key, kind="stable")
        key, a, b = key[order], self.starts[i][order], self.stops[i][order]
        lo, hi = np.searchsorted(key, mine, "left"), np.searchsorted(key, mine, "right")
        size = hi - lo
        row = np.repeat(np.arange(n), size)
        at = np.arange(len(row)) - np.repeat(np.cumsum(size) - size, size) + np.repeat(lo, size)
        rows, start, stop = {k: c[row] for k, c in rows.items()}, a[at], b[at]
        t = self.q.patterns[i].t
        if isinstance(t, TimeVar):
            x, y = f"{t.name}_from", f"{t.name}_to"
            rows[x] = np.maximum(rows[x], start) if x in rows else start
            rows[y] = np.minimum(rows[y], stop) if y in rows else stop
            keep = rows[x] < rows[y]
            rows = {k: c[keep] for k, c in rows.items()}
            return rows, int(keep.sum())
        return rows, len(row)

    def solve_adaptive(self, order: list[str]) -> tuple[dict[str, np.ndarray], int]:
        """All solutions with an order of its own for each partial binding: rows are parted by the variable that has the
        fewest children below their binding, and each part goes on by itself. ``order`` only breaks ties."""
        nodes = [v for v in order if v in self.q.nodes]
        names = [*self.q.nodes, *dict.fromkeys(f"{p.t.name}_{e}" for p in self.q.patterns if isinstance(p.t, TimeVar) for e in ("from", "to"))]
        done: list[tuple[dict[str, np.ndarray], int]] = []

        def fewest(rows: dict[str, np.ndarray], n: int, v: str) -> np.ndarray:
            out = np.full(n, np.iinfo(np.int64).max)
            for i, p in enumerate(self.q.patterns):
                bound = [b for b in p.variables if b in rows]
                if v not in p.variables or (rows and not bound):
                    continue
                c = self.cols[i]
                own, key = _joint([c[b] for b in bound], [rows[b] for b in bound], self.base) if bound else (np.zeros(len(c[v]), np.int64), np.zeros(n, np.int64))
                prefix = np.unique(own * self.base + c[v]) // self.base
                out = np.minimum(out, np.searchsorted(prefix, key, "right") - np.searchsorted(prefix, key, "left"))
            return out

        def go(rows: dict[str, np.ndarray], n: int, open_: frozenset[int]) -> None:
            for i in sorted(open_):
                if set(self.q.patterns[i].variables) <= set(rows):
                    rows, n = self.close(rows, n, i)
                    open_ = open_ - {i}
            left = [v for v in nodes if v not in rows]
            if not left or not n:
                if n and not left:
                    done.append((rows, n))
                return
            pick = np.stack([fewest(rows, n, v) for v in left]).argmin(0) if n else np.zeros(0, int)
            for k in np.unique(pick):
                mine = pick == k
                part, size = self.bind({c: x[mine] for c, x in rows.items()}, int(mine.sum()), left[k])
                go(part, size, open_)

        go({}, 1, frozenset(range(len(self.q.patterns))))
        if not done:
            return {c: np.zeros(0, np.int64) for c in names}, 0
        return {c: np.concatenate([r[c] for r, _ in done]) for c in names}, sum(n for _, n in done)

    def solve(self, order: list[str], prune: bool = True) -> tuple[dict[str, np.ndarray], int]:
        """All solutions, a row for each combination of edges; time variables narrow as early as the order has them."""
        rows: dict[str, np.ndarray] = {}
        n, nodes, open_ = 1, [v for v in order if v in self.q.nodes], set(range(len(self.q.patterns)))
        late = set() if prune else {t for t in self.q.times if t in order and order.index(t) > max([order.index(v) for v in nodes], default=-1)}
        for v in nodes:
            rows, n = self.bind(rows, n, v)
            for i in sorted(open_):
                p = self.q.patterns[i]
                if set(p.variables) <= set(rows) and not (isinstance(p.t, TimeVar) and p.t.name in late):
                    rows, n = self.close(rows, n, i)
                    open_.discard(i)
        for i in sorted(open_):
            rows, n = self.close(rows, n, i)
        return rows, n


def narrow(rows: dict[str, np.ndarray], q: PatternQuery, const, span: tuple[int, int]) -> np.ndarray:
    """Order clauses on the ranges, in whole units; returns the rows to keep. ``const`` turns a constant into units."""
    n = len(next(iter(rows.values()))) if rows else 1
    for t in q.times:
        rows.setdefault(f"{t}_from", np.full(n, span[0]))
        rows.setdefault(f"{t}_to", np.full(n, span[1]))

    def move(c: OrderClause) -> None:
        less = c.offset - (1 if c.strict else 0)
        if isinstance(c.left, TimeVar) and isinstance(c.right, TimeVar):
            a, b = rows[f"{c.left.name}_from"] - less, rows[f"{c.right.name}_to"] + less
            rows[f"{c.right.name}_from"] = np.maximum(rows[f"{c.right.name}_from"], a)
            rows[f"{c.left.name}_to"] = np.minimum(rows[f"{c.left.name}_to"], b)
        elif isinstance(c.left, TimeVar):
            rows[f"{c.left.name}_to"] = np.minimum(rows[f"{c.left.name}_to"], const(c.right.value) + less + 1)
        elif isinstance(c.right, TimeVar):
            rows[f"{c.right.name}_from"] = np.maximum(rows[f"{c.right.name}_from"], const(c.left.value) - less)

    for _ in range(len(q.times)):
        for c in q.clauses:
            move(c)
    keep = np.full(n, not q.unsatisfiable)
    for t in q.times:
        keep &= rows[f"{t}_from"] < rows[f"{t}_to"]
    return keep


def variables_of(q: PatternQuery, i: int) -> dict[str, str]:
    """Variable -> first column it stands in."""
    out: dict[str, str] = {}
    for col, term in q.patterns[i].terms:
        if isinstance(term, Var):
            out.setdefault(term.name, col)
    return out
