"""DuckDB SQL of graphs and pattern queries, written independently of the engine's plans."""

from __future__ import annotations

from .model.query import Const, OrderClause, PatternQuery, TimeVar, Var

_BASE = """SELECT *, CAST(json_extract_string(props,'$.k') AS INT) AS k,
 lead(CAST(json_extract_string(props,'$.k') AS INT)) OVER w AS nk, lead(ts) OVER w AS nts
 FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id)"""


def _trip(label: str) -> str:
    return f"SELECT 'k'||(k%20) AS s, {label} AS p, 'k'||(nk%20) AS o, ts, nts AS te FROM ({_BASE}) WHERE nts IS NOT NULL"


_SHIP = "SELECT 's'||l_suppkey AS s, 'ships_'||l_returnflag AS p, 'p'||l_partkey AS o, l_shipdate AS ts, l_shipdate + to_days(CAST(l_quantity AS INT)) AS te FROM lineitem"
_KGT = _SHIP + """ UNION ALL SELECT 'p'||l_partkey, 'sold_to', 'c'||o_custkey, l_shipdate, l_shipdate + to_days(CAST(l_quantity AS INT)) FROM lineitem JOIN orders ON l_orderkey = o_orderkey
 UNION ALL SELECT 'o'||o_orderkey, 'placed_by', 'c'||o_custkey, o_orderdate, o_orderdate + INTERVAL 1 DAY FROM orders"""
_SPAN = "TIMESTAMP '1995-01-01', TIMESTAMP '2002-01-01'"
_STATIC = f"""SELECT 'c'||c_custkey, 'in_nation', 'n'||c_nationkey, {_SPAN} FROM customer
 UNION ALL SELECT 's'||s_suppkey, 'in_nation', 'n'||s_nationkey, {_SPAN} FROM supplier
 UNION ALL SELECT 'n'||n_nationkey, 'in_region', 'r'||n_regionkey, {_SPAN} FROM nation
 UNION ALL SELECT 'p'||p_partkey, 'has_brand', p_brand, {_SPAN} FROM part
 UNION ALL SELECT 'p'||p_partkey, 'has_type', p_type, {_SPAN} FROM part
 UNION ALL SELECT 'c'||c_custkey, 'in_segment', c_mktsegment, {_SPAN} FROM customer"""
_D = "TIMESTAMP '2024-01-01', TIMESTAMP '2025-01-01'"
RAW = {
    "TRIP": _trip("'u'||user_id"),
    "TRIP10": _trip("'g'||(user_id%10)"),
    "SKEW": _trip("'v'||CAST(floor(value/10) AS INT)"),
    "MONO": f"SELECT 'k'||k AS s, 'link' AS p, 'k'||nk AS o, CAST(date_trunc('day',ts) AS TIMESTAMP) AS ts, CAST(date_trunc('day',nts) AS TIMESTAMP)+INTERVAL 1 DAY AS te FROM ({_BASE}) WHERE nts IS NOT NULL",
    "SHIP": _SHIP,
    "KGT": _KGT,
    "KG": f"{_KGT} UNION ALL {_STATIC}",
    "TURN": "SELECT 'v'||conv_id AS s, role AS p, 'n'||length(text)%10 AS o, CAST(turn AS BIGINT) AS ts, CAST(turn AS BIGINT)+1 AS te FROM conversations",
    "DOC": f"""SELECT 'd'||doc_id AS s, 'in_lang' AS p, lang AS o, TIMESTAMP '2024-01-01' AS ts, TIMESTAMP '2025-01-01' AS te FROM documents
 UNION ALL SELECT 'd'||doc_id, 'from_source', source, {_D} FROM documents
 UNION ALL SELECT 'd'||doc_id, 'quality', 'q'||quality, {_D} FROM labels
 UNION ALL SELECT 'd'||doc_id, 'toxic', 'x'||toxic, {_D} FROM labels
 UNION ALL SELECT 'e'||vec_id, 'has_label', 'l'||label, {_D} FROM embeddings
 UNION ALL SELECT 'b'||item_id, 'is_a', 'benchmark_item', {_D} FROM benchmark
 UNION ALL SELECT 'g'||page_id, 'links_to', unnest(regexp_extract_all(html, 'href="([^"]*)"', 1)), {_D} FROM pages""",
}


def graph_ctes(name: str, as_: str = "e") -> str:
    """CTEs ending in ``as_`` with the coalesced edges of a graph."""
    return f"""{as_}_raw AS MATERIALIZED ({RAW[name]}),
{as_}_x AS (SELECT *, max(te) OVER (PARTITION BY s,p,o ORDER BY ts,te ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING) AS reach FROM {as_}_raw WHERE ts < te AND s IS NOT NULL AND p IS NOT NULL AND o IS NOT NULL),
{as_}_y AS (SELECT *, sum(CASE WHEN reach IS NULL OR ts > reach THEN 1 ELSE 0 END) OVER (PARTITION BY s,p,o ORDER BY ts,te ROWS UNBOUNDED PRECEDING) AS grp FROM {as_}_x),
{as_} AS MATERIALIZED (SELECT s, p, o, min(ts) AS ts, max(te) AS te FROM {as_}_y GROUP BY s, p, o, grp)"""


def over(name: str, body: str) -> str:
    return f"WITH {graph_ctes(name)}\n{body}"


def literal(value: object) -> str:
    return str(value) if isinstance(value, int) else f"TIMESTAMP '{value}'"


def _moved(x: str, units: int, whole: bool) -> str:
    if not units:
        return x
    return f"({x} + {units})" if whole else f"({x} + to_microseconds({units}))"


def _bounds(q: PatternQuery, parts: dict[str, tuple[list[str], list[str]]], whole: bool, unit: int = 1) -> dict[str, tuple[str, str]]:
    """Lower and upper end of each time variable after all clauses, by repeated propagation."""
    lo = {t: list(a) for t, (a, _) in parts.items()}
    hi = {t: list(b) for t, (_, b) in parts.items()}
    for _ in range(len(q.times) + 1):
        for c in q.clauses:
            less = c.offset - (unit if c.strict else 0)
            if isinstance(c.left, TimeVar) and isinstance(c.right, TimeVar):
                for x in list(lo[c.left.name]):
                    if (y := _moved(x, -less, whole)) not in lo[c.right.name]:
                        lo[c.right.name].append(y)
                for x in list(hi[c.right.name]):
                    if (y := _moved(x, less, whole)) not in hi[c.left.name]:
                        hi[c.left.name].append(y)
            elif isinstance(c.left, TimeVar):
                x = _moved(literal(c.right.value), less + unit, whole)
                if x not in hi[c.left.name]:
                    hi[c.left.name].append(x)
            elif isinstance(c.right, TimeVar):
                x = _moved(literal(c.left.value), -less, whole)
                if x not in lo[c.right.name]:
                    lo[c.right.name].append(x)
    one = lambda f, xs: xs[0] if len(xs) == 1 else f"{f}({', '.join(xs)})"
    return {t: (one("greatest", lo[t]), one("least", hi[t])) for t in parts}


def pattern_sql(q: PatternQuery, name: str, mode: str = "times", source: str = "e", distinct: bool = False, extra: str = "", whole: bool | None = None) -> str:
    """A query's solutions. ``mode``: ``times`` gives a range for each time variable, ``none`` ignores time (distinct bindings)."""
    whole = name == "TURN" if whole is None else whole
    where, first, ends = [], {}, {}
    for i, p in enumerate(q.patterns):
        for col, term in p.terms:
            here = f"a{i}.{col}"
            if isinstance(term, Const):
                where.append(f"{here} = '{term.value}'")
            elif term.name in first:
                where.append(f"{here} = {first[term.name]}")
            else:
                first[term.name] = here
        if mode == "times":
            if isinstance(p.t, TimeVar):
                a, b = ends.setdefault(p.t.name, ([], []))
                for start, stop in zip(a, b, strict=True):  # pairwise overlap follows from the common range; it lets joins prune
                    where.append(f"a{i}.ts < {stop} AND {start} < a{i}.te")
                a.append(f"a{i}.ts")
                b.append(f"a{i}.te")
            else:
                where.append(f"a{i}.ts <= {literal(p.t.value)} AND a{i}.te > {literal(p.t.value)}")
    cols = [f'{c} AS "{v}"' for v, c in first.items()]
    if mode == "times":
        for t in q.times:
            ends.setdefault(t, (["(SELECT min(ts) FROM e)"], ["(SELECT max(te) FROM e)"]))
        for t, (lo, hi) in _bounds(q, ends, whole).items():
            where.append(f"{lo} < {hi}")
            cols += [f'{lo} AS "{t}_from"', f'{hi} AS "{t}_to"']
    if extra:
        where.append(extra)
    tables = ", ".join(f"{source} a{i}" for i in range(len(q.patterns)))
    kind = "DISTINCT " if mode == "none" or distinct else ""
    return over(name, f"SELECT {kind}{', '.join(cols) or '1 AS hit'} FROM {tables}" + (f" WHERE {' AND '.join(where)}" if where else ""))


def stepwise_sql(q: PatternQuery, name: str) -> str:
    """The same solutions for one shared time variable with constant bounds at most, a pattern at a time: each pattern's
    edges are filtered first, and every join is on shared nodes, in an order in which each pattern meets one before it."""
    (t,) = {p.t.name for p in q.patterns}
    if not all(isinstance(p.t, TimeVar) for p in q.patterns) or any(isinstance(c.left, TimeVar) == isinstance(c.right, TimeVar) for c in q.clauses):
        raise ValueError("one shared time variable, with constant bounds at most")
    unit = "INTERVAL 1 MICROSECOND"
    lows = [f"{literal(c.left.value)}{f' + {unit}' if c.strict else ''}" for c in q.clauses if isinstance(c.left, Const)]
    highs = [f"{literal(c.right.value)}{'' if c.strict else f' + {unit}'}" for c in q.clauses if isinstance(c.right, Const)]
    if any(c.offset for c in q.clauses):
        raise ValueError("no offsets")
    start, stop = (f"{f}({', '.join([x, *more])})" if more else x for f, x, more in (("greatest", "ts", lows), ("least", "te", highs)))
    ctes, left = [], list(range(len(q.patterns)))
    for i, p in enumerate(q.patterns):
        where = [f"{c} = '{x.value}'" for c, x in p.terms if isinstance(x, Const)]
        cols = [f'{c} AS "{x.name}"' for c, x in p.terms if isinstance(x, Var)]
        ctes.append(f"f{i} AS MATERIALIZED (SELECT {', '.join([*cols, f'{start} AS ts', f'{stop} AS te'])} FROM e WHERE {' AND '.join([*where, f'{start} < {stop}'])})")
    fixed = lambda i: sum(isinstance(x, Const) for _, x in q.patterns[i].terms)
    first = max(left, key=lambda i: (fixed(i), -i))
    left.remove(first)
    bound, last = list(q.patterns[first].variables), f"f{first}"
    while left:
        i = max((j for j in left if set(q.patterns[j].variables) & set(bound)), key=lambda j: (len(set(q.patterns[j].variables) & set(bound)), fixed(j), -j))
        left.remove(i)
        vs = q.patterns[i].variables
        on = " AND ".join(f'a."{v}" = b."{v}"' for v in vs if v in bound)
        cols = [f'a."{v}"' for v in bound] + [f'b."{v}"' for v in vs if v not in bound]
        step = f"SELECT {', '.join(cols)}, greatest(a.ts, b.ts) AS ts, least(a.te, b.te) AS te FROM {last} a JOIN f{i} b ON {on}"
        last = f"j{i}"
        ctes.append(f"{last} AS MATERIALIZED (SELECT * FROM ({step}) WHERE ts < te)")
        bound += [v for v in vs if v not in bound]
    cols = ", ".join(f'"{v}"' for v in q.nodes)
    return f'WITH {graph_ctes(name)},\n' + ",\n".join(ctes) + f'\nSELECT {cols}, ts AS "{t}_from", te AS "{t}_to" FROM {last}'


__all__ = ["RAW", "OrderClause", "Var", "graph_ctes", "literal", "over", "pattern_sql", "stepwise_sql"]
