"""Logs of patterns on the star-schema graph: constants in every position, variable labels, stars, paths, cycles."""

from __future__ import annotations

from pyspark.sql import DataFrame

from ..model.graph import TemporalGraph
from ..model.query import Const, PatternQuery, parse

#: Templates with constants that occur at every size of the given tables (fixed values).
KG_LOG = [
    "?x in_nation n3 @t ; ?x ships_R ?p @t",
    "s7 ships_R ?p @t ; ?p sold_to ?c @t",
    "?o placed_by ?c @t ; ?c in_nation n5 @t ; n5 in_region ?r @t",
    "s3 ?l ?p @t ; ?p has_brand ?b @t",
    "?x ships_A p7 @t ; ?x in_nation ?n @t",
    "?x ships_R ?p @t ; ?p sold_to c10 @t ; ?x in_nation ?n @t",
    "?c in_segment BUILDING @t ; ?o placed_by ?c @t ; ?c in_nation n2 @t",
    "?x ships_N p3 @t ; ?y ships_N p3 @t",
    "?x ships_R ?p @t ; ?p sold_to ?c @t ; ?x in_nation ?n @t ; ?c in_nation ?n @t ; ?n in_region r1 @t",
    "p5 ?l ?z @t",
    "s1 ?l ?p @t ; ?p sold_to ?c @t ; ?c in_segment ?g @t",
    "?x ?l p1 @t ; ?x in_nation ?n @t",
]
KGT_LOG = [
    "s5 ships_R ?p @t ; ?p sold_to ?c @t",
    "?x ships_A p9 @t ; ?y ships_R p9 @t",
    "?x ships_N ?p @t ; ?p sold_to c4 @t",
    "?o placed_by c7 @t",
    "s2 ?l ?p @t ; ?p ?m c20 @t",
    "?x ships_R p4 @t ; ?x ships_A ?q @t ; ?q sold_to ?c @t",
]


def kg_log() -> list[PatternQuery]:
    return [parse(t) for t in KG_LOG]


def kgt_log() -> list[PatternQuery]:
    return [parse(t) for t in KGT_LOG]


def more(n: int, seed: int, labels: dict[str, tuple[str, str]] | None = None) -> list[PatternQuery]:
    """``n`` further patterns of 1 to 5 quads by a random walk over the schema, each with one constant end."""
    import random

    rng = random.Random(seed)
    schema = labels or {"ships_R": ("s", "p"), "ships_A": ("s", "p"), "ships_N": ("s", "p"), "sold_to": ("p", "c"), "placed_by": ("o", "c")}
    top = {"s": 10, "p": 200, "c": 150, "o": 1500}
    out = []
    while len(out) < n:
        quads, kinds, size = [], {}, rng.randint(1, 5)
        label = rng.choice(sorted(schema))
        a, b = schema[label]
        kinds["v0"], kinds["v1"] = a, b
        quads.append(("v0", label, "v1"))
        while len(quads) < size:
            v = rng.choice(sorted(kinds))
            fits = [(name, e) for name, e in sorted(schema.items()) if kinds[v] in e]
            name, (x, y) = rng.choice(fits)
            w = f"v{len(kinds)}"
            kinds[w] = y if x == kinds[v] else x
            quads.append((v, name, w) if x == kinds[v] else (w, name, v))
        fixed = rng.choice(sorted(kinds))
        term = {v: f"?{v}" for v in kinds} | {fixed: f"{kinds[fixed]}{rng.randint(1, top[kinds[fixed]])}"}
        out.append(parse(" ; ".join(f"{term[a]} {p} {term[b]} @t" for a, p, b in quads)))
    return out


def filter_by_constants(queries: list[PatternQuery], g: TemporalGraph) -> list[PatternQuery]:
    """Queries all of whose node constants occur in the graph: one semi-join of the constants with the universe."""
    spark = g.frame.sparkSession
    terms = sorted({str(t.value) for q in queries for p in q.patterns for _, t in p.terms if isinstance(t, Const)})
    if not terms:
        return queries
    known: DataFrame = spark.createDataFrame([(t,) for t in terms], "term string").join(g.universe(), "term", "left_semi")
    have = {r["term"] for r in known.collect()}
    return [q for q in queries if all(str(t.value) in have for p in q.patterns for _, t in p.terms if isinstance(t, Const))]
