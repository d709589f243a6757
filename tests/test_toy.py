import random
from datetime import datetime

from chronoweave.index import tries
from chronoweave.model.graph import TemporalGraph
from chronoweave.model.query import parse
from chronoweave.operators import baselines, solve, versions
from chronoweave.plans import order as plan
from chronoweave.sources.graphs import toy


def at(text):
    h, m = map(int, text.split(":"))
    return datetime(2024, 1, 1, h, m)


def test_worked_example(spark):
    g = toy(spark)
    assert g.timeline().count() == 14 and baselines.point_expand(g).count() == 13
    riders = lambda t: {r["x"] for r in solve.snapshot(parse("?x trip B12 @t"), g, at(t)).collect()}
    assert riders("10:50") == riders("10:46") == {"Anna", "Carl"} and "Anna" not in riders("11:05")
    together = solve.all_instants("?x trip B12 ; ?y trip B12", g).collect()
    got = {(r["x"], r["y"], r["t_from"], r["t_to"]) for r in together}
    assert len(together) == 8 and ("Anna", "Bob", at("10:32"), at("10:40")) in got and ("Anna", "Carl", at("10:46"), at("11:05")) in got
    q = parse("?x trip B12 @t1 ; ?x trip B6 @t2 ; @t1 <= @'2024-01-01 12:00:00' ; @'2024-01-01 12:00:00' <= @t2")
    assert {r["x"] for r in solve.solve(q, g).collect()} == {"Anna"}
    edge = parse("?x trip B12 @t")
    a, b = at("10:32"), at("10:46")
    names = lambda df: {r["x"] for r in df.collect()}
    assert names(solve.snapshot(edge, g, a)) == {"Anna", "Bob"} == names(solve.during_any(edge, g, a, b)) and names(solve.during_all(edge, g, a, b)) == {"Anna"}
    level = [r for r in tries.time_level(g, ["o"]).collect() if r["o"] == "B12"]
    assert len(level) == 6 and all(r["start"] != at("11:25") for r in level)
    diff = {(r["s"], r["change"]) for r in versions.diff(g, at("10:32"), at("10:46")).collect()}
    assert diff == {("Bob", "removed"), ("Carl", "added")}
    floors = g.floor(spark.createDataFrame([(at("10:50"),), (at("05:00"),), (at("23:00"),)], "at timestamp_ntz")).collect()
    assert {(r["at"], r["floor"]) for r in floors} == {(at("10:50"), at("10:46")), (at("05:00"), None), (at("23:00"), at("19:10"))}


def random_graph(spark, seed):
    rng = random.Random(seed)
    rows = []
    for _ in range(rng.randint(5, 50)):
        a = rng.randrange(20)
        rows.append((rng.choice("abcdef"), rng.choice("pq"), rng.choice("abcdefp"), a, a + rng.choice([1, 1, 2, 5, 20])))
    return TemporalGraph.from_edges(spark.createDataFrame(rows + rows[:3], "s string, p string, o string, ts long, te long"))


def ticks(df, q):
    return {(*[r[v] for v in q.nodes], t) for r in df.collect() for t in range(r["t_from"], r["t_to"])}


def test_all_routes_and_strategies_agree(spark):
    for seed, text in enumerate(["?x p ?y @t ; ?y q ?z @t", "?x p ?y @t ; ?y p ?z @t ; ?z p ?x @t", "?x ?l ?y @t ; ?y q a @t"]):
        g, q = random_graph(spark, seed), parse(text)
        line = sorted(r["at"] for r in g.timeline().collect())
        want = None
        for route in ("pairwise", "generic", "cells", "sweep", "expanded"):
            for strategy in ("JF", "TF", "LC") if route in ("pairwise", "cells") else ("LC",):
                got = ticks(solve.solve(q, g, strategy, route), q)
                got = {x for x in got if x[-1] in line}
                want = got if want is None else want
                assert got == want, (text, route, strategy)
        for t in line[::4]:
            snap = {tuple(r[v] for v in q.nodes) for r in solve.snapshot(q, g, t).collect()}
            assert snap == {x[:-1] for x in want if x[-1] == t}


def test_every_binding_order_gives_the_same(spark):
    from itertools import permutations

    g, q = random_graph(spark, 9), parse("?x p ?y @t ; ?y q ?z @t")
    want = None
    for order in list(permutations(["x", "y", "z", "t"]))[::3]:
        got = ticks(solve.solve(q, g, order=list(order), route="generic"), q)
        want = got if want is None else want
        assert got == want
    assert plan.pattern_order(q, ["z", "y", "x", "t"]) == [1, 0]


def test_index_store_and_packed_matrices(spark, tmp_path):
    g = random_graph(spark, 4)
    index = tries.build(g, ("otps",))
    index.save(f"file://{tmp_path}/ix")
    back = tries.load(spark, f"file://{tmp_path}/ix")
    events = {}
    for r in sorted(tries.numbered_events(g, "otps", index.width).collect(), key=lambda r: r["update"]):
        events.setdefault(r["o"], []).append((r["key"], r["sign"]))
    rows = {}
    for r in back.matrices["otps"].collect():
        rows.setdefault(r["prefix"][0], []).append(r)
    for o, ev in events.items():
        m, live = tries.unpack(rows[o], 2 * index.width), set()
        for i, (k, s) in enumerate(ev, 1):
            live = live | {k} if s > 0 else live - {k}
            assert m.members(i) == sorted(live)


def test_set_algebra(spark):
    a, b = random_graph(spark, 5), random_graph(spark, 6)
    pts = lambda g: {(r["s"], r["p"], r["o"], t) for r in g.frame.collect() for t in range(r["ts"], r["te"])}
    assert pts(a.union(b)) == pts(a) | pts(b) and pts(a.intersect(b)) == pts(a) & pts(b) and pts(a.minus(b)) == pts(a) - pts(b)
