"""Sources, sinks, measures, functions and plans that have no key of their own."""

import math
import time

import numpy as np
import pytest
from pyspark.sql import functions as F

from chronoweave.functions import sql as functions
from chronoweave.index import store, tries
from chronoweave.measures import cost
from chronoweave.model.graph import EDGE, TemporalGraph
from chronoweave.model.query import Const, parse
from chronoweave.model.ranks import part_of, ranked, split_points
from chronoweave.operators import cells, leapfrog, reduced, solve
from chronoweave.plans import order as plan
from chronoweave.plans import stats
from chronoweave.sources import datasource, tables
from chronoweave.sources.graphs import graph, toy
from chronoweave.workloads import logs, shapes

SF = "/root/testdata/sf0.001"


def numbers(spark, rows):
    return TemporalGraph.from_edges(spark.createDataFrame(rows, "s string, p string, o string, ts long, te long"))


def random_rows(seed, n=60, nodes=6, labels="pq", top=20):
    rng = np.random.default_rng(seed)
    out = []
    for _ in range(n):
        a = int(rng.integers(0, top))
        out.append((f"n{rng.integers(nodes)}", str(rng.choice(list(labels))), f"n{rng.integers(nodes)}", a, a + int(rng.integers(1, 8))))
    return out


def test_ranks_are_gapless_without_exchange_reuse(spark):
    spark.conf.set("spark.sql.exchange.reuse", "false")
    try:
        for values, kind in ((spark.range(20_000).select((F.col("id") * 7 - 300).alias("v")), "long"), (spark.range(5000).select(F.concat(F.lit("k"), (F.col("id") * 13 % 5003).cast("string")).alias("v")), "string")):
            got = ranked(values, "v", "r").collect()
            assert [r["v"] for r in sorted(got, key=lambda r: r["r"])] == sorted(r["v"] for r in values.collect()), kind
            assert sorted(r["r"] for r in got) == list(range(len(got)))
        g = graph(spark, SF, "SHIP")
        live = {r["start"]: (r["stop"], r["live"]) for r in tries.time_level(g, []).collect()}
        edges = g.frame.select("ts", "te").collect()
        for at in sorted(live)[::97]:
            stop, n = live[at]
            assert n == sum(e["ts"] <= at < e["te"] for e in edges) and stop > at
    finally:
        spark.conf.unset("spark.sql.exchange.reuse")


def test_parts_of_bounds(spark):
    points = [3, 7, 7.5, 20, 21, 22, 50]
    rows = spark.createDataFrame([(float(x),) for x in range(60)], "v double").select("v", part_of(F.col("v"), points, "double").alias("p")).collect()
    assert all(r["p"] == sum(b <= r["v"] for b in points) for r in rows)
    assert split_points(spark.createDataFrame([], "v long"), "v") == []


def test_edges_in_every_format_and_layout(spark, tmp_path):
    g = graph(spark, SF, "TRIP10")
    want = sorted(map(tuple, g.frame.collect()))
    for fmt in ("csv", "json", "orc", "parquet"):
        path = f"file://{tmp_path}/{fmt}"
        options = {"timestampNTZFormat": "yyyy-MM-dd HH:mm:ss.SSSSSS"} | ({"header": "true"} if fmt == "csv" else {}) if fmt in ("csv", "json") else {}
        g.frame.write.format(fmt).options(**options).save(path)
        back = tables.read_edges(spark, fmt, path, **options)
        assert sorted(map(tuple, back.collect())) == want, fmt
    tables.write_edges(g.frame, f"file://{tmp_path}/laid")
    back = spark.read.parquet(f"file://{tmp_path}/laid")
    assert {"label_class", "month"} <= set(back.columns) and sorted(map(tuple, back.select(*EDGE).collect())) == want


def test_data_source_prunes(spark, tmp_path):
    g = graph(spark, SF, "TRIP10")
    path = str(tmp_path / "edges")
    tables.write_edges(g.frame, f"file://{path}")
    spark.dataSource.register(datasource.TemporalEdges)
    spark.conf.set("spark.sql.python.filterPushdown.enabled", "true")
    df = spark.read.format("temporal_edges").load(path)
    assert sorted(map(tuple, df.select(*EDGE).collect())) == sorted(map(tuple, g.frame.collect()))
    some = df.filter("p = 'g3'").select(*EDGE)
    assert sorted(map(tuple, some.collect())) == sorted(map(tuple, g.frame.filter("p = 'g3'").collect()))


def test_sql_functions_and_table_functions(spark):
    g = toy(spark)
    functions.register(spark, g, "toy_edges")
    n = spark.sql("SELECT count(*) AS n FROM toy_edges WHERE valid_at(ts, te, TIMESTAMP_NTZ '2024-01-01 10:35:00')").first()["n"]
    assert n == 2
    pairs = spark.sql("SELECT a.s, b.s AS t FROM toy_edges a JOIN toy_edges b ON a.o = b.o AND a.s < b.s AND overlaps(a.ts, a.te, b.ts, b.te)").collect()
    assert {tuple(r) for r in pairs} == {("Anna", "Bob"), ("Anna", "Carl"), ("Anna", "Dick")}
    rows = spark.sql("SELECT * FROM pattern('?x trip ?z @t1 ; Bob trip ?z @t2 ; @t1 <= @t2')").collect()
    assert [(r["kind"], r["s"], r["o"], r["t"]) for r in rows] == [("quad", "?x", "?z", "@t1"), ("quad", "Bob", "?z", "@t2"), ("clause", "@t1", "@t2", None)]
    out = functions.solve_view(spark, "?x trip ?z @t ; Bob trip ?z @t", "toy_edges", "toy_answers", strategy="JF")
    assert spark.sql("SELECT count(*) AS n FROM toy_answers WHERE x <> 'Bob'").first()["n"] == out.filter("x <> 'Bob'").count() == 1


def test_coalescing_aggregate(spark):
    rows = [("a", 0, 3), ("a", 2, 5), ("a", 7, 9), ("b", 1, 2), ("b", 2, 4)]
    got = spark.createDataFrame(rows, "k string, ts long, te long").groupBy("k").agg(functions.coalesce_ranges("ts", "te").alias("r")).collect()
    assert {r["k"]: [tuple(x) for x in r["r"]] for r in got} == {"a": [(0, 5), (7, 9)], "b": [(1, 4)]}


def test_limits_and_timeouts(spark):
    g = graph(spark, SF, "SHIP")
    ms, n, late = cost.timed(lambda: solve.solve("?x ships_R ?z @t ; ?y ships_A ?z @t", g, "JF"), limit=10)
    assert n == 10 and not late and ms > 0
    assert solve.solve("?x ships_R ?z @t", g, "JF", limit=7).count() == 7
    slow = lambda: spark.range(10**13).filter("id % 7919 = 3 AND sqrt(id) > 0")
    began = time.perf_counter()
    ms, n, late = cost.timed(slow, timeout=2)
    assert late and n == 0 and ms == 2000 and time.perf_counter() - began < 60


def test_timing_measures(spark):
    rows = [(q, s, float(ms), 1, False) for q, s, ms in ((1, "A", 1), (1, "B", 2), (2, "A", 5), (2, "B", 3), (3, "A", 1), (3, "B", 4))]
    times = spark.createDataFrame(rows, cost.TIMING)
    box = {r["strategy"]: r for r in cost.boxplot(times).collect()}
    assert (box["A"]["lower"], box["A"]["median"], box["A"]["upper"]) == (1, 1, 5) and math.isclose(box["B"]["mean"], 3)
    won = {r["strategy"]: r.asDict() for r in cost.wins(times).collect()}
    assert won["A"]["B"] == 2 and won["B"]["A"] == 1
    assert math.isclose(cost.best(times).first()["best_mean"], 5 / 3)


def test_space_and_build_time(spark):
    g = graph(spark, SF, "MONO")
    index = tries.build(g, ("ptso", "otps"))
    n = g.frame.count()
    rows = {r["order"]: r for r in cost.space(index, n).collect()}
    assert math.isclose(sum(r["share"] for r in rows.values()), 1.0)
    for r in rows.values():  # two bits a level and update, two updates an edge, and little beyond
        assert r["updates"] == 2 * n and r["bytes"] * 8 >= 2 * 2 * index.width * r["updates"]
    kinds = {r["kind"]: r["bytes_per_edge"] for r in cost.table_space(g, ("otps",)).collect()}
    assert kinds["plain spo"] <= 20 <= kinds["packed 5 x 32 bit"] * 1.0001 and kinds["temporal otps"] > 0
    grown = cost.build_time(g, (0.5, 1.0), ("otps",))
    assert [r["fraction"] for r in grown] == [0.5, 1.0] and grown[0]["edges"] < grown[1]["edges"] and all(r["us_per_edge"] > 0 for r in grown)


def test_work_of_strategies_against_a_count(spark):
    g = numbers(spark, random_rows(4))
    q = plan.normalise(parse("?x p ?y @t ; ?y q ?z @t ; ?z p ?x @t"))
    answers = solve.solve(q, g, "JF").count()
    for s in ("JF", "TF", "LC"):
        r = cost.work(q, g, s).first()
        assert r["answers"] == answers and r["proposals"] >= 0


def test_constants_filter(spark):
    g = graph(spark, SF, "KGT")
    queries = [parse("s1 ships_R ?p @t"), parse("nobody ships_R ?p @t"), parse("?x sold_to c99999999 @t"), parse("?x ships_A ?p @t")]
    assert logs.filter_by_constants(queries, g) == [queries[0], queries[3]]
    more = logs.more(20, 3)
    assert len(more) == 20 and all(any(isinstance(t, Const) for p in q.patterns for _, t in p.terms) for q in more)
    assert logs.filter_by_constants(more, g)


def test_shapes_labels_and_windows(spark):
    g = graph(spark, SF, "TRIP10")
    at = "2024-01-15 12:00:00"
    labels = shapes.sample_labels(g, "circle3", at, 3)
    assert labels is None or solve.solve(shapes.shape_query("circle3", labels), g, "TF").count() > 0
    lo, hi = shapes.month()
    spans = shapes.windows(lo, hi, 0.1, 5, 1)
    assert all(a >= lo and b <= hi and abs((b - a) / (hi - lo) - 0.1) < 1e-6 for a, b in spans) and spans == shapes.windows(lo, hi, 0.1, 5, 1)


def test_store_prunes_folders_and_needs_no_statistics_pass(spark, tmp_path):
    g = graph(spark, SF, "SHIP")
    path = f"file://{tmp_path}/store"
    store.save(g, path)
    back = store.open_store(spark, path).graph
    assert sorted(map(tuple, back.frame.select(*EDGE).collect())) == sorted(map(tuple, g.frame.collect()))
    q = parse("?x ships_R ?z @t ; ?y ships_A ?z @t")
    scan = solve.pairwise.scan(q, 0, back)._jdf.queryExecution().executedPlan().toString()
    assert "label_class" in scan.split("PartitionFilters:")[1].split("]")[0]
    long = back.at_least(40 * 86_400_000_000)
    assert "length_class" in long.frame._jdf.queryExecution().executedPlan().toString().split("PartitionFilters:")[1].split("]")[0]
    assert long.frame.count() == g.at_least(40 * 86_400_000_000).frame.count()
    exact = plan.statistics(q, g, exact=True)
    for a, b in zip(plan.statistics(q, back), exact, strict=True):
        assert a.rows == b.rows and all(abs(a.distinct[v] - b.distinct[v]) <= 0.1 * b.distinct[v] + 1 for v in b.distinct)
    assert {r["prefix"] for r in stats.fanout(g, exact=False).collect()} == {f"{a}>{b}" for a, b in stats.PREFIXES}


def test_matrices_of_a_store_answer_windows(spark, tmp_path):
    g = numbers(spark, random_rows(8, 120))
    edges = g.frame.collect()
    for orders, each in ((("otps",), 1 << 20), (("ptso",), 8), (("tspo",), 16)):
        path = f"file://{tmp_path}/{orders[0]}-{each}"
        store.save(g, path, orders, pack=True, events_each=each)
        s = store.open_store(spark, path)
        for lo, hi in ((-5, 3), (0, 1), (4, 9), (10, 30), (26, 40)):
            alive = lambda t: {(e["s"], e["p"], e["o"]) for e in edges if e["ts"] <= t < e["te"]}
            spans = [alive(t) for t in range(lo, hi)]
            assert {tuple(r) for r in s.triples("at", lo).collect()} == alive(lo), (orders, lo)
            assert {tuple(r) for r in s.triples("any", lo, hi).collect()} == set.union(*spans), (orders, lo, hi)
            assert {tuple(r) for r in s.triples("all", lo, hi).collect()} == set.intersection(*spans), (orders, lo, hi)


def test_join_trees_and_reduction(spark):
    g = numbers(spark, random_rows(5, 80))
    for text in ("?x p ?y @t ; ?y q ?z @t ; ?z p ?w @t", "?x p ?y @t ; ?x q ?z @t ; ?x p ?w @t", "?x p ?y @t ; ?y q n1 @u ; @t <= @u"):
        q = parse(text)
        assert reduced.join_tree(q) is not None and not solve.cyclic(q)
        a, b = (sorted(map(str, solve.solve(q, g, "JF", route=r).collect())) for r in ("pairwise", "reduced"))
        assert a == b
        parts = reduced.reduce(q, [solve.pairwise.scan(q, i, g) for i in range(len(q.patterns))])
        ever = solve.solve(parse(text.replace("@u", "@t").split(" ; @t <=")[0]), g.of(g.frame.withColumns({"ts": F.lit(0).cast("long"), "te": F.lit(1).cast("long")}).distinct()), "JF")
        for p, part in zip(q.patterns, parts, strict=True):
            assert {tuple(r) for r in part.select(*p.variables).distinct().collect()} == {tuple(r) for r in ever.select(*p.variables).distinct().collect()}
    assert solve.cyclic(parse("?x p ?y @t ; ?y q ?z @t ; ?z p ?x @t"))
    with pytest.raises(ValueError):
        solve.solve("?x p ?y @t ; ?x q ?y @t ; ?a p ?b @u", g, "JF")
    assert solve.solve("?x p ?y @t ; n1 q ?b @u", g, "JF", products=True).count() == g.frame.filter("p = 'p'").count() * g.frame.filter("p = 'q' AND s = 'n1'").count()


def test_order_of_its_own_for_each_binding(spark):
    g = numbers(spark, random_rows(6, 80))
    for text in ("?x p ?y @t ; ?y q ?z @t ; ?z p ?x @t", "?x p ?y @t ; ?y q ?z @t ; ?x q ?w @t", "?x p ?y @t ; ?y q ?x @u ; @t <= @u"):
        a, b = (sorted(map(str, solve.solve(text, g, s, route="cells").collect())) for s in ("LC", "LC_adaptive"))
        assert a == b == sorted(map(str, solve.solve(text, g, "JF", route="pairwise").select(*solve.solve(text, g, "LC", route="cells").columns).collect()))


def test_joint_numbers_of_many_terms():
    rng = np.random.default_rng(1)
    base = 3_000_000
    table, probe = ([rng.integers(base - 5, base, 500) for _ in range(3)] for _ in range(2))
    a, b = leapfrog._joint(table, probe, base)
    left, right = list(zip(*table, strict=True)), list(zip(*probe, strict=True))
    assert all((a[i] == b[j]) == (left[i] == right[j]) for i in range(0, 500, 7) for j in range(0, 500, 11))
    assert max(a.max(), b.max()) * base < 2**63


def test_shares_follow_sizes():
    q = parse("?x p ?y @t ; ?y q ?z @t")
    assert cells.shares(q, [10**6, 10**6], 16) == {"y": 16}
    tri = parse("?x p ?y @t ; ?y q ?z @t ; ?z p ?x @t")
    h = cells.shares(tri, [10**6, 10, 10**6], 16)
    assert h["x"] >= 8 and cells._load(tri, [100, 100, 100], {"x": 2, "y": 5, "z": 1}) == 100 / 10 + 100 / 5 + 100 / 2


def test_clauses_prune_joins(spark):
    g = numbers(spark, random_rows(9, 80))
    q = parse("?x p ?z @t1 ; ?y q ?z @t2 ; @t1 <= @t2")
    df = solve.pairwise.run(q, g, ["z", "x", "y", "t1", "t2"])
    assert "__ts0" in next(line for line in df._jdf.queryExecution().optimizedPlan().toString().split("\n") if "Join" in line)
    want = set()
    rows = g.frame.collect()
    for a in rows:
        for b in rows:
            if a["p"] == "p" and b["p"] == "q" and a["o"] == b["o"] and a["ts"] < b["te"]:
                want.add((a["s"], a["o"], b["s"], a["ts"], min(a["te"], b["te"]), max(a["ts"], b["ts"]), b["te"]))
    assert {(r["x"], r["z"], r["y"], r["t1_from"], r["t1_to"], r["t2_from"], r["t2_to"]) for r in df.collect()} == want


def test_permutations_choose_tables(spark):
    g = graph(spark, SF, "TRIP10")
    index = tries.build(g, ("ptso", "otps"), pack_=False)
    q = parse("?x g3 ?y @t ; k1 ?l ?y @t")
    assert index.choose(plan.pick_permutation(q.patterns[0], ["y", "t", "x"])) == "ptso"
    assert index.choose("otsp") == "otps"
    got = index.scan(q, 0, ["x", "y", "t"], g)
    assert sorted(map(str, got.collect())) == sorted(map(str, solve.pairwise.scan(q, 0, g).collect()))


def test_keys_without_common_children(spark):
    left = spark.createDataFrame([("s1", "p1"), ("s1", "p2"), ("s2", "p3"), ("s3", "p4")], "s string, child string")
    right = spark.createDataFrame([("s1", "p2"), ("s1", "p5"), ("s2", "p4"), ("s4", "p4")], "s string, child string")
    assert [tuple(r) for r in functions.merge_intersect(left, right, "s").collect()] == [("s1", "p2")]


def _joins(df):
    return [x for x in df._jdf.queryExecution().optimizedPlan().toString().split("\n") if "Join" in x]


def test_join_first_tests_overlap_in_every_join(spark):
    g = numbers(spark, random_rows(13, 80))
    text = "?x p ?z @t ; ?y p ?z @t ; ?x q ?w @t ; ?y q ?w @t"
    assert sum("__ts" in x for x in _joins(solve.solve(text, g, "JF", route="pairwise"))) == 3
    for s in ("JF", "LC"):  # a variable that completes a pattern comes with the pattern's edges: one semi-join, then one join a pattern
        joins = _joins(solve.solve("?x p ?y @t ; ?y q ?z @t", g, s, route="generic"))
        assert len(joins) == 3 and "__ts" in joins[0]
    rows = lambda df: sorted(map(str, df.select("x", "y", "z", "w", "t_from", "t_to").collect()))
    want = rows(solve.solve(text, g, "JF", strict=True))
    assert want == rows(solve.solve(text, g, "JF")) == rows(solve.solve(text, g, "LC", route="generic")) == rows(solve.solve(text, g, "TF"))


def test_small_labels_of_a_store_are_broadcast_and_windows_cut_edges(spark, tmp_path):
    g = numbers(spark, random_rows(14, 80))
    path = f"file://{tmp_path}/g"
    store.save(g, path)
    held = store.open_store(spark, path).graph
    text = "?x p ?y @t ; ?y q ?z @t ; ?z p ?w @t ; @t <= @12 ; @7 <= @t"
    old = spark.conf.get("spark.sql.autoBroadcastJoinThreshold")
    spark.conf.set("spark.sql.autoBroadcastJoinThreshold", "-1")
    try:
        for s in ("LC", "TF"):
            df = solve.solve(text, held, s, route="pairwise")
            plan_ = df._jdf.queryExecution().executedPlan().toString()
            assert plan_.count("BroadcastHashJoin") == 2 and "hashpartitioning" not in plan_
            assert "__ts2" not in _joins(df)[0].split("Join")[0]
            cols = ["x", "y", "z", "w", "t_from", "t_to"]
            assert sorted(map(str, df.select(*cols).collect())) == sorted(map(str, solve.solve(text, g, "LC", route="cells").select(*cols).collect()))
    finally:
        spark.conf.set("spark.sql.autoBroadcastJoinThreshold", old)
    ends = [(r["__ts0"], r["__te0"]) for r in solve.pairwise.scan(parse(text), 0, g).collect()]
    assert ends and all(7 <= a < b <= 13 for a, b in ends)
