"""How a store is written and read: one shuffle a part, no shuffle files left, parts narrowed before they are shuffled."""

from pyspark.sql import functions as F

from chronoweave.index import store
from chronoweave.model.graph import EDGE, TemporalGraph
from chronoweave.operators import generic, solve
from chronoweave.plans import order as plan
from chronoweave.sources.graphs import graph

SF = "/root/testdata/sf0.001"
CYCLE = "?x ships_R ?p @t ; ?p sold_to ?c @t ; ?x in_nation ?n @t ; ?c in_nation ?n @t ; ?n in_region r1 @t"


def rows(df, cols=EDGE):
    return sorted(map(str, df.select(*cols).collect()))


def test_parts_of_a_graph_are_written_behind_one_shuffle_each(spark, tmp_path):
    g = graph(spark, SF, "KG")
    assert len(g.parts) == 4
    labels = [{r["p"] for r in part.select("p").distinct().collect()} for part in g.parts]
    assert sum(map(len, labels)) == len(set.union(*labels))
    for part in (g.parts[0], g.parts[2]):  # labels read from the table, and a literal one
        plan_ = store.laid_out(g, part, 16, True)._jdf.queryExecution().executedPlan().toString()
        assert plan_.count("Exchange ") == 1 and "rangepartitioning" in plan_
    key = "spark.sql.classic.shuffleDependency.fileCleanup.enabled"
    before = spark.conf.get(key, None)
    store.save(g, f"file://{tmp_path}/kg")
    assert spark.conf.get(key, None) == before
    assert rows(store.open_store(spark, f"file://{tmp_path}/kg").graph.frame) == rows(g.frame)


def test_merging_keeps_touching_overlapping_and_equal_intervals_together(spark, tmp_path):
    edges = [("a", "p", "b", 0, 4), ("a", "p", "b", 0, 4), ("a", "p", "b", 4, 6), ("a", "p", "b", 1, 2), ("a", "p", "b", 8, 9), ("a", "p", "b", 8, 12), ("a", "p", "c", 5, 5), ("a", "q", "b", 6, 8), ("c", "p", "b", 3, 9)]
    df = spark.createDataFrame(edges, "s string, p string, o string, ts long, te long")
    want = sorted([("a", "p", "b", 0, 6), ("a", "p", "b", 8, 12), ("a", "q", "b", 6, 8), ("c", "p", "b", 3, 9)])
    g = TemporalGraph.from_edges(df)
    assert sorted(map(tuple, g.frame.collect())) == want
    for name, x in (("merged", g), ("as_they_are", TemporalGraph.from_edges(df, coalesce=False))):
        store.save(x, f"file://{tmp_path}/{name}")
        got = sorted(map(tuple, store.open_store(spark, f"file://{tmp_path}/{name}").graph.frame.select(*EDGE).collect()))
        assert got == (want if name == "merged" else sorted(e for e in edges if e[3] < e[4]))


def test_selective_parts_narrow_the_others_before_a_shuffle(spark, tmp_path):
    store.save(graph(spark, SF, "KG"), f"file://{tmp_path}/kg")
    g = store.open_store(spark, f"file://{tmp_path}/kg").graph
    q = plan.normalise(solve.parse(CYCLE))
    scans = {i: generic.scan(q, i, g) for i in range(5)}
    less = generic.narrowed(scans, q, g)
    size = lambda parts: [parts[i].agg(F.count(F.lit(1))).first()[0] for i in range(5)]
    assert all(a < b for a, b in list(zip(size(less), size(scans), strict=True))[:4]) and size(less)[4] == size(scans)[4]
    assert generic.narrowed(scans, q, g, most=0)[1] is scans[1]
    cols = ["x", "p", "c", "n", "t_from", "t_to"]
    assert rows(solve.solve(q, g, "JF", route="generic"), cols) == rows(solve.solve(q, graph(spark, SF, "KG"), "JF", route="pairwise"), cols)
