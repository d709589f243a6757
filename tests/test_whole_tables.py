from collections import Counter

from chronoweave import catalogue
from chronoweave.operators import solve
from chronoweave.sources.graphs import graph
from chronoweave.sources.tables import load

SF = "/root/testdata/sf0.001"


def test_keys_take_whole_tables(spark):
    q = catalogue.queries()
    assert q["fn_json"](spark, SF).count() == load(spark, SF, "events").count()
    edges = graph(spark, SF, "SHIP").frame.select("ts", "te").collect()
    got = {r["o_orderkey"]: r["live"] for r in q["point_in_interval"](spark, SF).collect()}
    live = Counter()
    for r in load(spark, SF, "orders").select("o_orderkey", "o_orderdate").collect():
        live[r["o_orderkey"]] += sum(e["ts"] <= r["o_orderdate"] < e["te"] for e in edges)
    assert got == {k: n for k, n in live.items() if n}
    trips = graph(spark, SF, "TRIP10").frame.select("s", "p", "o").distinct().collect()
    assert {(r["x"], r["l"], r["y"]) for r in q["label_as_node"](spark, SF).select("x", "l", "y").collect()} == {tuple(r) for r in trips}
    keys = {r["o"] for r in graph(spark, SF, "MONO").frame.select("o").distinct().collect()}
    assert {r["key"] for r in q["stream_overlap_join"](spark, SF).select("key").distinct().collect()} == keys


def test_sweep_and_comparisons_take_the_whole_graph(spark):
    q = catalogue.queries()
    cols = ["x", "z", "y", "t_from", "t_to"]
    rows = lambda df: sorted(map(str, df.select(*cols).collect()))
    want = rows(solve.solve("?x ships_R ?z @t ; ?y ships_A ?z @t", graph(spark, SF, "SHIP"), "JF"))
    for key in ("sweep_pair", "h_jf_pair", "h_lc_pair", "h_tf_pair"):
        assert want and rows(q[key](spark, SF)) == want
    assert not [k for k in q if k.endswith("_slice")]
