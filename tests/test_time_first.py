"""Time-first plans own a result by the number of the bucket of its latest start."""

from collections import Counter

from chronoweave.index import store
from chronoweave.operators import pairwise, solve
from chronoweave.plans import order as plan
from chronoweave.sources.graphs import graph

SF = "/root/testdata/sf0.001"


def test_results_are_owned_by_bucket_numbers_not_by_converted_instants(spark):
    g = graph(spark, SF, "TRIP10")
    q = plan.normalise(solve.parse("?x g3 ?y @t ; ?y g3 ?z @t ; ?z g9 ?w @t"))
    cols = ["x", "y", "z", "w", "t_from", "t_to"]
    want = sorted(map(str, solve.solve(q, g, "JF").select(*cols).collect()))
    assert want
    for buckets in (2, 16, 60):
        df = pairwise.run(q, g, ["t", "x", "y", "z", "w"], buckets)
        assert sorted(map(str, df.select(*cols).collect())) == want
        text = df._jdf.queryExecution().optimizedPlan().toString()
        assert not [x for x in text.splitlines() if ("Join " in x or "Filter " in x) and "as double" in x]


def test_broadcast_joins_are_cut_by_time_whatever_the_order(spark, tmp_path):
    g = graph(spark, SF, "TRIP10")
    store.save(g, str(tmp_path / "g"))
    held = store.open_store(spark, str(tmp_path / "g")).graph
    cols = ["x", "y", "z", "w", "t_from", "t_to"]
    for tail in ("", " ; @'2024-01-10' <= @t ; @t <= @'2024-01-20'"):
        q = plan.normalise(solve.parse("?x g3 ?y @t ; ?y g3 ?z @t ; ?z g9 ?w @t" + tail))
        want = sorted(map(str, solve.solve(q, g, "JF", route="pairwise").select(*cols).collect()))
        assert want
        for strategy in ("LC", "JF", "TF"):
            df = solve.solve(q, held, strategy, route="pairwise")
            assert sorted(map(str, df.select(*cols).collect())) == want
            joins = [x for x in df._jdf.queryExecution().optimizedPlan().toString().splitlines() if "Join " in x]
            assert len(joins) == 2 and all("__b" in x for x in joins), strategy
    rows = [r for r in held.stats if r["p"] in ("g3", "g9")]
    mean = sum(r["rows"] * r["length"] for r in rows) / sum(r["rows"] for r in rows)
    assert pairwise.mean_lengths(q, held) == int(max(r["span"] for r in rows) / mean)


def test_patterns_at_one_instant_join_on_nodes_alone_and_expand_last(spark, tmp_path):
    def rows(df):
        cols = sorted(df.columns)
        return Counter(map(str, df.select(*cols).collect()))

    day = " ; @'2024-01-15' <= @t ; @t <= @'2024-01-15'"
    texts = {
        "MONO": ["?x link ?y @t ; ?y link ?z @t", "?x link ?y @t ; ?y link ?z @t ; ?z link ?x @t", "k1 link ?y @t ; ?y ?l ?z @t ; ?z link ?w @t", "?x link ?x @t ; ?x link ?y @t", "?x link ?y @t ; ?y link ?z @t ; @t < @'2024-01-15'"],
        "TURN": ["?x user ?n @t ; ?y user ?n @t"],
    }
    found = set()
    for name, some in texts.items():
        g = graph(spark, SF, name)
        store.save(g, str(tmp_path / name))
        held = store.open_store(spark, str(tmp_path / name)).graph
        for text in some:
            q = solve.parse(text + (" ; @2 <= @t ; @t <= @2" if name == "TURN" else day))
            assert pairwise.pinned(q) is not None
            plain = solve.solve(q, g, "JF", route="pairwise")
            want = rows(plain)
            found |= {name} if want else set()
            for strategy in ("LC", "TF"):
                df = solve.solve(q, held, strategy, route="pairwise")
                assert sorted(df.dtypes) == sorted(plain.dtypes) and rows(df) == want, (text, strategy)
                joins = [x for x in df._jdf.queryExecution().optimizedPlan().toString().splitlines() if "Join " in x]
                assert bool(joins) == ("@t < @" not in text) and not any("__b" in x or "__ts" in x for x in joins), text
    assert found == set(texts)
    assert pairwise.pinned(solve.parse("?x link ?y @t ; @'2024-01-15' <= @t ; @t <= @'2024-01-16'")) is None
    assert pairwise.pinned(solve.parse("?x link ?y @t ; ?y link ?z @u" + day)) is None
    held, was = store.open_store(spark, str(tmp_path / "MONO")).graph, spark.conf.get("spark.sql.adaptive.enabled")
    spark.conf.set("spark.sql.adaptive.enabled", "false")
    try:
        q = solve.parse(" ; ".join(f"?x{i} link ?x{i + 1} @t" for i in range(5)) + day)
        lines = solve.solve(q, held, "TF", route="pairwise")._jdf.queryExecution().executedPlan().toString().splitlines()
    finally:
        spark.conf.set("spark.sql.adaptive.enabled", was)
    fused = Counter(x[x.index("*(") : x.index(")")] for x in lines if "*(" in x and "BroadcastHashJoin" in x)
    assert sorted(fused.values()) == [2, 2] and any("Generate inline(" in x for x in lines)


def test_a_node_that_a_later_pattern_closes_is_bound_by_joined_edges(spark, tmp_path, monkeypatch):
    def rows(df):
        return Counter(map(str, df.select(*sorted(df.columns)).collect()))

    day = " ; @'2024-01-15' <= @t ; @t <= @'2024-01-15'"
    g = graph(spark, SF, "MONO")
    store.save(g, str(tmp_path / "g"))
    held = store.open_store(spark, str(tmp_path / "g")).graph
    circle = "?x link ?y @t ; ?y link ?z @t ; ?z link ?u @t ; ?u link ?x @t"
    for text, listed in ((circle, True), (circle + " ; ?x link ?z @t ; ?y link ?u @t", False), ("?x link ?y @t ; ?y link ?x @t", False), ("?x link ?y @t ; ?y link ?z @t ; ?z link ?y @t", True), ("?x link ?y @t ; ?y ?l ?z @t ; ?z ?l ?x @t", True)):
        q = solve.parse(text + day)
        want = rows(solve.solve(q, g, "JF", route="pairwise"))
        df = solve.solve(q, held, "TF", route="pairwise")
        assert want and rows(df) == want, text
        assert ("Generate inline(" in df._jdf.queryExecution().optimizedPlan().toString()) == listed, text
    with monkeypatch.context() as m:  # more of them than may be broadcast: the patterns are joined one at a time
        m.setattr(pairwise.paths, "__defaults__", (0,))
        q = solve.parse(circle + day)
        df = solve.solve(q, held, "TF", route="pairwise")
        assert rows(df) == rows(solve.solve(q, g, "JF", route="pairwise")) and "Generate inline(" not in df._jdf.queryExecution().optimizedPlan().toString()
