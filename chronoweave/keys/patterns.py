"""Pattern queries: strategies, routes, baselines, clauses, windows, logs and shapes."""

from __future__ import annotations

from datetime import datetime

from pyspark.sql import functions as F

from ..measures import cost
from ..model.query import Const, OrderClause, PatternQuery, TimeVar, parse
from ..index import store
from ..operators import baselines, pairwise, results, solve, versions
from ..plans import bounds
from ..plans import order as plan
from ..sources.graphs import graph
from ..sql_text import graph_ctes, over, pattern_sql, stepwise_sql
from ..workloads.logs import kg_log, kgt_log
from ..workloads.shapes import SHAPES, arcs, shape_query, two_times
from . import Registry

PAIR = "?x ships_R ?z @t ; ?y ships_A ?z @t"
TRIANGLE = "?x g3 ?y @t ; ?y g3 ?z @t ; ?z g9 ?x @t"
SQUARE = "?x ships_R ?p @t ; ?p sold_to ?c @t ; ?x in_nation ?n @t ; ?c in_nation ?n @t"
BICLIQUE = "?x ships_R ?z @t ; ?y ships_R ?z @t ; ?x ships_R ?w @t ; ?y ships_R ?w @t"
MONO = "?x link ?y @t ; ?y link ?z @t ; ?z link ?x @t"
EDGE = "?x ?l ?y @t"
T = TimeVar("t")
AT, W1, W2 = datetime(1998, 6, 15), datetime(1998, 6, 1), datetime(1998, 6, 11)
SHAPE_WINDOW = (datetime(2024, 1, 14), datetime(2024, 1, 17))
NARROW = (datetime(2024, 1, 15, 9), datetime(2024, 1, 15, 16))
#: Labels of each shape on TRIP10 and on SKEW, read from one embedding live at 2024-01-15 12:00 (fixed values).
TRIP10_LABELS = {
    "star3": "g3 g0 g2",
    "star4": "g3 g0 g2 g2",
    "star5": "g3 g0 g2 g2 g7",
    "chain3": "g3 g2 g6",
    "chain4": "g3 g2 g6 g2",
    "chain5": "g3 g2 g6 g2 g8",
    "circle3": "g3 g3 g9",
    "circle4": "g3 g2 g5 g2",
    "circle5": "g3 g2 g0 g5 g1",
    "diamond": "g3 g3 g0 g7",
    "clique4": "g3 g0 g9 g2 g3 g7",
    "clique5": "g2 g3 g0 g9 g5 g8 g7 g2 g3 g7",
}
SKEW_LABELS = {
    "star3": "v6 v4 v1",
    "star4": "v9 v1 v5 v8",
    "star5": "v2 v1 v5 v0 v10",
    "chain3": "v6 v8 v0",
    "chain4": "v2 v0 v7 v1",
    "chain5": "v3 v0 v2 v3 v5",
    "circle3": "v6 v1 v6",
    "circle4": "v4 v5 v1 v2",
    "circle5": "v1 v4 v10 v6 v6",
    "diamond": "v6 v1 v4 v2",
    "clique4": "v4 v2 v4 v0 v7 v2",
    "clique5": "v5 v3 v0 v3 v0 v12 v2 v4 v0 v10",
}
MONO_LABELS = {s: " ".join(["link"] * len(arcs(s))) for s in SHAPES}


def _window(q: PatternQuery, lo: datetime, hi: datetime) -> PatternQuery:
    return q.with_clauses(OrderClause(Const(lo), T), OrderClause(T, Const(hi)))


def _solved(q: PatternQuery | str, g: str, **options):
    q = parse(q) if isinstance(q, str) else q
    return lambda spark, d: solve.solve(q, graph(spark, d, g), **options)


def _indexed(q: PatternQuery, g: str, **options):
    """On the stored graph: edges by folder, orders from stored statistics, as queries on a built index."""
    return lambda spark, d: solve.solve(q, stored(spark, d, g).graph, **options)


def _plain(q: PatternQuery, name: str, where: str) -> str:
    """Bindings over the distinct triples of edges that meet a condition."""
    return pattern_sql(q.with_time(T), name, mode="none", source=f"(SELECT DISTINCT s, p, o FROM e WHERE {where})")


def _two(text: str) -> str:
    return pattern_sql(plan.normalise(parse(text)), "SHIP")


def register(r: Registry) -> None:
    _strategies(r)
    _clauses(r)
    _windows(r)
    _logs(r)
    _shapes(r)
    _stored(r)


def _strategies(r: Registry) -> None:
    named = {"pair": (PAIR, "SHIP"), "triangle": (TRIANGLE, "TRIP10"), "square_kg": (SQUARE, "KG"), "biclique": (BICLIQUE, "SHIP"), "mono_triangle": (MONO, "MONO")}
    for name, (text, g) in named.items():
        sql = stepwise_sql(parse(text), g) if name == "square_kg" else pattern_sql(parse(text), g)
        for s in ("JF", "TF", "LC"):
            r.add(f"{s.lower()}_{name}", _solved(text, g, strategy=s, route="pairwise"), sql)
        if name != "mono_triangle":
            r.add(f"gj_{name}", _solved(text, g, strategy="LC", route="generic"), sql)
            r.add(f"hc_{name}", _solved(text, g, strategy="LC", route="cells"), sql)
            r.add(f"pairwise_{name}", _solved(text, g, order=[*parse(text).nodes, "t"], route="pairwise"), sql)
    clique = shape_query("clique4", TRIP10_LABELS["clique4"].split())
    r.add("gj_clique4", _solved(clique, "TRIP10", strategy="LC", route="generic"), pattern_sql(clique, "TRIP10"))
    r.add("hc_clique4", _solved(clique, "TRIP10", strategy="LC", route="cells"), pattern_sql(clique, "TRIP10"))
    for name, q, g in (("triangle", parse(TRIANGLE), "TRIP10"), ("clique4", clique, "TRIP10"), ("pair", parse(PAIR), "SHIP")):
        r.add(f"lca_{name}", _solved(q, g, strategy="LC_adaptive"), pattern_sql(q, g))
    for estimate in plan.TIME_ESTIMATES:
        r.add(f"lc_triangle_{estimate}", _solved(TRIANGLE, "TRIP10", strategy="LC", route="pairwise", time_estimate=estimate), pattern_sql(parse(TRIANGLE), "TRIP10"))
    r.add("lc_user_order", _solved(PAIR, "SHIP", order=["x", "t", "z", "y"], route="generic"), pattern_sql(parse(PAIR), "SHIP"))
    # timeless
    path = parse("?o placed_by ?c @t ; ?c in_nation ?n @t ; ?n in_region r1 @t")
    r.add("bgp_static_path", lambda s, d: solve.ever(path, graph(s, d, "KG")), _plain(path, "KG", "TRUE"))
    r.add("bgp_static_triangle", lambda s, d: solve.ever(parse(MONO), graph(s, d, "MONO")), _plain(parse(MONO), "MONO", "TRUE"))
    r.add("ever_triangle", lambda s, d: solve.ever(parse(TRIANGLE), graph(s, d, "TRIP10")), _plain(parse(TRIANGLE), "TRIP10", "TRUE"))
    doc = parse("?d in_lang de @t ; ?d from_source ?s @t ; ?d quality q1 @t")
    r.add("bgp_doc_lang_source", lambda s, d: solve.ever(doc, graph(s, d, "DOC")), _plain(doc, "DOC", "TRUE"))
    r.add("ever_pair", lambda s, d: solve.ever(parse(PAIR), graph(s, d, "SHIP")), _plain(parse(PAIR), "SHIP", "TRUE"))
    # baselines
    turn = parse("?x user ?n @t ; ?y assistant ?n @t")
    r.add("expanded_pair_turn", lambda s, d: baselines.expanded(turn, graph(s, d, "TURN")), pattern_sql(turn, "TURN"))
    r.add("expanded_mono_triangle", lambda s, d: baselines.expanded(parse(MONO), graph(s, d, "MONO")), pattern_sql(parse(MONO), "MONO"))
    for key, run in (("sweep", lambda q, g: baselines.sweep(q, g)), ("h_jf", lambda q, g: solve.solve(q, g, "JF")), ("h_lc", lambda q, g: solve.solve(q, g, "LC")), ("h_tf", lambda q, g: solve.solve(q, g, "TF"))):
        r.add(f"{key}_pair", lambda s, d, run=run: run(parse(PAIR), graph(s, d, "SHIP")), pattern_sql(parse(PAIR), "SHIP"))
        r.add(f"{key}_triangle", lambda s, d, run=run: run(parse(TRIANGLE), graph(s, d, "TRIP10")), pattern_sql(parse(TRIANGLE), "TRIP10"))
    for shape in SHAPES:
        q = shape_query(shape, TRIP10_LABELS[shape].split())
        r.add(f"win_shape_{shape}", lambda s, d, q=q: baselines.window_join(q, graph(s, d, "TRIP10"), *SHAPE_WINDOW), pattern_sql(_window(q, *SHAPE_WINDOW), "TRIP10"))
    r.add("clause_table_turn", lambda s, d: baselines.clause_table(graph(s, d, "TURN")), over("TURN", "SELECT a.at AS w1, b.at AS w2 FROM (SELECT ts AS at FROM e UNION SELECT te FROM e) a JOIN (SELECT ts AS at FROM e UNION SELECT te FROM e) b ON a.at <= b.at"))
    # plans and bounds
    r.add("order_choice", _order_choice)
    r.add("agm_inputs", lambda s, d: bounds.sizes(parse(TRIANGLE), graph(s, d, "TRIP10"), "triples"), over("TRIP10", "SELECT (SELECT count(*) FROM (SELECT DISTINCT s, o FROM e WHERE p = 'g3')) AS n0, (SELECT count(*) FROM (SELECT DISTINCT s, o FROM e WHERE p = 'g3')) AS n1, (SELECT count(*) FROM (SELECT DISTINCT s, o FROM e WHERE p = 'g9')) AS n2"))
    sizes = "SELECT (SELECT count(*) FROM (SELECT DISTINCT s, o FROM e WHERE p = 'g3')) AS a, (SELECT count(*) FROM (SELECT DISTINCT s, o FROM e WHERE p = 'g9')) AS c"
    r.add("agm_bound", _agm, over("TRIP10", f"SELECT CAST(least(a * sqrt(c), a * a, a * c) AS DOUBLE) AS bound FROM ({sizes})"))
    plain = _plain(parse(TRIANGLE), "TRIP10", "TRUE")
    answers = plain[plain.index("\nSELECT") + 1 :]
    r.add("bound_check", _bound_check, f"WITH {graph_ctes('TRIP10')}, q AS ({answers})\nSELECT (SELECT count(*) FROM q) AS answers, (SELECT count(*) FROM q) <= least(a * sqrt(c), a * a, a * c) AS within_bound FROM ({sizes})")


def _order_choice(spark, d):
    g = graph(spark, d, "TRIP10")
    q = parse(TRIANGLE)
    stats = plan.statistics(q, g, exact=True)
    rows = [(s, e, ",".join(plan.greedy(q, stats, s, e))) for s in plan.STRATEGIES for e in plan.TIME_ESTIMATES]
    return spark.createDataFrame(rows, "strategy string, estimate string, binding_order string")


def _agm(spark, d):
    g = graph(spark, d, "TRIP10")
    row = bounds.sizes(parse(TRIANGLE), g, "triples").first()
    return spark.createDataFrame([(bounds.agm(parse(TRIANGLE), [row[f"n{i}"] for i in range(3)], times=False),)], "bound double")


def _bound_check(spark, d):
    g, q = graph(spark, d, "TRIP10"), parse(TRIANGLE)
    n = solve.ever(q, g).count()
    return spark.createDataFrame([(n, cost.bound_ratio(q, g, n) <= 1.0)], "answers long, within_bound boolean")


def _clauses(r: Registry) -> None:
    two = "?x ships_R ?z @t1 ; ?y ships_A ?z @t2"
    texts = {
        "pq_two_times": f"{two} ; @t1 <= @t2",
        "pq_order_clause": "s7 ships_R ?z @t1 ; ?y ships_A ?z @t2 ; @t2 <= @t1",
        "pq_strict": "s7 ships_R ?z @t1 ; ?y ships_A ?z @t2 ; @t1 < @t2",
        "pq_free_times": "s7 ships_R ?z @t1 ; ?y ships_A ?z @t2",
        "pq_const_bounds": "?x ships_R ?z @t ; @t <= @'1998-06-15' ; @'1998-06-01' <= @t",
        "pq_before_after": "s7 ships_R ?z @t1 ; s7 ships_A ?w @t2 ; @t1 <= @'1998-06-15 12:00:00' ; @'1998-06-15 12:00:00' <= @t2",
        "pq_three_times_chain": "s7 ships_R ?z @t1 ; ?y ships_A ?z @t2 ; ?v ships_N ?z @t3 ; @t1 <= @t2 ; @t2 <= @t3",
        "pq_offset_clause": "s7 ships_R ?z @t1 ; ?y ships_A ?z @t2 ; @t1 <= @t2 + 864000000000 ; @t2 <= @t1 + 864000000000",
        "pq_equal_times": "s7 ships_R ?z @t1 ; ?y ships_A ?z @t2 ; @t1 = @t2",
        "pq_constant_instant": "?x ships_R ?z @'1998-06-15' ; ?y ships_A ?z @t",
    }
    for key, text in texts.items():
        r.add(key, _solved(text, "SHIP", strategy="LC", route="pairwise", products=key == "pq_before_after"), _two(text))
    r.add("pq_two_times_generic", _solved(texts["pq_two_times"], "SHIP", strategy="LC", route="generic"), _two(texts["pq_two_times"]))
    r.add("pq_two_times_jf", _solved(texts["pq_two_times"], "SHIP", strategy="JF"), _two(texts["pq_two_times"]))
    r.add("pq_together", lambda s, d: solve.all_instants("?x u3 ?z ; ?y u5 ?z", graph(s, d, "TRIP")), pattern_sql(parse("?x u3 ?z @t ; ?y u5 ?z @t"), "TRIP"))
    r.add("pq_clause_only_time", _solved("s7 ships_R ?z @t1 ; @t1 <= @t2 ; @t2 <= @'1998-06-15'", "SHIP", strategy="JF"), _two("s7 ships_R ?z @t1 ; @t1 <= @t2 ; @t2 <= @'1998-06-15'"))
    multi = [q for q in kg_log() if len(q.patterns) > 1]
    for i, q in enumerate(multi[:6], 1):
        q2 = two_times(q, seed=i)
        r.add(f"two_time_{i:02d}", _solved(q2, "KG", strategy="LC" if i % 2 else "JF", route="pairwise"), pattern_sql(q2, "KG"))
    r.add("pq_explicit_filter", _pairs, _two("s7 ships_R ?z @t1 ; ?y ships_A ?z @t2 ; @t1 <= @t2"))


def _pairs(spark, d):
    """The clause handled as a filter on the joined edges, without ranges clipped on the way (reference for clamping)."""
    g = graph(spark, d, "SHIP")
    q = parse("s7 ships_R ?z @t1 ; ?y ships_A ?z @t2")
    df = pairwise.run(q, g, ["z", "y", "t1", "t2"])
    df = df.filter(F.col("t1_from") < F.col("t2_to"))
    return df.withColumns({"t1_to": F.least("t1_to", "t2_to"), "t2_from": F.greatest("t1_from", "t2_from")})


def _windows(r: Registry) -> None:
    pair, edge = parse(PAIR), parse(EDGE)
    sql = {"snap": f"ts <= TIMESTAMP '{AT}' AND te > TIMESTAMP '{AT}'", "any": f"ts < TIMESTAMP '{W2}' AND te > TIMESTAMP '{W1}'", "all": f"ts <= TIMESTAMP '{W1}' AND te >= TIMESTAMP '{W2}'"}
    run = {"snap": lambda q, g: solve.snapshot(q, g, AT), "any": lambda q, g: solve.during_any(q, g, W1, W2), "all": lambda q, g: solve.during_all(q, g, W1, W2)}
    for k in sql:
        for name, q in (("pair", pair), ("edges", edge)):
            r.add(f"{k}_{name}", lambda s, d, k=k, q=q: run[k](q, graph(s, d, "SHIP")), _plain(q, "SHIP", sql[k]))
    mono = (datetime(2024, 1, 10), datetime(2024, 1, 13))
    r.add("within_mono_triangle", lambda s, d: solve.within(parse(MONO), graph(s, d, "MONO"), *mono, strategy="LC"), pattern_sql(_window(parse(MONO), *mono), "MONO"))
    days20 = "least(a0.te, a1.te) - greatest(a0.ts, a1.ts) >= INTERVAL 20 DAY"
    r.add("dur_pair", lambda s, d: solve.durable(pair, graph(s, d, "SHIP"), 20 * 86_400_000_000), pattern_sql(pair, "SHIP", extra=days20))
    trip = parse("?x u3 ?z @t ; ?y u5 ?z @t")
    r.add("dur_together", lambda s, d: solve.durable(trip, graph(s, d, "TRIP"), 3_600_000_000), pattern_sql(trip, "TRIP", extra="least(a0.te, a1.te) - greatest(a0.ts, a1.ts) >= INTERVAL 1 HOUR"))
    one = parse("?x ships_R ?z @t")
    hit = f"SELECT DISTINCT s, p, o FROM e WHERE p = 'ships_R' AND {sql['any']}"
    r.add("list_matches", lambda s, d: versions.list_matches(one, graph(s, d, "SHIP"), W1, W2), over("SHIP", hit))
    s7 = parse("s7 ships_R ?z @t")
    clip = f"greatest(ts, TIMESTAMP '{W1}') AS t_from, least(te, TIMESTAMP '{W2}') AS t_to"
    r.add("list_ranges", lambda s, d: versions.list_ranges(s7, graph(s, d, "SHIP"), W1, W2), over("SHIP", f"SELECT s, p, o, {clip} FROM e WHERE s = 's7' AND p = 'ships_R' AND {sql['any']}"))
    r.add("ranges_per_match", lambda s, d: results.as_arrays(graph(s, d, "SHIP").frame.filter("s = 's7'").select("s", "p", "o", F.col("ts").alias("t_from"), F.col("te").alias("t_to")), ["s", "p", "o"]).select("s", "p", "o", F.size("ranges").alias("n"), F.col("ranges")[0]["from"].alias("first_from"), F.element_at("ranges", -1)["to"].alias("last_to")), over("SHIP", "SELECT s, p, o, CAST(count(*) AS INT) AS n, min(ts) AS first_from, max(te) AS last_to FROM e WHERE s = 's7' GROUP BY s, p, o"))
    live = lambda x: f"(SELECT s, p, o FROM e WHERE ts <= TIMESTAMP '{x}' AND te > TIMESTAMP '{x}')"
    r.add("version_diff", lambda s, d: versions.diff(graph(s, d, "SHIP"), W1, AT), over("SHIP", f"SELECT *, 'added' AS change FROM ({live(AT)} EXCEPT {live(W1)}) UNION ALL SELECT *, 'removed' FROM ({live(W1)} EXCEPT {live(AT)})"))
    r.add("change_log", lambda s, d: versions.changes(graph(s, d, "SHIP"), W1, W2), over("SHIP", f"SELECT * FROM (SELECT s, p, o, ts AS at, 1 AS sign FROM e UNION ALL SELECT s, p, o, te, -1 FROM e) WHERE at >= TIMESTAMP '{W1}' AND at < TIMESTAMP '{W2}'"))
    r.add("snapshot_sizes", lambda s, d: versions.snapshot_sizes(graph(s, d, "SHIP")), over("SHIP", "SELECT at, CAST(sum(sum(d)) OVER (ORDER BY at) AS BIGINT) AS live FROM (SELECT ts AS at, 1 AS d FROM e UNION ALL SELECT te, -1 FROM e) GROUP BY at"))
    ticks = "line AS (SELECT at, row_number() OVER (ORDER BY at) AS k FROM (SELECT ts AS at FROM e UNION SELECT te FROM e))"
    inner = pattern_sql(pair, "SHIP")
    body = inner[inner.index("\nSELECT") + 1 :]
    r.add("count_points", lambda s, d: results.count_points(solve.solve(pair, (g := graph(s, d, "SHIP")), "JF"), g), f"WITH {graph_ctes('SHIP')},\n{ticks}, q AS ({body})\nSELECT CAST(sum(y.k - x.k) AS BIGINT) AS points FROM q JOIN line x ON x.at = q.t_from JOIN line y ON y.at = q.t_to")
    for key, text, test in (("count_pairs", "s7 ships_R ?z @t1 ; ?y ships_A ?z @t2 ; @t1 <= @t2", "greatest(0, d.k - greatest(c.k, x.k))"), ("count_pairs_free", "s7 ships_R ?z @t1 ; ?y ships_A ?z @t2", "d.k - c.k")):
        two = _two(text)
        held = two[two.index("\nSELECT") + 1 :]
        r.add(key, lambda s, d, t=text, o="greatest" in test: results.count_pairs(solve.solve(t, (g := graph(s, d, "SHIP")), "JF"), g, ordered=o), f"WITH {graph_ctes('SHIP')},\n{ticks}, q AS ({held})\nSELECT CAST(sum({test}) AS BIGINT) AS points FROM q JOIN line c ON c.at = q.t2_from JOIN line d ON d.at = q.t2_to JOIN line x ON x.at >= q.t1_from AND x.at < q.t1_to")
    r.add("points_mono", lambda s, d: results.points(solve.solve(_window(parse(MONO), *mono), (g := graph(s, d, "MONO"))), g), _points_sql(_window(parse(MONO), *mono)))
    for name, text, g in (("semijoin_reduction", "s7 ships_R ?p @t ; ?p sold_to ?c @t", "KGT"), ("semijoin_chain", "s7 ships_R ?p @t ; ?p sold_to ?c @t ; ?c in_nation ?n @t ; ?n in_region r1 @t", "KG"), ("semijoin_star", "?x ships_R p4 @t ; ?x ships_A ?q @t ; ?x in_nation ?n @t", "KG")):
        r.add(name, _solved(text, g, strategy="LC", route="reduced"), stepwise_sql(parse(text), g))


def _points_sql(q: PatternQuery) -> str:
    inner = pattern_sql(q, "MONO")
    body = inner[inner.index("\nSELECT") + 1 :]
    return f"WITH {graph_ctes('MONO')},\nline AS (SELECT ts AS t FROM e UNION SELECT te FROM e), q AS ({body})\nSELECT q.x, q.y, q.z, line.t FROM q JOIN line ON line.t >= q.t_from AND line.t < q.t_to"


def _logs(r: Registry) -> None:
    for i, q in enumerate(kg_log(), 1):
        route = ("pairwise", "generic")[i % 2] if len(q.patterns) > 1 else "pairwise"
        r.add(f"kg_log_{i:02d}", _indexed(q, "KG", strategy=("LC", "JF")[i % 2], route=route), stepwise_sql(q, "KG") if i == 9 else pattern_sql(q, "KG"))
    for i, q in enumerate(kgt_log(), 1):
        r.add(f"kgt_log_{i:02d}", _indexed(q, "KGT", strategy=("LC", "TF", "JF")[i % 3], route="pairwise"), stepwise_sql(q, "KGT") if i == 6 else pattern_sql(q, "KGT"))


def _shapes(r: Registry) -> None:
    for shape in SHAPES:
        q = shape_query(shape, TRIP10_LABELS[shape].split())
        for tag, w in (("w100", None), ("w10", SHAPE_WINDOW), ("w01", NARROW)):
            q2 = q if w is None else _window(q, *w)
            r.add(f"{shape}_{tag}", _indexed(q2, "TRIP10", strategy="LC" if tag == "w100" else "TF", route="pairwise"), pattern_sql(q2, "TRIP10"))
        for s in ("lc", "tf"):
            r.add(f"{shape}_{s}", _indexed(q, "TRIP10", strategy=s.upper(), route="pairwise"), pattern_sql(q, "TRIP10"))
    for name, labels in (("SKEW", SKEW_LABELS), ("MONO", MONO_LABELS)):
        for shape, ls in labels.items():
            q = _window(shape_query(shape, ls.split()), *(SHAPE_WINDOW if name == "SKEW" else (datetime(2024, 1, 15), datetime(2024, 1, 15))))
            r.add(f"{name.lower()}_{shape}", _indexed(q, name, strategy="TF", route="pairwise"), stepwise_sql(q, name))


def stored(spark, d: str, name: str, pack: bool = False) -> store.Store:
    """A graph's store, built once a session and table folder."""
    key = (spark.sparkContext.applicationId, d, name, pack)
    if key not in _STORES:
        path = store.shared_folder(spark, f"graph-{name}")
        store.save(graph(spark, d, name), path, pack=pack)
        _STORES[key] = store.open_store(spark, path)
    return _STORES[key]


_STORES: dict[tuple, store.Store] = {}


def _stored(r: Registry) -> None:
    """Queries on stored graphs: edges by folder, orders from stored statistics, windows from the matrices alone."""
    for name, text, g in (("pair", PAIR, "SHIP"), ("triangle", TRIANGLE, "TRIP10"), ("square_kg", SQUARE, "KG"), ("biclique", BICLIQUE, "SHIP")):
        q = parse(text)
        sql = stepwise_sql(q, g) if name == "square_kg" else pattern_sql(q, g)
        for s in ("JF", "LC", "TF"):
            r.add(f"ix_{s.lower()}_{name}", lambda sp, d, q=q, g=g, s=s: solve.solve(q, stored(sp, d, g).graph, strategy=s, route="pairwise"), sql)
    pair = parse(PAIR)
    days20 = "least(a0.te, a1.te) - greatest(a0.ts, a1.ts) >= INTERVAL 20 DAY"
    r.add("ix_dur", lambda s, d: solve.durable(pair, stored(s, d, "SHIP").graph, 20 * 86_400_000_000), pattern_sql(pair, "SHIP", extra=days20))
    at, lo, hi = datetime(2024, 1, 12), datetime(2024, 1, 10), datetime(2024, 1, 13)
    when = {"at": f"ts <= TIMESTAMP '{at}' AND te > TIMESTAMP '{at}'", "any": f"ts < TIMESTAMP '{hi}' AND te > TIMESTAMP '{lo}'", "all": f"ts <= TIMESTAMP '{lo}' AND te >= TIMESTAMP '{hi}'"}
    window = {"at": (at, None), "any": (lo, hi), "all": (lo, hi)}
    for mode, key in (("at", "snap"), ("any", "any"), ("all", "all")):
        r.add(f"ix_{key}", lambda s, d, m=mode: store.by_matrix(parse(MONO), stored(s, d, "MONO", True), m, *window[m]), _plain(parse(MONO), "MONO", when[mode]))
        r.add(f"ix_{key}_edges", lambda s, d, m=mode: stored(s, d, "MONO", True).triples(m, *window[m]), over("MONO", f"SELECT DISTINCT s, p, o FROM e WHERE {when[mode]}"))
