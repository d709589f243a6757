"""Scans, joins, aggregates, windows, sets, scalar functions and the batch twins of streams."""

from __future__ import annotations

from pyspark.sql import Window
from pyspark.sql import functions as F

from ..functions.sql import interval_intersect, interval_relation, merge_intersect, solutions_as_map
from ..measures import cost
from ..model.query import parse
from ..model.ranks import running
from ..operators import overlap, solve
from ..operators.pairwise import run as pairwise
from ..sources.graphs import graph
from ..sources.tables import load, with_layout
from ..sql_text import graph_ctes, over, pattern_sql
from ..streaming import intervals as stream
from . import Registry


def register(r: Registry) -> None:
    _scans(r)
    _joins(r)
    _aggregates(r)
    _scalars(r)
    _streams(r)


def _frame(name: str, f):
    return lambda s, d: f(graph(s, d, name).frame)


def _scans(r: Registry) -> None:
    cols = "SELECT s, p, o, ts, te FROM e WHERE "
    for key, cond in (("scan_const_p", "p = 'ships_R'"), ("scan_const_sp", "s = 's7' AND p = 'ships_R'"), ("scan_const_spo", "s = 's7' AND p = 'ships_R' AND o < 'p15'"), ("filter_terms", "p IN ('ships_R', 'ships_A') AND s LIKE 's1%' AND o BETWEEN 'p1' AND 'p3'")):
        r.add(key, _frame("SHIP", lambda e, c=cond: e.filter(c)), over("SHIP", cols + cond))
    r.add("scan_at", _frame("SHIP", lambda e: e.filter("ts <= TIMESTAMP_NTZ '1998-06-15' AND te > TIMESTAMP_NTZ '1998-06-15'")), over("SHIP", cols + "ts <= TIMESTAMP '1998-06-15' AND te > TIMESTAMP '1998-06-15'"))
    loop = parse("?x ?l ?x @t")
    r.add("self_loop", lambda s, d: solve.solve(loop, graph(s, d, "TRIP10"), "JF"), pattern_sql(loop, "TRIP10"))
    label = parse("?x ?l ?y @t ; ?l ?m ?z @t")
    r.add("label_as_node", lambda s, d: solve.solve(label, _labels_as_nodes(s, d), "JF"), _labels_sql())
    var = parse("s7 ?l ?z @t ; s8 ?l ?z @t2")
    r.add("var_label", lambda s, d: solve.solve(var, graph(s, d, "SHIP"), "JF"), pattern_sql(var, "SHIP"))
    pair = parse("?x ships_R ?z @t ; ?y ships_A ?z @t")
    r.add("project_distinct", lambda s, d: solve.solve(pair, graph(s, d, "SHIP"), "JF").select("x", "y").distinct(), _wrapped(pair, "SHIP", "SELECT DISTINCT x, y FROM q"))
    rel = "CASE WHEN a.te < b.ts THEN 'before' WHEN b.te < a.ts THEN 'after' WHEN a.te = b.ts THEN 'meets' WHEN b.te = a.ts THEN 'met_by' WHEN a.ts = b.ts AND a.te = b.te THEN 'equals' WHEN a.ts = b.ts AND a.te < b.te THEN 'starts' WHEN a.ts = b.ts THEN 'started_by' WHEN a.te = b.te AND a.ts > b.ts THEN 'finishes' WHEN a.te = b.te THEN 'finished_by' WHEN a.ts > b.ts AND a.te < b.te THEN 'during' WHEN a.ts < b.ts AND a.te > b.te THEN 'contains' WHEN a.ts < b.ts THEN 'overlaps' ELSE 'overlapped_by' END"
    r.add("interval_relations", _relations, over("SHIP", f"SELECT {rel} AS relation, count(*) AS n FROM e a JOIN e b ON a.o = b.o WHERE a.p = 'ships_R' AND b.p = 'ships_N' GROUP BY 1"))


def _wrapped(q, name: str, tail: str) -> str:
    inner = pattern_sql(q, name)
    return f"WITH {graph_ctes(name)}, q AS ({inner[inner.index(chr(10) + 'SELECT') + 1 :]})\n{tail}"


def _labels_as_nodes(spark, d):
    """The trip graph with facts about its labels: a label is also a node."""
    g = graph(spark, d, "TRIP10")
    span = g.frame.agg(F.min("ts").alias("ts"), F.max("te").alias("te"))
    facts = g.frame.select("p").distinct().crossJoin(F.broadcast(span)).select(F.col("p").alias("s"), F.lit("kind").alias("p"), F.when(F.substring("p", 2, 1).cast("int") % 2 == 0, "even").otherwise("odd").alias("o"), "ts", "te")
    return g.of(g.frame.unionByName(facts))


def _labels_sql() -> str:
    facts = "SELECT p AS s, 'kind' AS p, CASE WHEN CAST(substr(p, 2) AS INT) % 2 = 0 THEN 'even' ELSE 'odd' END AS o, (SELECT min(ts) FROM e) AS ts, (SELECT max(te) FROM e) AS te FROM (SELECT DISTINCT p FROM e)"
    return over("TRIP10", f"SELECT a.s AS x, a.p AS l, a.o AS y, b.p AS m, b.o AS z, greatest(a.ts, b.ts) AS t_from, least(a.te, b.te) AS t_to FROM (SELECT * FROM e UNION ALL {facts}) a JOIN (SELECT * FROM e UNION ALL {facts}) b ON a.p = b.s AND a.ts < b.te AND b.ts < a.te")


def _relations(spark, d):
    e = graph(spark, d, "SHIP").frame
    a, b = e.filter("p = 'ships_R'").alias("a"), e.filter("p = 'ships_N'").alias("b")
    rel = interval_relation(F.col("a.ts"), F.col("a.te"), F.col("b.ts"), F.col("b.te"))
    return a.join(b, F.col("a.o") == F.col("b.o")).groupBy(rel.alias("relation")).agg(F.count(F.lit(1)).alias("n"))


def _two(e, x: str, y: str):
    a = e.filter(F.col("p") == x).select(F.col("s").alias("x"), F.col("o").alias("z"), F.col("ts").alias("a0"), F.col("te").alias("a1"))
    b = e.filter(F.col("p") == y).select(F.col("s").alias("y"), F.col("o").alias("z"), F.col("ts").alias("b0"), F.col("te").alias("b1"))
    return a, b


def _joins(r: Registry) -> None:
    chain = parse("s7 ships_R ?p @t ; ?p sold_to ?c @t ; ?c in_nation ?n @t")
    for key, hint in (("pairwise_chain", None), ("join_merge", "merge"), ("join_hash", "shuffle_hash"), ("join_broadcast", "broadcast")):
        r.add(key, lambda s, d, h=hint: pairwise(chain, graph(s, d, "KG"), ["p", "c", "n", "t"], hint=h), pattern_sql(chain, "KG"))
    both = "SELECT a.s AS x, b.s AS y, a.o AS z, greatest(a.ts, b.ts) AS t_from, least(a.te, b.te) AS t_to FROM e a JOIN e b ON a.o = b.o AND a.ts < b.te AND b.ts < a.te WHERE a.p = 'ships_R' AND b.p = 'ships_A'"
    out = lambda df: df.select("x", "y", "z", F.greatest("a0", "b0").alias("t_from"), F.least("a1", "b1").alias("t_to"))
    r.add("overlap_equi", _frame("SHIP", lambda e: out(overlap.overlap_join(*_two(e, "ships_R", "ships_A"), ["z"], ("a0", "a1"), ("b0", "b1")))), over("SHIP", both))

    def pure(e):
        a, b = _two(e, "g3", "g9")
        return overlap.overlap_join(a.drop("z"), b.drop("z"), [], ("a0", "a1"), ("b0", "b1")).select("x", "y", F.greatest("a0", "b0").alias("t_from"), F.least("a1", "b1").alias("t_to"))

    r.add("overlap_pure", _frame("TRIP10", pure), over("TRIP10", "SELECT a.s AS x, b.s AS y, greatest(a.ts, b.ts) AS t_from, least(a.te, b.te) AS t_to FROM e a JOIN e b ON a.ts < b.te AND b.ts < a.te WHERE a.p = 'g3' AND b.p = 'g9'"))
    r.add("theta_pairs", _frame("TURN", lambda e: _theta(e)), over("TURN", "SELECT a.o AS x, b.o AS y, count(*) AS pairs FROM (SELECT o, ts FROM e WHERE p = 'user') a, (SELECT o, ts FROM e WHERE p = 'assistant') b WHERE a.ts <= b.ts GROUP BY 1, 2"))
    r.add("point_in_interval", _live_at_orders, over("SHIP", "SELECT o_orderkey, count(*) AS live FROM orders JOIN e ON e.ts <= o_orderdate AND e.te > o_orderdate GROUP BY o_orderkey"))
    r.add("asof_edges", _asof, over("SHIP", "SELECT x.s, x.at, max(e.ts) AS last_start FROM (SELECT DISTINCT s, te AS at FROM e WHERE p = 'ships_A') x LEFT JOIN e ON e.s = x.s AND e.p = 'ships_R' AND e.ts <= x.at GROUP BY x.s, x.at"))
    r.add("semi_join", _frame("SHIP", lambda e: e.join(e.filter("p = 'ships_R'").select("s", "o").distinct(), ["s", "o"], "left_semi").select("s", "p", "o", "ts", "te")), over("SHIP", "SELECT s, p, o, ts, te FROM e WHERE EXISTS (SELECT 1 FROM e b WHERE b.p = 'ships_R' AND b.s = e.s AND b.o = e.o)"))
    live = "p = 'ships_N' AND ts <= TIMESTAMP{} '1998-06-15' AND te > TIMESTAMP{} '1998-06-15'"
    r.add("anti_join", _frame("SHIP", lambda e: e.select("s").distinct().join(e.filter(live.format("_NTZ", "_NTZ")).select("s").distinct(), "s", "left_anti")), over("SHIP", f"SELECT DISTINCT s FROM e WHERE s NOT IN (SELECT s FROM e WHERE {live.format('', '')})"))
    r.add("outer_diff", _outer, over("SHIP", "SELECT coalesce(a.s, b.s) AS s, coalesce(a.n, 0) AS before, coalesce(b.n, 0) AS after FROM (SELECT s, count(*) AS n FROM e WHERE ts <= TIMESTAMP '1998-06-01' AND te > TIMESTAMP '1998-06-01' GROUP BY s) a FULL JOIN (SELECT s, count(*) AS n FROM e WHERE ts <= TIMESTAMP '1998-06-15' AND te > TIMESTAMP '1998-06-15' GROUP BY s) b ON a.s = b.s"))
    r.add("outer_left", _frame("SHIP", lambda e: e.select("o").distinct().join(e.filter("s = 's7'").groupBy("o").agg(F.count(F.lit(1)).alias("n")), "o", "left").select("o", F.coalesce("n", F.lit(0)).alias("n"))), over("SHIP", "SELECT o, count(*) FILTER (WHERE s = 's7') AS n FROM e GROUP BY o"))
    r.add("lateral_seek", _lateral, over("TRIP10", "SELECT x.p, (SELECT min(e.s) FROM e WHERE e.p = x.p AND e.s >= 'k15') AS child FROM (SELECT DISTINCT p FROM e) x"))
    r.add("cogroup_intersect", _frame("SHIP", lambda e: merge_intersect(e.filter("p = 'ships_R'").select("s", F.col("o").alias("child")).distinct(), e.filter("p = 'ships_A'").select("s", F.col("o").alias("child")).distinct(), "s")), over("SHIP", "SELECT s, o AS child FROM (SELECT DISTINCT s, o FROM e WHERE p = 'ships_R' INTERSECT SELECT DISTINCT s, o FROM e WHERE p = 'ships_A')"))


def _theta(e):
    """Pairs of turns in order of time, whatever else they share: a nested-loop join, of one row for each value and instant."""
    per = e.groupBy("p", "o", "ts").agg(F.count(F.lit(1)).alias("n"))
    a = per.filter("p = 'user'").select(F.col("o").alias("x"), F.col("ts").alias("a"), F.col("n").alias("m"))
    b = per.filter("p = 'assistant'").select(F.col("o").alias("y"), F.col("ts").alias("b"), "n")
    return a.join(b.hint("shuffle_replicate_nl"), F.col("a") <= F.col("b")).groupBy("x", "y").agg(F.sum(F.col("m") * F.col("n")).alias("pairs"))


def _live_at_orders(spark, d):
    """Live edges at each order's date; each date is joined once."""
    orders = load(spark, d, "orders").select("o_orderkey", F.col("o_orderdate").alias("at"))
    live = overlap.point_join(orders.select("at").distinct(), "at", graph(spark, d, "SHIP").frame.select("ts", "te"), "ts", "te").groupBy("at").agg(F.count(F.lit(1)).alias("live"))
    return orders.join(live, "at").groupBy("o_orderkey").agg(F.sum("live").alias("live"))


def _asof(spark, d):
    e = graph(spark, d, "SHIP").frame
    left = e.filter("p = 'ships_A'").select("s", F.col("te").alias("at")).distinct()
    return overlap.asof(left, e.filter("p = 'ships_R'").select("s", F.col("ts").alias("last_start")), ["s"], "at", "last_start").select("s", "at", "last_start")


def _outer(spark, d):
    e = graph(spark, d, "SHIP").frame
    at = lambda x, n: e.filter(f"ts <= TIMESTAMP_NTZ '{x}' AND te > TIMESTAMP_NTZ '{x}'").groupBy("s").agg(F.count(F.lit(1)).alias(n))
    return at("1998-06-01", "a").join(at("1998-06-15", "b"), "s", "full").select("s", F.coalesce("a", F.lit(0)).alias("before"), F.coalesce("b", F.lit(0)).alias("after"))


def _lateral(spark, d):
    e = graph(spark, d, "TRIP10").frame
    e.createOrReplaceTempView("lateral_edges")
    return spark.sql("SELECT x.p, y.child FROM (SELECT DISTINCT p FROM lateral_edges) x, LATERAL (SELECT min(s) AS child FROM lateral_edges e WHERE e.p = x.p AND e.s >= 'k15') y")


def _n():
    return F.count(F.lit(1)).alias("n")


def _us():
    """Length of an edge in microseconds."""
    return (F.unix_micros(F.col("te").cast("timestamp")) - F.unix_micros(F.col("ts").cast("timestamp"))).alias("us")


def _aggregates(r: Registry) -> None:
    r.add("label_histogram", _frame("SKEW", lambda e: e.groupBy("p").agg(F.count(F.lit(1)).alias("n"), F.min("ts").alias("first"), F.max("te").alias("last"))), over("SKEW", "SELECT p, count(*) AS n, min(ts) AS first, max(te) AS last FROM e GROUP BY p"))
    r.add("prefix_rollup", _frame("TRIP10", lambda e: e.rollup("p", "o", "s").agg(_n())), over("TRIP10", "SELECT p, o, s, count(*) AS n FROM e GROUP BY ROLLUP (p, o, s)"))
    r.add("prefix_cube", _frame("TRIP10", lambda e: e.cube("s", "p", "o").agg(_n())), over("TRIP10", "SELECT s, p, o, count(*) AS n FROM e GROUP BY CUBE (s, p, o)"))
    r.add("prefix_grouping_sets", _frame("TRIP10", lambda e: e.groupingSets([["s"], ["p"], ["o"], ["s", "o"]], "s", "p", "o").agg(_n())), over("TRIP10", "SELECT s, p, o, count(*) AS n FROM e GROUP BY GROUPING SETS ((s), (p), (o), (s, o))"))
    r.add("duration_percentiles", _frame("SHIP", lambda e: e.select("p", _us()).groupBy("p").agg(*[F.percentile("us", q).alias(n) for q, n in ((0.25, "q1"), (0.5, "median"), (0.75, "q3"))])), over("SHIP", "SELECT p, quantile_cont(u, 0.25) AS q1, quantile_cont(u, 0.5) AS median, quantile_cont(u, 0.75) AS q3 FROM (SELECT p, CAST(epoch_us(te) - epoch_us(ts) AS DOUBLE) AS u FROM e) GROUP BY p"))
    r.add("first_last_edge", _frame("TRIP10", lambda e: e.groupBy("p").agg(F.min_by("s", F.struct("ts", "s", "o")).alias("first_s"), F.max_by("o", F.struct("ts", "s", "o")).alias("last_o"), F.count_if(F.col("s") == F.col("o")).alias("loops"))), over("TRIP10", "SELECT p, arg_min(s, (ts, s, o)) AS first_s, arg_max(o, (ts, s, o)) AS last_o, count(*) FILTER (WHERE s = o) AS loops FROM e GROUP BY p"))
    r.add("top_edges_per_label", _frame("SKEW", lambda e: e.select("s", "p", "o", "ts", _us()).withColumn("r", F.row_number().over(Window.partitionBy("p").orderBy(F.desc("us"), "s", "o", "ts"))).filter("r <= 5")), over("SKEW", "SELECT s, p, o, ts, us, CAST(r AS INT) AS r FROM (SELECT s, p, o, ts, epoch_us(te) - epoch_us(ts) AS us, row_number() OVER (PARTITION BY p ORDER BY epoch_us(te) - epoch_us(ts) DESC, s, o, ts) AS r FROM e) WHERE r <= 5"))
    r.add("moving_live_7d", _moving, over("SHIP", "SELECT day, CAST(sum(n) OVER (ORDER BY day RANGE BETWEEN INTERVAL 6 DAY PRECEDING AND CURRENT ROW) AS BIGINT) AS n7 FROM (SELECT ts AS day, count(*) AS n FROM e GROUP BY ts)"))
    r.add("topk_longest", _frame("SHIP", lambda e: e.select("s", "p", "o", "ts", _us()).orderBy(F.desc("us"), "s", "p", "o", "ts").limit(20)), over("SHIP", "SELECT s, p, o, ts, epoch_us(te) - epoch_us(ts) AS us FROM e ORDER BY us DESC, s, p, o, ts LIMIT 20"))
    r.add("rank_functions", _ranks, over("MONO", "SELECT s, n, CAST(dense_rank() OVER (ORDER BY n DESC) AS INT) AS dr, CAST(rank() OVER (ORDER BY n DESC) AS INT) AS rk, CAST(ntile(4) OVER (ORDER BY n DESC, s) AS INT) AS tile FROM (SELECT s, count(*) AS n FROM e GROUP BY s)"))


def _ranks(spark, d):
    """Ranks of nodes by their edges, most first, and quarters: from running numbers in parts, so no task orders all nodes."""
    per = graph(spark, d, "MONO").frame.groupBy("s").agg(F.count(F.lit(1)).alias("n")).withColumn("less", -F.col("n"))
    rows = running(per, [], ["less", "s"], {}, row="r")
    kinds = running(rows.groupBy("less").agg(F.min("r").alias("rk")), [], ["less"], {}, row="dr").select(F.col("less").alias("k"), "rk", "dr")
    size, more = divmod(per.count(), 4)
    far = more * (size + 1)
    tile = F.when(F.col("r") <= far, F.ceil(F.col("r") / (size + 1))).otherwise(more + F.ceil((F.col("r") - far) / max(1, size)))
    out = rows.join(kinds, F.col("less") == F.col("k"))
    return out.select("s", "n", F.col("dr").cast("int").alias("dr"), F.col("rk").cast("int").alias("rk"), tile.cast("int").alias("tile"))


def _moving(spark, d):
    """Starts in the last seven days, a day a row (one row a day of the timeline: calendar-sized, whatever the data)."""
    per = graph(spark, d, "SHIP").frame.groupBy(F.col("ts").alias("day")).agg(F.count(F.lit(1)).alias("n"))
    num = F.datediff("day", F.lit("1970-01-01"))
    w = Window.orderBy(num).rangeBetween(-6, 0)
    return per.select("day", F.sum("n").over(w).cast("long").alias("n7"))


def _scalars(r: Registry) -> None:
    r.add("fn_string", _frame("TRIP10", lambda e: e.select(F.upper("s").alias("u"), F.substring("s", 2, 9).alias("d"), F.concat("s", F.lit("-"), "o").alias("c"), F.regexp_extract("p", "([0-9]+)", 1).alias("x")).distinct()), over("TRIP10", "SELECT DISTINCT upper(s) AS u, substr(s, 2) AS d, s||'-'||o AS c, regexp_extract(p, '([0-9]+)', 1) AS x FROM e"))
    r.add("fn_date", _frame("SHIP", lambda e: e.select(F.year("ts").alias("y"), F.month("ts").alias("m"), F.datediff("te", "ts").alias("days"), F.date_trunc("month", "ts").cast("timestamp_ntz").alias("first")).groupBy("y", "m", "first").agg(F.sum("days").cast("long").alias("days"))), over("SHIP", "SELECT CAST(year(ts) AS INT) AS y, CAST(month(ts) AS INT) AS m, CAST(date_trunc('month', ts) AS TIMESTAMP) AS first, CAST(sum(datediff('day', ts, te)) AS BIGINT) AS days FROM e GROUP BY 1, 2, 3"))
    r.add("fn_math", _frame("SHIP", lambda e: e.select(F.substring("s", 2, 9).cast("long").alias("n")).filter("n > 0").distinct().select("n", F.floor(F.log2(F.col("n").cast("double"))).cast("int").alias("lg"), F.pmod(F.col("n"), F.lit(7)).cast("int").alias("md"), F.greatest(F.col("n"), F.lit(50)).alias("g"), F.shiftright("n", 2).alias("sh"), F.bit_count("n").alias("bits"))), over("SHIP", "SELECT n, CAST(floor(log2(n)) AS INT) AS lg, CAST(n % 7 AS INT) AS md, greatest(n, 50) AS g, n >> 2 AS sh, CAST(bit_count(n) AS INT) AS bits FROM (SELECT DISTINCT CAST(substr(s, 2) AS BIGINT) AS n FROM e WHERE s <> 's0')"))
    r.add("fn_array", _frame("TRIP10", lambda e: e.groupBy("p").agg(F.collect_set("s").alias("a"), F.collect_set("o").alias("b")).select("p", F.size(F.array_intersect("a", "b")).alias("both"), F.element_at(F.array_sort("a"), 1).alias("least"), F.size(F.filter("a", lambda x: x >= "k15")).alias("high"))), over("TRIP10", "SELECT p, CAST(len(list_intersect(a, b)) AS INT) AS both, list_sort(a)[1] AS least, CAST(len(list_filter(a, lambda x: x >= 'k15')) AS INT) AS high FROM (SELECT p, list(DISTINCT s) AS a, list(DISTINCT o) AS b FROM e GROUP BY p)"))
    q = parse("s7 ships_R ?z @t ; ?y ships_A ?z @t")
    r.add("fn_map", lambda s, d: solutions_as_map(solve.solve(q, graph(s, d, "SHIP"), "JF"), ["z", "y"]).select(F.col("solution")["z"].alias("z"), F.col("solution")["y"].alias("y"), F.size(F.map_entries("solution")).alias("n")), _wrapped(q, "SHIP", "SELECT z, y, 2 AS n FROM q"))
    r.add("fn_json", lambda s, d: load(s, d, "events").select("event_id", F.from_json("props", "k int").alias("j")).select("event_id", F.col("j.k").alias("k"), F.to_json(F.struct(F.col("j.k").alias("k"))).alias("back")), "SELECT event_id, CAST(json_extract_string(props, '$.k') AS INT) AS k, '{\"k\":'||json_extract_string(props, '$.k')||'}' AS back FROM events")
    r.add("udf_interval_intersect", _intersections, over("MONO", "SELECT a.o, count(*) AS n, CAST(sum(epoch_us(least(a.te, b.te)) - epoch_us(greatest(a.ts, b.ts))) AS BIGINT) AS us FROM (SELECT DISTINCT o, ts, te FROM e WHERE CAST(substr(s, 2) AS INT) % 2 = 1) a JOIN (SELECT DISTINCT o, ts, te FROM e WHERE CAST(substr(s, 2) AS INT) % 2 = 0) b ON a.o = b.o AND a.ts < b.te AND b.ts < a.te GROUP BY a.o"))
    timings = lambda s, d: load(s, d, "events").groupBy(F.col("user_id").cast("int").alias("qid"), F.col("event_type").alias("strategy")).agg(F.max("value").alias("ms"))
    held = "times AS (SELECT user_id AS qid, event_type AS strategy, max(value) AS ms FROM events GROUP BY 1, 2)"
    five = ", ".join(f"quantile_cont(ms, {x}) AS {n}" for x, n in ((0.0, "lower"), (0.25, "q1"), (0.5, "median"), (0.75, "q3"), (1.0, "upper")))
    r.add("measure_boxplot", lambda s, d: cost.boxplot(timings(s, d)).select("strategy", "lower", "q1", "median", "q3", "upper"), f"WITH {held} SELECT strategy, {five} FROM times GROUP BY strategy")
    kinds = ("click", "error", "purchase", "signup", "view")
    won = ", ".join(f"count(*) FILTER (WHERE b.strategy = '{k}' AND a.ms < b.ms) AS {k}" for k in kinds)
    r.add("measure_wins", lambda s, d: cost.wins(timings(s, d)).select("strategy", *[F.coalesce(k, F.lit(0)).alias(k) for k in kinds]), f"WITH {held} SELECT a.strategy, {won} FROM times a JOIN times b ON a.qid = b.qid AND a.strategy <> b.strategy GROUP BY a.strategy")
    r.add("measure_best", lambda s, d: cost.best(timings(s, d)).select(F.round("best_mean", 6).alias("best_mean")), f"WITH {held} SELECT round(avg(ms), 6) AS best_mean FROM (SELECT min(ms) AS ms FROM times GROUP BY qid)")
    r.add("layout_classes", _frame("SHIP", lambda e: with_layout(e).groupBy("month", "length_class").agg(F.count(F.lit(1)).alias("n"))), over("SHIP", "SELECT strftime(ts, '%Y-%m') AS month, CAST(floor(log2(epoch_us(te) - epoch_us(ts))) AS INT) AS length_class, count(*) AS n FROM e GROUP BY 1, 2"))


def _intersections(spark, d):
    """Common parts of the ranges of odd and even sources at each target, by the Arrow function: their number and length."""
    e = graph(spark, d, "MONO").frame.withColumns({c: F.unix_micros(F.col(c).cast("timestamp")) for c in ("ts", "te")})
    ranges = lambda c: F.array_sort(F.collect_set(F.when(c, F.struct(F.col("ts").alias("from"), F.col("te").alias("to")))))
    odd = F.substring("s", 2, 9).cast("int") % 2 == 1
    g = e.groupBy("o").agg(ranges(odd).alias("x"), ranges(~odd).alias("y"))
    cut = F.explode(interval_intersect("x", "y")).alias("r")
    return g.select("o", cut).groupBy("o").agg(F.count(F.lit(1)).alias("n"), F.sum(F.col("r.to") - F.col("r.from")).alias("us"))


def _streams(r: Registry) -> None:
    win = lambda s, d, *a: stream.live_counts(load(s, d, "events"), "ts", *a)
    r.add("win_tumbling", lambda s, d: win(s, d, "1 day"), "SELECT CAST(date_trunc('day', ts) AS TIMESTAMP) AS w_from, CAST(date_trunc('day', ts) + INTERVAL 1 DAY AS TIMESTAMP) AS w_to, count(*) AS n FROM events GROUP BY 1, 2")
    r.add("win_sliding", lambda s, d: win(s, d, "1 day", "6 hours"), "SELECT CAST(w AS TIMESTAMP) AS w_from, CAST(w + INTERVAL 1 DAY AS TIMESTAMP) AS w_to, count(*) AS n FROM (SELECT unnest([time_bucket(INTERVAL 6 HOUR, ts, TIMESTAMP '1970-01-01') - to_hours(CAST(6 * i AS INT)) FOR i IN range(4)]) AS w FROM events) GROUP BY 1, 2")
    r.add("win_session", lambda s, d: stream.sessions(load(s, d, "events"), "ts", "user_id", "30 minutes"), "SELECT user_id, min(ts) AS w_from, max(ts) + INTERVAL 30 MINUTE AS w_to, count(*) AS n FROM (SELECT *, sum(f) OVER (PARTITION BY user_id ORDER BY ts) AS g FROM (SELECT user_id, ts, CASE WHEN ts - lag(ts) OVER (PARTITION BY user_id ORDER BY ts) < INTERVAL 30 MINUTE THEN 0 ELSE 1 END AS f FROM events)) GROUP BY user_id, g")
    r.add("stream_trips", lambda s, d: stream.trips(load(s, d, "events")), "SELECT user_id, CAST(json_extract_string(props,'$.k') AS INT) AS k, ts, nk, nts FROM (SELECT *, lead(CAST(json_extract_string(props,'$.k') AS INT)) OVER w AS nk, lead(ts) OVER w AS nts FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id)) WHERE nts IS NOT NULL")
    pair = parse("?x ships_R ?z @t ; ?y ships_A ?z @t")
    r.add("stream_delta_pattern", lambda s, d: _delta(s, d, pair), _wrapped_new(pair))
    r.add("stream_overlap_join", _stream_overlap, over("MONO", "SELECT a.o AS key, a.s AS x, b.s AS y, greatest(a.ts, b.ts) AS t_from, least(a.te, b.te) AS t_to FROM e a JOIN e b ON a.o = b.o AND a.ts < b.te AND b.ts < a.te WHERE b.ts >= a.ts - INTERVAL 40 DAY AND b.ts <= a.ts + INTERVAL 40 DAY"))
    r.add("stream_dedup", lambda s, d: stream.once(load(s, d, "events"), "event_id", "ts", "1 hour").agg(F.count(F.lit(1)).alias("n")), "SELECT count(DISTINCT event_id) AS n FROM events")


def _delta(spark, d, q):
    g = graph(spark, d, "SHIP")
    cut = F.lit("2000-01-01").cast("timestamp_ntz")
    return stream.delta_solve(q, g.of(g.frame.filter(F.col("ts") < cut)), g.of(g.frame.filter(F.col("ts") >= cut)))


def _wrapped_new(q) -> str:
    return pattern_sql(q, "SHIP", extra="(a0.ts >= TIMESTAMP '2000-01-01' OR a1.ts >= TIMESTAMP '2000-01-01')")


def _stream_overlap(spark, d):
    e = graph(spark, d, "MONO").frame
    return stream.overlap_stream_join(e, e, "o", "40 DAYS")
