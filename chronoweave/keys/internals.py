"""Building, encoding and index internals."""

from __future__ import annotations

from datetime import datetime

from pyspark.sql import functions as F

from ..functions.kernels import common_ranges, intersected
from ..functions.sql import seek_below
from ..index import tries
from ..measures import cost
from ..model.graph import TemporalGraph, validate
from ..operators import baselines
from ..plans import stats
from ..sources.graphs import graph, raw
from ..sources.tables import load, stops
from ..sql_text import RAW, _BASE, graph_ctes, over
from . import Registry

_LINE = "line AS (SELECT at, row_number() OVER (ORDER BY at) - 1 AS tick FROM (SELECT ts AS at FROM e UNION SELECT te FROM e))"


def _with_line(name: str, body: str) -> str:
    return f"WITH {graph_ctes(name)},\n{_LINE}\n{body}"


def register(r: Registry) -> None:
    _build(r)
    _index(r)


def _build(r: Registry) -> None:
    for key, g in (("trip", "TRIP"), ("trip10", "TRIP10"), ("skew", "SKEW"), ("mono", "MONO"), ("ship", "SHIP"), ("kg", "KG")):
        r.add(f"coalesce_{key}", lambda s, d, g=g: graph(s, d, g).frame, over(g, "SELECT s, p, o, ts, te FROM e"))
    r.add("edge_rejects", _rejects, f"SELECT 'u'||user_id AS s, ts FROM (SELECT user_id, ts, lead(ts) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS te FROM events) WHERE te IS NULL OR NOT ts < te")
    r.add("universe_size", lambda s, d: graph(s, d, "KG").universe().agg(F.count(F.lit(1)).alias("u")), over("KG", "SELECT count(*) AS u FROM (SELECT s FROM e UNION SELECT p FROM e UNION SELECT o FROM e)"))
    for key, g in (("ship", "SHIP"), ("turn", "TURN")):
        r.add(f"timeline_{key}", lambda s, d, g=g: graph(s, d, g).timeline(), _with_line(g, "SELECT tick, at FROM line"))
    r.add("floor_ticks", _floors, over("SHIP", "SELECT o_orderdate AS at, (SELECT max(x.at) FROM (SELECT ts AS at FROM e UNION SELECT te FROM e) x WHERE x.at <= o_orderdate) AS floor FROM (SELECT DISTINCT o_orderdate FROM orders)"))
    r.add("dictionary_roundtrip", lambda s, d: (g := graph(s, d, "TRIP10")).decode(g.encoded()), over("TRIP10", "SELECT s, p, o, ts, te FROM e"))
    r.add("dictionary_kg", lambda s, d: graph(s, d, "DOC").dictionary(), over("DOC", "SELECT row_number() OVER (ORDER BY term) - 1 AS id, term FROM (SELECT s AS term FROM e UNION SELECT p FROM e UNION SELECT o FROM e)"))
    r.add("expand_mono", lambda s, d: baselines.point_expand(graph(s, d, "MONO")), _with_line("MONO", "SELECT e.s, e.p, e.o, line.tick FROM e JOIN line ON line.at >= e.ts AND line.at < e.te"))
    r.add("expansion_size", lambda s, d: cost.expansion_size(graph(s, d, "SHIP")), _with_line("SHIP", "SELECT CAST(sum(b.tick - a.tick) AS BIGINT) AS points FROM e JOIN line a ON a.at = e.ts JOIN line b ON b.at = e.te"))
    kinds = "CASE WHEN ts = TIMESTAMP '1995-01-01' AND te = TIMESTAMP '2002-01-01' THEN 'static' WHEN p = 'placed_by' THEN 'point' ELSE 'interval' END"
    r.add("annotation_mix", lambda s, d: graph(s, d, "KG").frame.select(F.expr(kinds.replace("TIMESTAMP", "TIMESTAMP_NTZ")).alias("kind")).groupBy("kind").agg(F.count(F.lit(1)).alias("n")), over("KG", f"SELECT {kinds} AS kind, count(*) AS n FROM e GROUP BY 1"))
    r.add("transient_size", lambda s, d: graph(s, d, "KG").transient().frame.agg(F.count(F.lit(1)).alias("n")), over("KG", "SELECT count(*) AS n FROM e WHERE ts > (SELECT min(ts) FROM e) OR te < (SELECT max(te) FROM e)"))
    for key in ("SHIP", "TRIP10", "SKEW", "MONO", "TURN", "DOC"):
        r.add(f"graph_describe_{key.lower()}", lambda s, d, g=key: cost.describe(graph(s, d, g)), over(key, "SELECT (SELECT count(*) FROM e) AS n, (SELECT count(*) FROM (SELECT s FROM e UNION SELECT p FROM e UNION SELECT o FROM e)) AS u, (SELECT count(*) FROM (SELECT ts FROM e UNION SELECT te FROM e)) AS t, (SELECT count(DISTINCT p) FROM e) AS labels, (SELECT max(c) FROM (SELECT count(*) AS c FROM e GROUP BY p)) AS top_label"))
    for key, op in (("set_union", "union"), ("set_intersect", "intersect"), ("set_except", "minus")):
        r.add(key, lambda s, d, op=op: _algebra(s, d, op), _algebra_sql(op))


def _rejects(spark, d):
    from pyspark.sql import Window

    w = Window.partitionBy("user_id").orderBy("ts", "event_id")
    e = load(spark, d, "events").select(F.concat(F.lit("u"), "user_id").alias("s"), F.lit("p").alias("p"), F.lit("o").alias("o"), "ts", F.lead("ts").over(w).alias("te"))
    return validate(e)[1].select("s", "ts")


def _floors(spark, d):
    return graph(spark, d, "SHIP").floor(load(spark, d, "orders").select(F.col("o_orderdate").alias("at")).distinct()).select("at", "floor")


def _halves(spark, d):
    e = raw(spark, d, "MONO")
    odd = F.substring("s", 2, 9).cast("int") % 2 == 1
    low = F.substring("o", 2, 9).cast("int") < 60
    return TemporalGraph.from_edges(e.filter(odd)), TemporalGraph.from_edges(e.filter(low))


def _algebra(spark, d, op: str):
    a, b = _halves(spark, d)
    return getattr(a, op)(b).frame


def _algebra_sql(op: str) -> str:
    """Set algebra day by day, put together to ranges again."""
    days = "SELECT DISTINCT s, p, o, unnest(generate_series(ts, te - INTERVAL 1 DAY, INTERVAL 1 DAY)) AS day FROM m"
    a, b = f"({days} WHERE CAST(substr(s, 2) AS INT) % 2 = 1)", f"({days} WHERE CAST(substr(o, 2) AS INT) < 60)"
    word = {"union": "UNION", "intersect": "INTERSECT", "minus": "EXCEPT"}[op]
    return f"""WITH m AS ({RAW['MONO']}), x AS ({a} {word} {b}),
y AS (SELECT *, day - to_days(CAST(row_number() OVER (PARTITION BY s, p, o ORDER BY day) AS INT)) AS g FROM x)
SELECT s, p, o, CAST(min(day) AS TIMESTAMP) AS ts, CAST(max(day) + INTERVAL 1 DAY AS TIMESTAMP) AS te FROM y GROUP BY s, p, o, g"""


def _index(r: Registry) -> None:
    r.add("trie_children_pos", lambda s, d: tries.children(graph(s, d, "SHIP"), "pos", 2), over("SHIP", "SELECT p, o, count(DISTINCT s) AS children FROM e GROUP BY p, o"))
    r.add("trie_otps_levels", lambda s, d: tries.quads(graph(s, d, "TRIP10"), "otps").groupBy("o").agg(F.count(F.lit(1)).alias("edges"), F.min("ts").alias("first"), F.max("te").alias("last")), over("TRIP10", "SELECT o, count(*) AS edges, min(ts) AS first, max(te) AS last FROM e GROUP BY o"))
    r.add("trie_spo_rows", lambda s, d: tries.triples(graph(s, d, "TRIP10"), "spo"), over("TRIP10", "SELECT DISTINCT s, p, o FROM e"))
    level = "SELECT {k}at AS start, lead(at) OVER ({w}ORDER BY at) AS stop, CAST(sum(net) OVER ({w}ORDER BY at) AS BIGINT) AS live, CAST(sum(n) OVER ({w}ORDER BY at) AS BIGINT) AS updates FROM (SELECT {k}at, sum(d) AS net, count(*) AS n FROM (SELECT {k}ts AS at, 1 AS d FROM e UNION ALL SELECT {k}te, -1 FROM e) GROUP BY {k}at)"
    r.add("time_level_o", lambda s, d: tries.time_level(graph(s, d, "SHIP"), ["o"]), over("SHIP", f"SELECT * FROM ({level.format(k='o, ', w='PARTITION BY o ')}) WHERE live > 0"))
    r.add("time_level_po", lambda s, d: tries.time_level(graph(s, d, "SKEW"), ["p", "o"]), over("SKEW", f"SELECT * FROM ({level.format(k='p, o, ', w='PARTITION BY p, o ')}) WHERE live > 0"))
    r.add("time_level_root", lambda s, d: tries.time_level(graph(s, d, "SHIP"), []), over("SHIP", f"SELECT * FROM ({level.format(k='', w='')}) WHERE live > 0"))
    r.add("node_events", lambda s, d: tries.node_events(graph(s, d, "SHIP"), ["o"]).groupBy("o", "sign").agg(F.count(F.lit(1)).alias("n")), over("SHIP", "SELECT o, 1 AS sign, count(*) AS n FROM e GROUP BY o UNION ALL SELECT o, -1, count(*) FROM e GROUP BY o"))
    ids = "dict AS (SELECT term, row_number() OVER (ORDER BY term) - 1 AS id FROM (SELECT s AS term FROM e UNION SELECT p FROM e UNION SELECT o FROM e))"
    events = "w AS (SELECT CAST(ceil(log2(count(*))) AS BIGINT) AS w FROM dict), ev AS (SELECT o.id AS o, k.tick, k.sign, (p.id << w.w) + s.id AS key FROM (SELECT e.*, line.tick, 1 AS sign FROM e JOIN line ON line.at = e.ts UNION ALL SELECT e.*, line.tick, -1 FROM e JOIN line ON line.at = e.te) k JOIN dict s ON s.term = k.s JOIN dict p ON p.term = k.p JOIN dict o ON o.term = k.o, w)"
    num = "nev AS (SELECT o, tick, sign, key, row_number() OVER (PARTITION BY o ORDER BY tick, sign, key) AS upd FROM ev)"
    lv = "lv AS (SELECT nev.*, level, 2 * w.w AS w2, key >> (2 * w.w - level) AS node FROM nev, w, (SELECT unnest(range(0, 65)) AS level) WHERE level <= 2 * w.w)"
    bits = "SELECT o, CAST(level AS INT) AS level, row_number() OVER (PARTITION BY o, level ORDER BY node, upd) AS place, CASE WHEN level < w2 THEN CAST((key >> (w2 - 1 - level)) & 1 AS INT) ELSE -1 END AS b, CAST(sum(sign) OVER (PARTITION BY o, level, node ORDER BY upd) > 0 AS INT) AS e FROM lv"
    sql = f"WITH {graph_ctes('MONO')},\n{_LINE}, {ids}, {events}, {num}, {lv}\n{bits}"
    r.add("matrix_bits", _matrix_bits, sql)
    r.add("matrix_packed", lambda s, d: _packed(s, d, 1 << 20), sql)
    r.add("matrix_shards", lambda s, d: _packed(s, d, 64).groupBy("o", "level").agg(F.count(F.lit(1)).alias("n"), F.sum(F.when(F.col("b") > 0, 1).otherwise(0)).alias("ones")), f"WITH {graph_ctes('MONO')},\n{_LINE}, {ids}, {events}, {num}, {lv}, bits AS ({bits})\nSELECT o, level, count(*) AS n, CAST(sum(CASE WHEN b > 0 THEN 1 ELSE 0 END) AS BIGINT) AS ones FROM bits GROUP BY o, level")
    r.add("matrix_bit_count", _bit_count, f"WITH {graph_ctes('MONO')},\n{ids}\nSELECT CAST(2 * (SELECT count(*) FROM e) * 2 * 2 * (SELECT CAST(ceil(log2(count(*))) AS BIGINT) FROM dict) AS BIGINT) AS bits")
    r.add("seek_children", _seeks, over("TRIP10", "SELECT p, min(CAST(substr(s, 2) AS BIGINT)) AS child FROM e WHERE CAST(substr(s, 2) AS BIGINT) >= 7 GROUP BY p"))
    r.add("intersect_children", lambda s, d: _common(s, d), over("SHIP", "SELECT DISTINCT o AS child FROM e WHERE p = 'ships_R' AND s = 's1' INTERSECT SELECT DISTINCT o FROM e WHERE p = 'ships_A' AND s = 's2'"))
    two = f"lv AS ({level.format(k='o, p, ', w='PARTITION BY o, p ')}), live AS (SELECT * FROM lv WHERE live > 0 AND p IN ('ships_R', 'ships_N'))"
    r.add("time_ranges", _ranges, f"WITH {graph_ctes('SHIP')}, {two}\nSELECT a.o, greatest(a.start, b.start) AS t_from, least(a.stop, b.stop) AS t_to FROM live a JOIN live b ON a.o = b.o WHERE a.p = 'ships_R' AND b.p = 'ships_N' AND a.start < b.stop AND b.start < a.stop")
    fan = " UNION ALL ".join(f"SELECT '{a}>{b}' AS prefix, count(*) AS nodes, CAST(sum(k) AS BIGINT) AS children, max(k) AS widest FROM (SELECT count(DISTINCT {b}) AS k FROM e GROUP BY {', '.join(a)})" for a, b in stats.PREFIXES)
    r.add("fanout_stats", lambda s, d: stats.fanout(graph(s, d, "SHIP")), over("SHIP", fan))
    r.add("dur_classes", lambda s, d: tries.duration_classes(graph(s, d, "SHIP")), over("SHIP", "SELECT CAST(floor(log2(epoch_us(te) - epoch_us(ts))) AS INT) AS class, count(*) AS edges FROM e GROUP BY 1"))
    day = datetime(2024, 1, 15)
    r.add("dur_grid_long", lambda s, d: tries.duration_grid(graph(s, d, "SHIP")).filter(F.col("length") >= 40 * 86_400_000_000).select("s", "p", "o", "ts", "length"), over("SHIP", "SELECT s, p, o, ts, epoch_us(te) - epoch_us(ts) AS length FROM e WHERE te - ts >= INTERVAL 40 DAY"))
    r.add("trip_lead", lambda s, d: stops(s, d).filter(F.col("ts") >= F.lit(str(day)).cast("timestamp_ntz")).select("user_id", "k", "ts", "nk", "nts"), f"SELECT user_id, k, ts, nk, nts FROM ({_BASE}) WHERE nts IS NOT NULL AND ts >= TIMESTAMP '{day}'")
    r.add("work_counters", _work)


def _matrix_bits(spark, d):
    g = graph(spark, d, "MONO")
    width = tries.width_of(g)
    return tries.matrix_rows(tries.numbered_events(g, "otps", width), ["o"], 2 * width).withColumn("b", F.coalesce("b", F.lit(-1)))


def _packed(spark, d, events_each: int):
    """The bits that the packed matrices hold."""
    g = graph(spark, d, "MONO")
    width = tries.width_of(g)
    held = tries.pack(tries.numbered_events(g, "otps", width), ["o"], 2 * width, events_each)
    return tries.packed_bits(held).select(F.col("prefix")[0].alias("o"), "level", "place", "b", "e")


def _bit_count(spark, d):
    """Bits that the packed matrices store: next bits and existence bits of all levels, but for the leaves' alternating ones."""
    g = graph(spark, d, "MONO")
    width = tries.width_of(g)
    held = tries.pack(tries.numbered_events(g, "otps", width), ["o"], 2 * width)
    return held.agg(F.sum(F.when(F.col("level") < 2 * width, 2 * F.col("n")).otherwise(0)).cast("long").alias("bits"))


def _seeks(spark, d):
    """The least child from 7 on below each label, by the table function on each label's partition."""
    rows = graph(spark, d, "TRIP10").frame.select("p", F.substring("s", 2, 9).cast("long").alias("child")).distinct()
    rows.createOrReplaceTempView("label_children")
    spark.udtf.register("seek_below", seek_below)
    return spark.sql("SELECT p, child FROM seek_below(TABLE(label_children) PARTITION BY (p), 7)")


def _common(spark, d):
    """Children that two prefixes have in common, by the cyclic seeks on each prefix's sorted list of numbers."""
    e = graph(spark, d, "SHIP").frame
    lists = e.filter("(p = 'ships_R' AND s = 's1') OR (p = 'ships_A' AND s = 's2')").select(F.col("s").alias("key"), F.substring("o", 2, 18).cast("long").alias("child")).distinct()
    return intersected(lists, 2).select(F.concat(F.lit("p"), "child").alias("child"))


def _ranges(spark, d):
    """Common ranges of the time levels of two labels below each object, by seeks in their sorted ranges."""
    e = graph(spark, d, "SHIP").frame.filter("p IN ('ships_R', 'ships_N')")
    level = tries.time_level(TemporalGraph(e, "timestamp_ntz"), ["o", "p"])
    return common_ranges(level, "o", "p", 2).select("o", F.timestamp_micros("a").cast("timestamp_ntz").alias("t_from"), F.timestamp_micros("b").cast("timestamp_ntz").alias("t_to"))


def _work(spark, d):
    from ..model.query import parse

    g, q = graph(spark, d, "TRIP10"), parse("?x g3 ?y @t ; ?y g3 ?z @t ; ?z g9 ?x @t")
    out = None
    for s in ("JF", "TF", "LC"):
        part = cost.work(q, g, s).withColumn("strategy", F.lit(s))
        out = part if out is None else out.unionByName(part)
    return out
