"""Temporal graphs built from the given tables."""

from __future__ import annotations

from dataclasses import replace
from datetime import datetime
from functools import reduce

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from ..model.graph import TemporalGraph
from .tables import load, page_links, stops

STATIC_SPAN = ("1995-01-01", "2002-01-01")
DOC_SPAN = ("2024-01-01", "2025-01-01")


def _ntz(text: str) -> Column:
    return F.lit(text).cast("timestamp_ntz")


def _key(prefix: str, *cols: str | Column) -> Column:
    return F.concat(F.lit(prefix), *cols)


def _edge(df: DataFrame, s, p, o, ts, te) -> DataFrame:
    cols = [c if isinstance(c, Column) else F.lit(c) for c in (s, p, o, ts, te)]
    return df.select(*[c.alias(n) for c, n in zip(cols, ("s", "p", "o", "ts", "te"), strict=True)])


def _days(df_col: Column, days: Column) -> Column:
    return df_col + F.make_dt_interval(days)


def _trip_like(label) -> object:
    def build(spark: SparkSession, d: str) -> DataFrame:
        e = stops(spark, d)
        return _edge(e, _key("k", F.col("k") % 20), label(), _key("k", F.col("nk") % 20), F.col("ts"), F.col("nts"))

    return build


def _mono(spark: SparkSession, d: str) -> DataFrame:
    day = lambda c: F.date_trunc("day", c).cast("timestamp_ntz")
    return _edge(stops(spark, d), _key("k", "k"), F.lit("link"), _key("k", "nk"), day("ts"), day("nts") + F.expr("INTERVAL '1' DAY"))


def _ship(spark: SparkSession, d: str) -> DataFrame:
    at = F.col("l_shipdate")
    return _edge(load(spark, d, "lineitem"), _key("s", "l_suppkey"), _key("ships_", "l_returnflag"), _key("p", "l_partkey"), at, _days(at, F.col("l_quantity").cast("int")))


def _sold(spark: SparkSession, d: str) -> DataFrame:
    sold = load(spark, d, "lineitem").join(load(spark, d, "orders"), F.col("l_orderkey") == F.col("o_orderkey"))
    at = F.col("l_shipdate")
    return _edge(sold, _key("p", "l_partkey"), "sold_to", _key("c", "o_custkey"), at, _days(at, F.col("l_quantity").cast("int")))


def _placed(spark: SparkSession, d: str) -> DataFrame:
    return _edge(load(spark, d, "orders"), _key("o", "o_orderkey"), "placed_by", _key("c", "o_custkey"), F.col("o_orderdate"), F.col("o_orderdate") + F.expr("INTERVAL '1' DAY"))


def _static(spark: SparkSession, d: str) -> DataFrame:
    a, b = map(_ntz, STATIC_SPAN)
    t = lambda n: load(spark, d, n)
    parts = [
        _edge(t("customer"), _key("c", "c_custkey"), "in_nation", _key("n", "c_nationkey"), a, b),
        _edge(t("supplier"), _key("s", "s_suppkey"), "in_nation", _key("n", "s_nationkey"), a, b),
        _edge(t("nation"), _key("n", "n_nationkey"), "in_region", _key("r", "n_regionkey"), a, b),
        _edge(t("part"), _key("p", "p_partkey"), "has_brand", F.col("p_brand"), a, b),
        _edge(t("part"), _key("p", "p_partkey"), "has_type", F.col("p_type"), a, b),
        _edge(t("customer"), _key("c", "c_custkey"), "in_segment", F.col("c_mktsegment"), a, b),
    ]
    out = parts[0]
    for x in parts[1:]:
        out = out.union(x)
    return out


def _order_static(spark: SparkSession, d: str) -> DataFrame:
    a, b = map(_ntz, STATIC_SPAN)
    o = load(spark, d, "orders")
    out = _edge(o, _key("o", "o_orderkey"), "has_priority", F.col("o_orderpriority"), a, b)
    out = out.union(_edge(o, _key("o", "o_orderkey"), "has_status", F.col("o_orderstatus"), a, b))
    return out.union(_edge(load(spark, d, "lineitem"), _key("o", "l_orderkey"), "contains", _key("p", "l_partkey"), a, b))


def _turn(spark: SparkSession, d: str) -> DataFrame:
    c = load(spark, d, "conversations")
    return _edge(c, _key("v", "conv_id"), F.col("role"), _key("n", (F.length("text") % 10).cast("string")), F.col("turn").cast("long"), F.col("turn").cast("long") + 1)


def _doc(spark: SparkSession, d: str) -> DataFrame:
    a, b = map(_ntz, DOC_SPAN)
    t = lambda n: load(spark, d, n)
    out = _edge(t("documents"), _key("d", "doc_id"), "in_lang", F.col("lang"), a, b)
    for x in (
        _edge(t("documents"), _key("d", "doc_id"), "from_source", F.col("source"), a, b),
        _edge(t("labels"), _key("d", "doc_id"), "quality", _key("q", "quality"), a, b),
        _edge(t("labels"), _key("d", "doc_id"), "toxic", _key("x", "toxic"), a, b),
        _edge(t("embeddings"), _key("e", "vec_id"), "has_label", _key("l", "label"), a, b),
        _edge(t("benchmark"), _key("b", "item_id"), "is_a", "benchmark_item", a, b),
        _edge(page_links(spark, d), _key("g", "page_id"), "links_to", F.col("target"), a, b),
    ):
        out = out.union(x)
    return out


def _clock(text: str) -> datetime:
    h, m = text.split(":")
    return datetime(2024, 1, 1, int(h), int(m))


#: The worked example: riders, buses and times of one day (fixed values).
TOY_TRIPS = [
    ("Emma", "B6", "06:45", "07:22"),
    ("Bob", "B12", "09:51", "10:40"),
    ("Anna", "B12", "10:32", "11:05"),
    ("Carl", "B12", "10:46", "11:25"),
    ("Carl", "B12", "16:11", "17:03"),
    ("Anna", "B6", "18:30", "19:10"),
    ("Dick", "B6", "18:45", "18:56"),
]


def toy(spark: SparkSession) -> TemporalGraph:
    rows = [(a, "trip", b, _clock(x), _clock(y)) for a, b, x, y in TOY_TRIPS]
    return TemporalGraph.from_edges(spark.createDataFrame(rows, "s string, p string, o string, ts timestamp_ntz, te timestamp_ntz"))


#: Graphs whose edges come in parts without a label in common.
PARTS = {
    "KGT": (_ship, _sold, _placed),
    "KG": (_ship, _sold, _placed, _static),
    "KG_STATIC_HEAVY": (_ship, _sold, _placed, _static, _order_static),
}


def _all(name: str) -> object:
    return lambda spark, d: reduce(DataFrame.union, [part(spark, d) for part in PARTS[name]])


RAW = {
    "TRIP": _trip_like(lambda: _key("u", "user_id")),
    "TRIP10": _trip_like(lambda: _key("g", F.col("user_id") % 10)),
    "SKEW": _trip_like(lambda: _key("v", F.floor(F.col("value") / 10).cast("int"))),
    "MONO": _mono,
    "SHIP": _ship,
    "KGT": _all("KGT"),
    "KG": _all("KG"),
    "KG_STATIC_HEAVY": _all("KG_STATIC_HEAVY"),
    "TURN": _turn,
    "DOC": _doc,
}


def raw(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return RAW[name](spark, sf_dir)


def graph(spark: SparkSession, sf_dir: str, name: str) -> TemporalGraph:
    g = TemporalGraph.from_edges(raw(spark, sf_dir, name))
    return replace(g, parts=tuple(TemporalGraph.from_edges(part(spark, sf_dir), coalesce=False).frame for part in PARTS[name])) if name in PARTS else g
