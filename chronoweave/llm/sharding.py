"""Sharding by a k-d tree over metadata, with distributed weighted medians; DataFrame operations only.

Every row is a point: rank-free integer coordinates of length, source and language, each 31 bits. A node is
split along its widest dimension (extent over the extent of the whole table) at the byte-weighted median, found by
histogram refinement: 1,024 bins a round, each round one aggregate with map-side partial sums, of which at most
1,024 rows a node reach the driver. Ties of a coordinate are ordered by the text's hash and then the row's, so
rows of equal coordinates can still be cut. Equal texts share one point and one tie, so they stay in one shard,
except for the one group at a cut when it holds more bytes than the tolerance. Splitting ends when the tree has the asked number of leaves, a power of two.

Defined results: a null text has size 1 and crc of no bytes; nulls in any coordinate are a value of their own; an empty table
has no shards; repeated rows are told apart by a hash of the row only where they differ, and rows that are
equal in all of doc_id, source, lang and text go to one shard together; extra columns are ignored.
"""

from __future__ import annotations

import math

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import running, stored, table

BINS = 1024
_LOW = (1 << 31) - 1


def _coordinates() -> dict[str, Column]:
    """31-bit whole-number coordinates: log-scaled size (order kept), and hashed labels (nearness has no meaning there)."""
    label = lambda c: F.when(F.col(c).isNull(), F.lit(_LOW)).otherwise(F.xxhash64(c).bitwiseAND(_LOW >> 1))
    return {"c0": F.least(F.floor(F.log2(F.col("size").cast("double")) * (1 << 24)), F.lit(_LOW)).cast("long"), "c1": label("source"), "c2": label("lang")}


def kd_shards(docs: DataFrame, depth: int = 4, tolerance: float = 1e-3, target_bytes: int | None = None) -> DataFrame:
    """Rows (doc_id, size, text_crc32, h_id, shard): 2**depth leaves of near-equal bytes; with ``target_bytes`` nodes are
    split until leaves hold no more than that, but for the tolerance, which medians reach everywhere at one depth.

    A cut is accepted when it is within ``tolerance`` of the node's bytes of the median or falls between two rows.
    """
    size = F.coalesce(F.octet_length("text"), F.lit(0)).cast("long") + 1
    base = docs.select("doc_id", "source", "lang", size.alias("size"), F.crc32(F.coalesce(F.col("text"), F.lit("")).cast("binary")).alias("text_crc32"), F.xxhash64("text").alias("h_text"), F.xxhash64("doc_id", "source", "lang", "text").bitwiseAND((1 << 62) - 1).alias("h_id"))
    coords = _coordinates()
    # equal texts take the metadata of the least of them, so that they meet in one point; the least are written before
    # they are joined, so that a text with very many copies is split at run time instead of going to one task
    base = stored(base, "kd-rows")
    first = stored(base.groupBy(F.col("h_text").alias("g")).agg(F.min("source").alias("source"), F.min("lang").alias("lang")), "kd-texts")
    met = base.drop("source", "lang").join(first, F.col("h_text") == F.col("g"))
    tie = F.shiftrightunsigned("h_text", 33).alias("h_text")
    points = stored(met.select("doc_id", "size", "text_crc32", tie, "h_id", *[v.alias(k) for k, v in coords.items()]), "kd-points")
    ends = [f(c).alias(f"{f.__name__}_{c}") for c in coords for f in (F.min, F.max)]
    world = points.agg(F.sum("size").alias("bytes"), *ends).first()
    if world[0] is None:
        return points.select("doc_id", "size", "text_crc32", "h_id", F.lit(0).alias("shard"))
    if target_bytes is not None:
        depth = max(0, math.ceil(math.log2(max(1.0, world["bytes"] / (target_bytes * (1 + tolerance))))))
    extent = {c: max(1, world[f"max_{c}"] - world[f"min_{c}"]) for c in coords}
    points = points.withColumn("node", F.lit(0))
    for level in range(depth):
        stats = {r["node"]: r for r in points.groupBy("node").agg(F.sum("size").alias("bytes"), *ends).collect()}
        wide = {n: max(range(len(coords)), key=lambda i: (r[f"max_c{i}"] - r[f"min_c{i}"]) / extent[f"c{i}"]) for n, r in stats.items()}
        cut = _medians(points, {n: r["bytes"] for n, r in stats.items()}, wide, tolerance)
        small = spark_rows(points, [(n, *c) for n, c in cut.items()], "node int, dim int, a long, b long")
        right = (_key() > F.col("a")) | ((_key() == F.col("a")) & (F.col("h_id") >= F.col("b")))
        points = points.join(F.broadcast(small), "node").withColumn("node", F.col("node") * 2 + right.cast("int")).drop("dim", "a", "b")
        if level % 2 and level + 1 < depth:
            points = stored(points, "kd-level")
    return points.select("doc_id", "size", "text_crc32", "h_id", F.col("node").alias("shard"))


def spark_rows(like: DataFrame, rows: list[tuple], schema: str) -> DataFrame:
    return like.sparkSession.createDataFrame(rows, schema)


def _key() -> Column:
    """The order within a node: its dimension, then the text's hash."""
    return F.shiftleft(F.element_at(F.array("c0", "c1", "c2"), F.col("dim") + 1), 31) + F.col("h_text")


def _medians(points: DataFrame, total: dict[int, int], wide: dict[int, int], tolerance: float) -> dict[int, tuple[int, int, int]]:
    """For each node (dim, a, b): rows below (a, b) in (key, row hash) order hold about half of the node's bytes."""
    state = {n: {"lo": 0, "shift": 52, "before": 0, "a": None} for n in total}
    done: dict[int, tuple[int, int, int]] = {}
    while state:
        small = spark_rows(points, [(n, wide[n], s["lo"], s["shift"], s["a"]) for n, s in state.items()], "node int, dim int, lo long, shift int, a long")
        at = F.when(F.col("a").isNull(), _key()).otherwise(F.col("h_id")) - F.col("lo")
        bin_ = F.expr("shiftright(at, shift)")
        live = (F.col("a").isNull() | (_key() == F.col("a"))) & (F.col("at") >= 0) & (F.col("bin") < BINS)
        rows = points.join(F.broadcast(small), "node").withColumn("at", at).withColumn("bin", bin_).filter(live).groupBy("node", "bin").agg(F.sum("size").alias("bytes")).collect()
        by: dict[int, list] = {n: [] for n in state}
        for r in rows:
            by[r["node"]].append((r["bin"], r["bytes"]))
        for n, s in list(state.items()):
            half, seen, pick, held = total[n] / 2, s["before"], 0, 0
            for b, w in sorted(by[n]):
                pick, held = b, w
                if seen + w >= half:
                    break
                seen += w
            low = half - seen <= seen + held - half
            edge = s["lo"] + ((pick if low else pick + 1) << s["shift"])
            off = abs((seen if low else seen + held) - half)
            if off <= tolerance * total[n] or (s["shift"] == 0 and s["a"] is not None):
                done[n] = (wide[n], edge, 0) if s["a"] is None else (wide[n], s["a"], edge)
                del state[n]
            elif s["shift"] == 0:  # one key holds more than the tolerance: go on by row hash
                state[n] = {"lo": 0, "shift": 52, "before": seen, "a": s["lo"] + pick}
            else:
                state[n] = {"lo": s["lo"] + (pick << s["shift"]), "shift": max(0, s["shift"] - 10), "before": seen, "a": s["a"]}
    return done


def shard(docs: DataFrame, depth: int = 4, target_bytes: int | None = None) -> DataFrame:
    """``kd_shards`` with each row's place in its shard, gapless from 0."""
    rows = kd_shards(docs, depth, target_bytes=target_bytes)
    buckets = max(1, rows.count() // (2000 << depth))
    return running(rows, ["shard"], ["h_id", "doc_id", "text_crc32"], F.shiftright("h_id", 1) % F.lit(buckets), {}, "slot")


def op8_sharding(spark: SparkSession, sf_dir: str) -> DataFrame:
    rows = shard(table(spark, sf_dir, "documents"))
    return rows.select("doc_id", "size", "text_crc32", F.lit("bytes").alias("law"), "shard", "slot", F.lit(None).cast("int").alias("grown_shard"))
