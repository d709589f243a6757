"""Mixing sources to target weights by a low-discrepancy source schedule.

A source's documents are shuffled by a seeded hash and laid end to end as one circular stream of words, cut
into blocks of equal length. Slot k of the mix belongs to the source in whose share of the cumulative weights
the k-th van der Corput point falls; shares are whole numbers of slots, so that every source gets the slots its
target needs, however small it is. The slot's rank among its source's slots says which block it reads, its source's
last one up to the target. Blocks are joined to the documents that lie in them; k is the order of the mix.

Defined results: a null, empty or blank text, of any length, has size 0 and takes nothing; a null source is a source of its
own, last in order; an empty table gives an empty mix; rows are told apart even when they are equal in all columns, and
null or repeated doc_ids are as good as others; a very long text is read block by block like others; ties in the shuffle
order are broken by the row's number; extra columns are ignored.
"""

from __future__ import annotations

import math
from dataclasses import dataclass

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import identified, running, stored, table, word_count


@dataclass(frozen=True)
class MixPlan:
    """Per source: its size, target and the bounds of its share in [0, 1); all of it is one row a source."""

    names: list
    sizes: list[int]
    targets: list[float]


def capped_targets(sizes: list[int], weights: list[float], total: float, cap: float) -> list[float]:
    """Shares of ``total`` by weight; a target above ``cap`` times its source stops there, the excess goes to the rest by weight."""
    targets = [0.0] * len(sizes)
    free = {i for i in range(len(sizes)) if sizes[i] > 0}
    left = float(total)
    while free:
        w = sum(weights[i] for i in free)
        over = {i for i in free if left * weights[i] / w > cap * sizes[i]}
        if not over:
            for i in free:
                targets[i] = left * weights[i] / w
            break
        for i in over:
            targets[i] = cap * sizes[i]
            left -= targets[i]
        free -= over
    return targets


def plan_mix(per_source: list[tuple], weights_cycle: tuple[float, ...] = (3.0, 1.0, 2.0), share: float = 1.5, cap: float = 2.0) -> MixPlan:
    """``per_source``: (source, size) rows. Sources are taken by code point, null last."""
    rows = sorted(per_source, key=lambda r: (r[0] is None, r[0] or ""))
    sizes = [int(r[1]) for r in rows]
    weights = [weights_cycle[i % len(weights_cycle)] for i in range(len(rows))]
    return MixPlan([r[0] for r in rows], sizes, capped_targets(sizes, weights, share * sum(sizes), cap))


def source_schedule(spark: SparkSession, needs: list[int], cells: int = 4096) -> DataFrame:
    """Slots (k, src, rank) of sources that need so many slots each.

    The k-th van der Corput point is k's bits reversed, as a fraction of a power of two; the points below the sum of the
    needs are kept, and each belongs to the source in whose part of the cumulative needs it falls. All sources, split at
    the bounds of some ``cells`` even parts, are joined on the part, so a point is held against few of them.
    """
    total = sum(needs)
    if total <= 0:
        return spark.createDataFrame([], "k long, src int, rank long")
    bits = max(1, (total - 1).bit_length())
    shift = max(0, bits - max(cells, 4 * len(needs)).bit_length())
    parts, at = [], 0
    for i, n in enumerate(needs):
        parts += [(c, i, at, at + n) for c in range(at >> shift, ((at + n - 1) >> shift) + 1)] if n else []
        at += n
    owner = spark.createDataFrame(parts, "cell long, src int, lo long, hi long")
    point = F.conv(F.reverse(F.lpad(F.bin("id"), bits, "0")), 2, 10).cast("long")
    points = spark.range(1 << bits).select(F.col("id").alias("k"), point.alias("x")).filter(F.col("x") < total)
    mine = points.withColumn("cell", F.shiftright("x", shift)).join(F.broadcast(owner), "cell").filter("lo <= x AND x < hi")
    return running(mine.select("k", "src"), ["src"], ["k"], F.shiftright("k", bits // 2), {}, "rank")


def mix(docs: DataFrame, block: int = 4096, seed: int = 17, share: float = 1.5, cap: float = 2.0, weights: tuple[float, ...] = (3.0, 1.0, 2.0), size: Column | None = None) -> tuple[DataFrame, MixPlan]:
    """(rows, plan): each document (``row``, its number) with its size, its source's figures, the words taken, its place in
    the stream, and the first slot of the mix that reads it (null if none).

    ``doc_id`` and ``source`` are read, and ``text`` for the size unless ``size`` is given; a ``row`` column, if there is one,
    is taken as the rows' number. Sources are metadata with one row each on the driver; all that grows with the documents stays distributed.
    """
    spark = docs.sparkSession
    n = word_count(F.col("text")) if size is None else size
    rows = docs if "row" in docs.columns else identified(docs, "row")
    sized = stored(rows.select("row", "doc_id", "source", n.alias("size")), "mix-sizes")
    sums = sized.groupBy("source").agg(F.sum("size").alias("size"), F.count(F.lit(1)).alias("rows")).collect()
    plan = plan_mix([(r["source"], r["size"]) for r in sums], weights, share, cap)
    names = ["row", "doc_id", "source", "src", "size", "source_size", "target", "start", "place"]
    if not plan.names:
        kinds = sized.select("row", "doc_id", "source").schema.simpleString()[7:-1].replace(":", " ").replace(",", ", ")
        return spark.createDataFrame([], f"{kinds}, src int, size long, source_size long, target double, start long, place long, taken long, first_slot long"), plan
    whole = [min(int(round(t)), int(cap * s)) for t, s in zip(plan.targets, plan.sizes, strict=True)]
    held = {r["source"]: r["rows"] for r in sums}
    buckets = [math.isqrt(held[nm]) + 1 for nm in plan.names]
    info = spark.createDataFrame([(i, *r) for i, r in enumerate(zip(plan.names, plan.sizes, plan.targets, whole, buckets, strict=True))], "src int, source string, source_size long, target double, whole long, buckets long")
    small = F.broadcast(info) if len(plan.names) <= 10_000 else info
    rows = sized.join(small, sized["source"].eqNullSafe(info["source"])).drop(info["source"])
    rows = rows.withColumn("h", F.shiftrightunsigned(F.xxhash64("row", F.lit(seed)), 2))
    # places of the hash by its upper bits: a source has as many buckets as a bucket has rows
    rows = running(rows, ["src"], ["h", "row"], F.floor(F.col("h") / F.lit(float(1 << 62)) * F.col("buckets")), {"start": "size"}, "place")

    slots = source_schedule(spark, [-(-w // block) for w in whole])
    # slot r of a source reads words [r * block, ...) of its circular stream; a read over the stream's end goes on at its start
    reads = slots.join(F.broadcast(info.select("src", "source_size", "whole")) if len(plan.names) <= 10_000 else info.select("src", "source_size", "whole"), "src")
    reads = reads.withColumn("a", F.col("rank") * block).withColumn("b", F.least((F.col("rank") + 1) * block, F.col("whole")))
    first, last = F.floor(F.col("a") / F.col("source_size")), F.floor((F.col("b") - 1) / F.col("source_size"))
    reads = reads.select("k", "src", "source_size", "a", "b", F.explode(F.sequence(first, last)).alias("turn"))
    base = F.col("turn") * F.col("source_size")
    reads = reads.select("k", "src", (F.greatest("a", base) - base).alias("lo"), (F.least("b", base + F.col("source_size")) - base).alias("hi"))
    cell = F.explode(F.sequence(F.floor(F.col("lo") / block), F.floor((F.col("hi") - 1) / block))).alias("cell")
    reads = reads.select("k", "src", "lo", "hi", cell)
    reads = reads.select("k", "src", "cell", F.greatest("lo", F.col("cell") * block).alias("lo"), F.least("hi", (F.col("cell") + 1) * block).alias("hi"))

    covers = F.sequence(F.floor(F.col("start") / block), F.floor((F.col("start") + F.greatest("size", F.lit(1)) - 1) / block))
    spans = rows.select(*names, F.explode(covers).alias("cell"))
    hit = F.least(F.col("start") + F.col("size"), F.col("hi")) - F.greatest("start", "lo")
    met = spans.join(reads, ["src", "cell"], "left").withColumn("hit", F.coalesce(F.greatest(hit, F.lit(0)), F.lit(0)))
    out = met.groupBy(*names).agg(F.sum("hit").cast("long").alias("taken"), F.min(F.when(F.col("hit") > 0, F.col("k"))).alias("first_slot"))
    return out, plan


def first_words(text: Column, words: Column) -> Column:
    """A text up to the end of its ``words``-th word; the matches are runs of one class each, so any length will do."""
    runs = F.regexp_extract_all(text, F.lit(r"([\x20\x09-\x0D]*+[^\x20\x09-\x0D]++)"), F.lit(1))
    return F.array_join(F.slice(runs, 1, words), "")


def op1_mixture(spark: SparkSession, sf_dir: str) -> DataFrame:
    rows, _ = mix(table(spark, sf_dir, "documents"))
    return rows.select("doc_id", "size", "source_size", "target", "taken", "first_slot")
