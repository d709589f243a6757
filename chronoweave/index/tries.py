"""The temporal index as tables: prefix tries, time levels, node events and packed update matrices."""

from __future__ import annotations

import json
from collections.abc import Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from ..model.graph import TemporalGraph
from ..model.ranks import running
from ..model.query import PatternQuery
from ..plans.order import pick_permutation
from .bits import UpdateMatrix

MATRIX = "prefix array<long>, shard int, level int, n long, b binary, e binary, updates binary"


def triples(g: TemporalGraph, order: str) -> DataFrame:
    """A trie of distinct triples as a table clustered and sorted by the components in ``order``."""
    cols = list(order)
    return g.ever().select(*cols).repartitionByRange(cols[0], cols[1]).sortWithinPartitions(*cols)


def quads(g: TemporalGraph, order: str) -> DataFrame:
    """Edges clustered for a four-level trie; ``t`` in ``order`` stands for the interval, sorted by its start."""
    cols = [c if c != "t" else "ts" for c in order]
    return g.frame.repartitionByRange(cols[0], cols[1]).sortWithinPartitions(*cols, "te")


def plain(g: TemporalGraph, orders: tuple[str, ...] = ("spo", "pos", "osp")) -> dict[str, DataFrame]:
    """An index without time: the numbered distinct triples in several orders, as a yardstick for the temporal one's size."""
    ids = g.encoded().select("s", "p", "o").distinct()
    return {o: ids.select(*o).repartitionByRange(o[0], o[1]).sortWithinPartitions(*o) for o in orders}


def children(g: TemporalGraph, order: str, depth: int) -> DataFrame:
    """Child count of every node at ``depth`` of the trie of distinct triples."""
    cols = list(order)
    return g.ever().groupBy(*cols[:depth]).agg(F.countDistinct(cols[depth]).alias("children"))


def node_events(g: TemporalGraph, prefix: list[str]) -> DataFrame:
    """(prefix.., at, sign, suffix..): an insert at each start and a delete at each end, below the node of the prefix."""
    rest = [c for c in ("s", "p", "o") if c not in prefix]
    return g.frame.select(*prefix, *rest, F.col("ts").alias("at"), F.lit(1).alias("sign")).union(g.frame.select(*prefix, *rest, "te", F.lit(-1)))


def time_level(g: TemporalGraph, prefix: list[str]) -> DataFrame:
    """(prefix.., start, stop, live, updates): elementary intervals of each node, those without edges removed.

    ``updates`` is the number of the node's last update at the interval's start. The root (no prefix) sums its events
    by instant first and takes its running sums in parts of the time axis.
    """
    per = node_events(g, prefix).groupBy(*prefix, "at").agg(F.sum("sign").alias("net"), F.count(F.lit(1)).alias("n"))
    out = running(per, prefix, ["at"], {"live": "net", "updates": "n"}, follow="stop")
    return out.select(*prefix, F.col("at").alias("start"), "stop", "live", "updates").filter("live > 0")


def width_of(g: TemporalGraph) -> int:
    """Bits that number every node and label."""
    return max(1, int(g.universe().count() - 1).bit_length())


def split_order(order: str) -> tuple[list[str], list[str]]:
    """(prefix above the time level, suffix below it) of a trie order such as ``otps``."""
    at = order.index("t")
    return list(order[:at]), list(order[at + 1 :])


def numbered_events(g: TemporalGraph, order: str, width: int) -> DataFrame:
    """(prefix.., update, tick, sign, key): events below each prefix of the order in time order, deletes first, with the
    suffix joined to one number in the order's own order. Numbers come from parts of the time axis, so the events of one
    prefix, or of the whole graph where time comes first, are never sorted by one task."""
    e = g.encoded()
    prefix, rest = split_order(order)
    key = F.lit(0).cast("long")
    for c in rest:
        key = F.shiftleft(key, width) + F.col(c)
    ev = e.select(*prefix, F.col("ts_tick").alias("tick"), F.lit(1).alias("sign"), key.alias("key")).union(e.select(*prefix, "te_tick", F.lit(-1), key))
    return running(ev, prefix, ["tick", "sign", "key"], {}, row="update").select(*prefix, "update", "tick", "sign", "key")


def matrix_rows(events: DataFrame, prefix: list[str], width: int) -> DataFrame:
    """The bits of every update matrix by window sums: (prefix.., level, place, b, e).

    At level d an update's place is its rank by (first d key bits, update); E says whether the running sum of
    signs in its group is positive, B is the next bit. This is the SQL twin of the packed form.
    """
    levels = events.withColumn("level", F.explode(F.sequence(F.lit(0), F.lit(width))))
    node = F.expr(f"shiftright(key, {width} - level)")
    order = Window.partitionBy(*prefix, "level").orderBy("node", "update")
    group = Window.partitionBy(*prefix, "level", "node").orderBy("update").rowsBetween(Window.unboundedPreceding, 0)
    out = levels.withColumn("node", node)
    b = F.when(F.col("level") < width, F.expr(f"CAST(shiftright(key, {width} - 1 - level) & 1 AS INT)"))
    return out.select(*prefix, "level", F.row_number().over(order).cast("long").alias("place"), b.alias("b"), (F.sum("sign").over(group) > 0).cast("int").alias("e"))


def _packed(prefix: int, width: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        t = pa.Table.from_batches(list(batches))
        update = t.column("update").to_numpy()
        order = np.argsort(update, kind="stable")
        m = UpdateMatrix.build(t.column("key").to_numpy()[order], t.column("sign").to_numpy()[order], width)
        head = [int(t.column(i)[0].as_py()) for i in range(prefix)]
        shard = int(t.column("shard")[0].as_py())
        n = m.width + 1
        numbers = np.stack((update[order], t.column("tick").to_numpy()[order])).astype("<i8").tobytes()
        yield pa.RecordBatch.from_arrays(
            [pa.array([head] * n, pa.list_(pa.int64())), pa.array([shard] * n, pa.int32()), pa.array(range(n), pa.int32()), pa.array([m.length] * n, pa.int64()), pa.array([x.packed.tobytes() for x in m.B] + [b""], pa.binary()), pa.array([x.packed.tobytes() for x in m.E], pa.binary()), pa.array([numbers] + [b""] * (n - 1), pa.binary())],
            ["prefix", "shard", "level", "n", "b", "e", "updates"],
        )

    return run


def pack(events: DataFrame, prefix: list[str], width: int, events_each: int = 1 << 20) -> DataFrame:
    """Packed update matrices, a row a level; the first has the updates' numbers and ticks.

    A prefix with more than ``events_each`` events is cut into shards by its suffix, each a matrix of its own: a seek over shards is the
    least of their seeks, a node is alive where any shard's is. Only prefixes that are cut, one per ``events_each`` events at most, are broadcast.
    """
    if prefix:
        large = events.groupBy(*prefix).agg(F.ceil(F.count(F.lit(1)) / events_each).cast("int").alias("shards")).filter("shards > 1")
        dealt = events.join(F.broadcast(large), prefix, "left")
    else:
        dealt = events.withColumn("shards", F.lit(-(-events.count() // events_each)).cast("int"))
    dealt = dealt.withColumn("shard", F.pmod(F.xxhash64("key"), F.coalesce("shards", F.lit(1))).cast("int"))
    cols = [*prefix, "shard", "update", "tick", "sign", "key"]
    return dealt.select(*cols).groupBy(*prefix, "shard").applyInArrow(_packed(len(prefix), width), MATRIX)


def _bits(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        for r in batch.to_pylist():
            e, b = (np.unpackbits(np.frombuffer(r[c], np.uint8), bitorder="little")[: r["n"]].astype(np.int32) for c in ("e", "b"))
            n = r["n"]
            yield pa.RecordBatch.from_arrays([pa.array([r["prefix"]] * n, pa.list_(pa.int64())), pa.array([r["shard"]] * n, pa.int32()), pa.array([r["level"]] * n, pa.int32()), pa.array(np.arange(1, n + 1)), pa.array(b if len(b) else np.full(n, -1, np.int32)), pa.array(e)], ["prefix", "shard", "level", "place", "b", "e"])


def packed_bits(matrices: DataFrame) -> DataFrame:
    """The bits that packed matrices hold: (prefix, shard, level, place, b, e); b is -1 on the last level."""
    return matrices.select("prefix", "shard", "level", "n", "b", "e").mapInArrow(_bits, "prefix array<long>, shard int, level int, place long, b int, e int")


def unpack(rows: list, width: int) -> UpdateMatrix:
    """An update matrix from its level rows."""
    from .bits import RankBits

    rows = sorted(rows, key=lambda r: r["level"])
    read = lambda raw, n: RankBits(np.unpackbits(np.frombuffer(raw, np.uint8), bitorder="little", count=n))
    return UpdateMatrix(width, rows[0]["n"], [read(r["b"], r["n"]) for r in rows[:-1]], [read(r["e"], r["n"]) for r in rows])


def _window(width: int, prefix: int, rest: int, lo: int, hi: int, mode: str):
    """Suffixes alive at some or all instants of ticks [lo, hi] of each packed matrix."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        t = pa.Table.from_batches(list(batches))
        rows = sorted(t.to_pylist(), key=lambda r: r["level"])
        ticks = np.frombuffer(rows[0]["updates"], "<i8").reshape(2, -1)[1]
        m = unpack(rows, width * rest)
        p1, p2 = (int(np.searchsorted(ticks, x, "right")) for x in (lo, hi))
        got = np.array(m.members(p1) if lo == hi else m.window(p1, p2, mode), np.int64)
        if len(got):
            cols = [pa.array(np.full(len(got), v), pa.int64()) for v in rows[0]["prefix"]]
            cols += [pa.array((got >> (width * (rest - 1 - i))) & ((1 << width) - 1)) for i in range(rest)]
            yield pa.RecordBatch.from_arrays(cols, [f"c{i}" for i in range(prefix + rest)])

    return run


def matrix_window(matrices: DataFrame, order: str, width: int, lo: int, hi: int, mode: str) -> DataFrame:
    """Ids (s, p, o) of the triples that exist at some (``any``) or at every (``all``) instant of ticks [lo, hi], from the
    existence bits of the matrices alone; lo = hi is a snapshot, which is read by seeks. A prefix or shard is one task's work."""
    prefix, rest = split_order(order)
    names = [*prefix, *rest]
    schema = ", ".join(f"c{i} long" for i in range(len(names)))
    rows = matrices.withColumn("k", F.col("prefix").cast("string")).groupBy("k", "shard").applyInArrow(_window(width, len(prefix), len(rest), lo, hi, mode), schema)
    return rows.select(*[F.col(f"c{names.index(c)}").alias(c) for c in ("s", "p", "o")])


@dataclass
class IndexHandle:
    """A built index: clustered edge tables and packed matrices for a choice of orders."""

    tables: dict[str, DataFrame]
    matrices: dict[str, DataFrame]
    width: int

    def choose(self, permutation: str) -> str:
        """The order of this index that has the longest start in common with a pattern's permutation."""
        common = lambda o: next((i for i, (a, b) in enumerate(zip(o, permutation, strict=False)) if a != b), len(o))
        return max(self.tables, key=lambda o: (common(o), o))

    def scan(self, q: PatternQuery, i: int, order: list[str], g: TemporalGraph) -> DataFrame:
        """Pattern ``i``'s edges from the table that fits its constants and the binding order; its sorting lets files and row groups be skipped."""
        from ..operators.pairwise import scan

        return scan(q, i, g.of(self.tables[self.choose(pick_permutation(q.patterns[i], order))]))

    def save(self, path: str) -> None:
        spark = next(iter(self.tables.values())).sparkSession
        for name, df in self.tables.items():
            df.write.mode("overwrite").parquet(f"{path}/edges/{name}")
        for name, df in self.matrices.items():
            df.write.mode("overwrite").parquet(f"{path}/matrix/{name}")
        manifest = json.dumps({"orders": list(self.tables), "packed": list(self.matrices), "width": self.width})
        spark.createDataFrame([(manifest,)], "manifest string").coalesce(1).write.mode("overwrite").text(f"{path}/manifest")


def load(spark: SparkSession, path: str) -> IndexHandle:
    m = json.loads(spark.read.text(f"{path}/manifest").first()[0])
    return IndexHandle({o: spark.read.parquet(f"{path}/edges/{o}") for o in m["orders"]}, {o: spark.read.parquet(f"{path}/matrix/{o}") for o in m["packed"]}, m["width"])


def build(g: TemporalGraph, orders: tuple[str, ...] = ("tspo", "ptso", "otps"), pack_: bool = True, events_each: int = 1 << 20) -> IndexHandle:
    """Clustered tables for each order, and matrices for what follows the time level (one or two components below it)."""
    width = width_of(g)
    tables = {o: quads(g, o) for o in orders}
    matrices = {}
    if pack_:
        for o in orders:
            prefix, rest = split_order(o)
            if rest and len(rest) * width <= 62:
                matrices[o] = pack(numbered_events(g, o, width), prefix, len(rest) * width, events_each)
    return IndexHandle(tables, matrices, width)


def duration_classes(g: TemporalGraph) -> DataFrame:
    """(class, edges): floor(log2(length)); a scan for ranges of at least a length skips the classes below."""
    length = g.length(F.col("ts"), F.col("te"))
    return g.frame.select(F.floor(F.log2(length.cast("double"))).cast("int").alias("class")).groupBy("class").agg(F.count(F.lit(1)).alias("edges"))


def duration_grid(g: TemporalGraph) -> DataFrame:
    """Edges as (start, length) points, clustered by length class and start."""
    length = g.length(F.col("ts"), F.col("te"))
    out = g.frame.withColumns({"length": length, "class": F.floor(F.log2(length.cast("double"))).cast("int")})
    return out.repartitionByRange("class", "ts").sortWithinPartitions("class", "ts")
