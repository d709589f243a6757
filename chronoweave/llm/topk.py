"""Exact top-k inner products by multi-resolution segment statistics.

For a cut of the coordinates into segments of length L, Cauchy's inequality per segment gives
<x, y> <= sum L * (mx * my + sx * sy) with segment means m and deviations s: an upper bound of the product (a lower
bound of the distance) that tightens from coarse to fine cuts. Coordinates are taken along the principal axes of a few
of the task's vectors, which changes no product but puts most of it into the first ones; cuts are fine there and coarse
behind. For a block of queries and one of candidates the coarsest bound of all pairs names a few promising
candidates a query, whose exact products give a first k-th best score; finer bounds are then computed only for pairs
whose bound still reaches that score, and what is left gets its exact integer product.

Vectors are packed into binary blocks. Query blocks meet every candidate block (a stated query set against all
rows); each task keeps only k rows a query. Query blocks are broadcast while their total size, which is summed
first, is below ``broadcast_bytes``, and dealt out by an equi-join on block numbers beyond.

Where vectors have no structure (independent coordinates, many dimensions) no such bound can rule out much before it has
seen most coordinates; then nearly all pairs are multiplied, as matrices.

Defined results: null vectors, vectors with null or non-finite components and rows of null id take no part;
so do components that leave 63 bits after scaling. A query is never its own candidate (same vec_id); ties go to
the smaller vec_id; repeated vec_ids are separate candidates of the same id, and separate queries with a list each; vectors of
another length than the query's are compared with queries of their own length only; empty tables give no rows; extra columns are ignored.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from .common import frugal, stored, table

#: Segments of the cuts, from coarse to fine; each has twice as many in the first half of what is left as behind.
LEVELS = (2, 6, 12, 24)
_DENSE = 0.25
_PACKED = "dims int, n int, ids binary, data binary"


def _pack(rows_per_block: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for at in range(0, batch.num_rows, rows_per_block):
                part = batch.slice(at, rows_per_block)
                ids = part.column(0).to_numpy(zero_copy_only=False).astype(np.int64)
                lists = part.column(1)
                size = np.diff(np.asarray(lists.offsets))
                flat = np.asarray(lists.flatten())
                first = np.concatenate(([0], np.cumsum(size)))[:-1]
                out: list[tuple] = []
                for d in np.unique(size):
                    pick = np.flatnonzero(size == d)
                    x = flat[first[pick][:, None] + np.arange(d)[None, :]] if d else np.zeros((len(pick), 0))
                    kind = np.int32 if np.abs(x).max(initial=0) < 2**31 else np.int64
                    out.append((int(d), len(pick), ids[pick].tobytes(), x.astype(kind).tobytes()))
                cols = list(zip(*out, strict=True))
                yield pa.RecordBatch.from_arrays([pa.array(cols[0], pa.int32()), pa.array(cols[1], pa.int32()), pa.array(cols[2], pa.binary()), pa.array(cols[3], pa.binary())], ["dims", "n", "ids", "data"])

    return run


def packed(vectors: DataFrame, scale: int, rows_per_block: int) -> DataFrame:
    """Binary blocks (dims, n, ids, data) of floor(scale * x) for the rows that take part."""
    ints = F.transform("embedding", lambda x: F.floor(F.lit(scale).cast("double") * x.cast("double")))
    bad = F.exists("embedding", lambda x: x.isNull() | F.isnan(x.cast("double")) | (F.abs(x.cast("double") * scale) >= 2.0**63))
    rows = vectors.filter(F.col("vec_id").isNotNull() & F.col("embedding").isNotNull() & ~F.coalesce(bad, F.lit(True)))
    return rows.select(F.col("vec_id").cast("long").alias("vec_id"), ints.cast("array<long>").alias("v")).mapInArrow(frugal(_pack(rows_per_block)), _PACKED)


def unpacked(data: bytes, n: int, dims: int) -> np.ndarray:
    """Whole numbers of a block, 4 or 8 bytes each."""
    wide = n and dims and len(data) == 8 * n * dims
    return np.frombuffer(data, np.int64 if wide else np.int32).reshape(n, dims)


def axes(x: np.ndarray) -> np.ndarray:
    """Principal axes of some vectors, the one with most of their squares first; any orthonormal axes give right results."""
    x = x.astype(np.float64)
    return np.linalg.eigh(x.T @ x)[1][:, ::-1] if len(x) and x.shape[1] else np.eye(x.shape[1])


def _edges(dims: int, segments: int) -> list[int]:
    """Ends of so many segments: their lengths grow by a half from each to the next, and are one at least."""
    size = 1.5 ** np.arange(segments)
    ends = np.round(np.cumsum(size) / size.sum() * dims).astype(int)
    return sorted({max(int(e), i + 1) for i, e in enumerate(ends) if max(int(e), i + 1) < dims} | {dims})


class Segments:
    """Means and deviations of a block of vectors, along given axes, at each level from coarse to fine.

    Both are scaled by the root of the segment's length and stand side by side, so a bound is one inner product.
    """

    def __init__(self, x: np.ndarray, along: np.ndarray) -> None:
        y = x.astype(np.float64) @ along
        self.levels, self.norm = [], np.sqrt((y * y).sum(1))
        for k in LEVELS:
            parts = np.split(y, _edges(y.shape[1], k)[:-1], axis=1) if y.shape[1] else [y]
            root = [max(1, p.shape[1]) ** 0.5 for p in parts]
            mean = [p.mean(1) * r if p.shape[1] else np.zeros(len(y)) for p, r in zip(parts, root, strict=True)]
            dev = [p.std(1) * r for p, r in zip(parts, root, strict=True) if p.shape[1] > 1]
            self.levels.append(np.stack(mean + dev, 1))


def _pairs(a: np.ndarray, b: np.ndarray, i: np.ndarray, j: np.ndarray, chunk: int = 1 << 15) -> np.ndarray:
    """Inner products of the pairs (a[i], b[j])."""
    out = np.empty(len(i), np.result_type(a, b))
    for at in range(0, len(i), chunk):
        out[at : at + chunk] = np.einsum("ij,ij->i", a[i[at : at + chunk]], b[j[at : at + chunk]])
    return out


class Best:
    """The k best candidates so far of each query of a block, fed with blocks of candidates; counts what it multiplies."""

    def __init__(self, queries: np.ndarray, qids: np.ndarray, k: int) -> None:
        self.q, self.ids, self.k = queries.astype(np.int64), qids, k
        self.most = float(np.abs(self.q).max(initial=0))
        self.held: list[list[tuple[int, int]]] = [[] for _ in qids]
        self.along, self.segments = None, None
        self.exact = self.pairs = 0

    def _floor(self) -> np.ndarray:
        return np.array([float(h[-1][0]) if len(h) >= self.k else -np.inf for h in self.held])

    def _take(self, i: np.ndarray, j: np.ndarray, x: np.ndarray, ids: np.ndarray, dense: bool) -> None:
        """Exact products of the pairs (i ascending), into the lists; all of them as one matrix if ``dense``."""
        self.exact += len(i)
        small = self.most * float(np.abs(x).max(initial=0)) * max(1, x.shape[1]) < 2.0**52
        a, b = (self.q.astype(np.float64), x.astype(np.float64)) if small else (self.q, x)
        score = ((a @ b.T)[i, j] if dense else _pairs(a, b, i, j)).astype(np.int64)
        cut = np.searchsorted(i, np.arange(len(self.ids) + 1))
        for n in np.flatnonzero(np.diff(cut)).tolist():
            s, c = score[cut[n] : cut[n + 1]], ids[j[cut[n] : cut[n + 1]]]
            if len(s) > 4 * self.k:
                keep = s >= np.partition(s, -self.k)[-self.k]
                s, c = s[keep], c[keep]
            self.held[n] = sorted(self.held[n] + list(zip(s.tolist(), c.tolist(), strict=True)), key=lambda v: (-v[0], v[1]))[: self.k]

    def add(self, x: np.ndarray, ids: np.ndarray) -> None:
        x = x.astype(np.int64)
        if self.along is None:
            self.along = axes(x)
            self.segments = Segments(self.q, self.along)
        mine, theirs = self.segments, Segments(x, self.along)
        slack = 1e-9 * (1 + np.outer(mine.norm, theirs.norm))
        alive = self.ids[:, None] != ids[None, :]  # a query is not its own candidate
        self.pairs += int(alive.sum())
        bound = mine.levels[0] @ theirs.levels[0].T + slack
        bound[~alive] = -np.inf
        done = np.zeros_like(alive)
        if any(len(h) < self.k for h in self.held):
            first = min(4 * self.k, x.shape[0])
            j = np.argpartition(bound, -first, axis=1)[:, -first:].ravel()
            i = np.repeat(np.arange(len(self.ids)), first)
            use = alive[i, j]
            self._take(i[use], j[use], x, ids, False)
            done[i[use], j[use]] = True
        floor = self._floor()[:, None]
        alive &= (bound >= floor) & ~done
        for level in range(1, len(LEVELS)):
            share = alive.mean()
            if not share:
                return
            if share > _DENSE:
                alive &= mine.levels[level] @ theirs.levels[level].T + slack >= floor
            else:
                i, j = np.nonzero(alive)
                alive[i, j] = _pairs(mine.levels[level], theirs.levels[level], i, j) + slack[i, j] >= floor[i, 0]
        i, j = np.nonzero(alive)
        if len(i):
            self._take(i, j, x, ids, len(i) > _DENSE * alive.size)


def best(queries: np.ndarray, qids: np.ndarray, cands: np.ndarray, cids: np.ndarray, k: int, chunk: int = 2048) -> Best:
    """The k best (score, vec_id) of each query, highest score first, then smaller id; exact."""
    out = Best(queries, qids, k)
    for at in range(0, len(cands) if len(queries) else 0, chunk):
        out.add(cands[at : at + chunk], cids[at : at + chunk])
    return out


def _search(k: int, chunk: int = 2048):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        found: dict[int, Best] = {}
        for batch in batches:
            for row in range(batch.num_rows):
                r = {name: batch.column(i)[row].as_py() for i, name in enumerate(batch.schema.names)}
                if r["block"] not in found:
                    found[r["block"]] = Best(unpacked(r["qdata"], r["qn"], r["dims"]), np.frombuffer(r["qids"], np.int64), k)
                ids, x = np.frombuffer(r["ids"], np.int64), unpacked(r["data"], r["n"], r["dims"])
                for at in range(0, len(x), chunk):
                    found[r["block"]].add(x[at : at + chunk], ids[at : at + chunk])
        for block, b in found.items():
            rows = [(block, n, q, s, v) for n, (q, top) in enumerate(zip(b.ids.tolist(), b.held, strict=True)) for s, v in top]
            if rows:
                yield pa.RecordBatch.from_arrays([pa.array(c, pa.int64()) for c in zip(*rows, strict=True)], ["block", "place", "query_id", "score", "vec_id"])
        if found:
            yield pa.RecordBatch.from_arrays([pa.array([v], pa.int64()) for v in (None, None, None, sum(b.exact for b in found.values()), sum(b.pairs for b in found.values()))], ["block", "place", "query_id", "score", "vec_id"])

    return run


def _found(vectors: DataFrame, queries: DataFrame, k: int, scale: int = 256, block: int = 1024, broadcast_bytes: int = 64 << 20) -> DataFrame:
    """Each task's best candidates of each query row (block, place), and a row with null query_id for its work: score is the
    number of exact products, vec_id that of pairs."""
    mine = stored(packed(queries, scale, block), "topk-queries")
    mine = mine.select(F.monotonically_increasing_id().alias("block"), F.col("dims").alias("qdims"), F.col("n").alias("qn"), F.col("ids").alias("qids"), F.col("data").alias("qdata"))
    theirs = packed(vectors, scale, 4 * block)
    size = mine.agg(F.sum(F.octet_length("qdata"))).first()[0] or 0
    if size <= broadcast_bytes:
        pairs = theirs.join(F.broadcast(mine), F.col("dims") == F.col("qdims"))
    else:
        mine = stored(mine, "topk-blocks")
        per = mine.groupBy("qdims").agg(F.collect_list("block").alias("blocks"))
        spread = theirs.join(F.broadcast(per), F.col("dims") == F.col("qdims")).select("dims", "n", "ids", "data", F.explode("blocks").alias("b"))
        pairs = spread.join(mine, F.col("b") == F.col("block"))
    return pairs.select("block", "dims", "n", "ids", "data", "qn", "qids", "qdata").mapInArrow(frugal(_search(k)), "block long, place long, query_id long, score long, vec_id long")


def search(vectors: DataFrame, queries: DataFrame, k: int = 5, **options) -> DataFrame:
    """(query_id, rank, vec_id, score): each query's k best candidates among ``vectors``."""
    top = _found(vectors, queries, k, **options).filter("query_id IS NOT NULL")
    order = Window.partitionBy("block", "place").orderBy(F.desc("score"), "vec_id")
    return top.withColumn("rank", F.row_number().over(order)).filter(F.col("rank") <= k).select("query_id", "rank", "vec_id", "score")


def work(vectors: DataFrame, queries: DataFrame, k: int = 5, **options) -> DataFrame:
    """(exact, pairs): products computed in a search, of how many pairs."""
    rows = _found(vectors, queries, k, **options).filter("query_id IS NULL")
    return rows.agg(F.sum("score").alias("exact"), F.sum("vec_id").alias("pairs"))


def op10_topk(spark: SparkSession, sf_dir: str) -> DataFrame:
    e = table(spark, sf_dir, "embeddings")
    return search(e.select("vec_id", "embedding"), e.filter(F.col("vec_id") % 50 == 0).select("vec_id", "embedding"))


OP10_SQL = """
WITH v AS (SELECT vec_id, list_transform(embedding, lambda x: CAST(floor(256 * CAST(x AS DOUBLE)) AS BIGINT)) AS e FROM embeddings
           WHERE embedding IS NOT NULL AND len(list_filter(embedding, lambda x: x IS NULL OR NOT isfinite(x))) = 0),
s AS (SELECT q.vec_id AS query_id, c.vec_id AS vec_id, CAST(list_sum(list_transform(list_zip(q.e, c.e), lambda p: p[1] * p[2])) AS BIGINT) AS score
      FROM v q JOIN v c ON q.vec_id <> c.vec_id WHERE q.vec_id % 50 = 0),
r AS (SELECT *, CAST(row_number() OVER (PARTITION BY query_id ORDER BY score DESC, vec_id) AS INTEGER) AS rank FROM s)
SELECT query_id, rank, vec_id, score FROM r WHERE rank <= 5
"""
