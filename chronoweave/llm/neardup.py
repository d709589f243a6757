"""MinHash near-duplicate detection: universal hash minima, banding, verification, connected components.

Each document becomes the set of its word shingles, hashed to 64 bits. ``bands * rows`` universal hash
functions (odd multiplier, addend, modulo 2**64) give minima; equal minima of a band put two documents in one
bucket. Documents of equal sets are one class from the start. With 50 bands of 6 rows a pair of similarity 0.8
is missed with probability 2e-7, more similar ones far less.

No bucket is expanded into all its pairs. In each round every bucket ties its members to one representative;
pairs whose one-byte signatures speak clearly against the link are dropped, the others are confirmed on the
full sets, and components are formed. Buckets whose members are all in one component are done. The documents of
the other buckets are compared across components by their rarest shingles: all their shingles are counted, and in
the order of those counts two linked sets share a shingle within the first places of both; all pairs of different
components that do, early enough for the rest to reach the similarity, are confirmed. That step is exact for any order; rarity
only makes it selective, as the shingles of a large group of alike texts come last. So links between components
are found whatever the representatives were. Documents of one component give no rows in that join.

Defined results: null, empty and blank texts have an empty set and are linked with nothing; a text of fewer
words than a shingle is one shingle, a very long one a set like others; where doc_ids are null or repeated, each row is
a document of its own, and the component of a row is the least non-null doc_id of the rows it reaches; ties do not matter,
as every link counts; equal rows are linked; an empty table gives no rows; extra columns are ignored.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from .common import Memo, frugal, slices, stored, table, unique_ids
from .components import components

_M1, _M2 = np.uint64(0x9E3779B97F4A7C15), np.uint64(0xC2B2AE3D27D4EB4F)


def word_hashes() -> Memo:
    """Word (bytes) -> 64-bit hash."""
    return Memo(xxhash.xxh64_intdigest, 24 << 20)


def shingle_set(text: str | None, words: int, cache: dict) -> np.ndarray:
    """Sorted distinct 64-bit hashes of the text's word shingles."""
    parts = (text or "").encode().lower().split()
    if not parts:
        return np.zeros(0, np.uint64)
    h = np.fromiter(map(cache.__getitem__, parts), np.uint64, len(parts))
    k = min(words, len(parts))
    mix = h[: len(h) - k + 1].copy()
    for i in range(1, k):
        mix = (mix ^ (mix >> np.uint64(29))) * _M1 + h[i : len(h) - k + 1 + i]
    mix = (mix ^ (mix >> np.uint64(32))) * _M2
    if k < words:
        mix = mix + np.uint64(k)
    return np.unique(mix ^ (mix >> np.uint64(29)))


def hash_family(n: int, seed: int = 1) -> tuple[np.ndarray, np.ndarray]:
    rng = np.random.default_rng(seed)
    return rng.integers(0, 2**63, n, np.uint64) * np.uint64(2) + np.uint64(1), rng.integers(0, 2**63, n, np.uint64)


def minima(s: np.ndarray, a: np.ndarray, b: np.ndarray, chunk: int = 256) -> np.ndarray:
    """Least value of each hash function over the set."""
    out = np.full(len(a), np.iinfo(np.uint64).max, np.uint64)
    for at in range(0, len(s), chunk):
        np.minimum(out, (a[:, None] * s[None, at : at + chunk] + b[:, None]).min(1), out=out)
    return out


def _sketch(words: int, bands: int, rows: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        cache = word_hashes()
        a, b = hash_family(bands * rows)
        for batch in batches:
            for part in slices(batch, 1, 256):
                n, set_hash, sigs, keys = [], [], [], []
                for t in part.column(1).to_pylist():
                    s = shingle_set(t, words, cache)
                    n.append(len(s))
                    set_hash.append(xxhash.xxh3_128_digest(s.tobytes()))
                    if not len(s):
                        sigs.append(b"")
                        keys.append([])
                        continue
                    m = minima(s, a, b)
                    sigs.append((m >> np.uint64(40)).astype(np.uint8).tobytes())
                    raw = m.tobytes()
                    keys.append([xxhash.xxh64_intdigest(raw[8 * rows * i : 8 * rows * (i + 1)], i) - (1 << 63) for i in range(bands)])
                yield pa.RecordBatch.from_arrays([part.column(0), pa.array(n, pa.int64()), pa.array(set_hash, pa.binary()), pa.array(sigs, pa.binary()), pa.array(keys, pa.list_(pa.int64()))], ["doc_id", "n_shingles", "set_hash", "sig", "bands"])

    return run


def sketches(docs: DataFrame, words: int, bands: int, rows: int) -> DataFrame:
    """(doc_id, n_shingles, set_hash, sig, bands) of each document."""
    return docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text").mapInArrow(frugal(_sketch(words, bands, rows)), "doc_id long, n_shingles long, set_hash binary, sig binary, bands array<long>")


def _shingles(words: int):
    """Every shingle of each document, with its component and the size of its set."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        cache = word_hashes()
        for batch in batches:
            for part in slices(batch, 2, 256):
                cols: list[list] = [[], [], [], []]
                for doc, comp, text in zip(*(part.column(i).to_pylist() for i in range(3)), strict=True):
                    s = shingle_set(text, words, cache)
                    for c, v in zip(cols, (np.full(len(s), doc), np.full(len(s), comp), np.full(len(s), len(s)), s.view(np.int64)), strict=True):
                        c.append(v)
                yield pa.RecordBatch.from_arrays([pa.array(np.concatenate(c), pa.int64()) for c in cols], ["doc_id", "comp", "n_shingles", "band"])

    return run


def rare_pairs(shingles: DataFrame, per_cent: int) -> DataFrame:
    """Pairs (a, b) of documents of different components that can be linked, by the rarest shingles they share.

    Shingles are ordered by their number of documents, then by hash. Those of one document only come first and match
    nothing, so a document's places are counted from their number. Two linked sets share a shingle so early in both
    that enough others can follow. Only the rows of those early places are shuffled; what the join tests and rejects (one
    component, or too late a place) is never a row.
    """
    counts = stored(shingles.groupBy("band").agg(F.count(F.lit(1)).alias("held"), F.min("comp").alias("lo"), F.max("comp").alias("hi")).filter("held > 1"), "nd-counts")
    shared = shingles.join(counts, "band")
    own = Window.partitionBy("doc_id")
    place = F.col("n_shingles") - F.count(F.lit(1)).over(own) + F.row_number().over(own.orderBy("held", "band")) - 1
    prefix = F.col("n_shingles") - F.ceil(per_cent * F.col("n_shingles") / 100) + 1
    early = stored(shared.withColumn("place", place).filter((F.col("place") < prefix) & (F.col("lo") < F.col("hi"))).select("band", "comp", "doc_id", "n_shingles", "place"), "nd-early")
    x, y = early.alias("x"), early.alias("y")
    follow = F.least(F.col("x.n_shingles") - F.col("x.place"), F.col("y.n_shingles") - F.col("y.place"))
    reach = (100 + per_cent) * follow >= per_cent * (F.col("x.n_shingles") + F.col("y.n_shingles"))
    on = (F.col("x.band") == F.col("y.band")) & (F.col("x.doc_id") < F.col("y.doc_id")) & (F.col("x.comp") != F.col("y.comp")) & reach
    return x.join(y, on).select(F.col("x.doc_id").alias("a"), F.col("y.doc_id").alias("b"))


def _alike(least: float):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            if not batch.num_rows:
                continue
            x, y = (np.frombuffer(b"".join(batch.column(i).to_pylist()), np.uint8).reshape(batch.num_rows, -1) for i in (2, 3))
            keep = pa.array((x == y).mean(1) >= least)
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1)], ["a", "b"]).filter(keep)

    return run


def _confirm(words: int, per_cent: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        cache = word_hashes()
        last: tuple = (None, None)
        for batch in batches:
            for part in slices(batch, 3, 256):
                out = []
                for i in range(part.num_rows):
                    a, x, y = (part.column(c)[i].as_py() for c in (0, 2, 3))
                    if last[0] != a:
                        last = (a, shingle_set(x, words, cache))
                    s, t = last[1], shingle_set(y, words, cache)
                    both = len(np.intersect1d(s, t, assume_unique=True))
                    out.append(100 * both >= per_cent * (len(s) + len(t) - both))
                keep = pa.array(out, pa.bool_())
                yield pa.RecordBatch.from_arrays([part.column(0), part.column(1)], ["a", "b"]).filter(keep)

    return run


def near_duplicates(docs: DataFrame, words: int = 5, per_cent: int = 80, bands: int = 50, rows: int = 6, rounds: int = 3) -> DataFrame:
    """(doc_id, n_shingles, component_id, kept): each document's class by links of at least ``per_cent`` similarity."""
    docs = docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text")
    if unique_ids(docs):
        return _classes(docs, words, per_cent, bands, rows, rounds)
    held = stored(docs.withColumn("row", F.monotonically_increasing_id()), "nd-rows")
    told = _classes(held.select(F.col("row").alias("doc_id"), "text"), words, per_cent, bands, rows, rounds)
    told = stored(told.select(F.col("doc_id").alias("row"), "n_shingles", F.col("component_id").alias("c")), "nd-told").join(held.select("row", "doc_id"), "row")
    least = told.groupBy(F.col("c").alias("g")).agg(F.min("doc_id").alias("component_id"))
    out = told.join(least, F.col("c") == F.col("g")).select("doc_id", "n_shingles", "component_id")
    return out.withColumn("kept", F.col("doc_id").eqNullSafe(F.col("component_id")))


def _classes(docs: DataFrame, words: int, per_cent: int, bands: int, rows: int, rounds: int) -> DataFrame:
    """``near_duplicates`` of rows with unique ids."""
    sk = stored(sketches(docs, words, bands, rows), "nd-sketches")
    ident = sk.groupBy("set_hash", "n_shingles").agg(F.min("doc_id").alias("rep"))
    members = sk.filter("n_shingles > 0").select("doc_id", "n_shingles", "set_hash").join(ident.select("set_hash", "rep"), "set_hash")
    classes = stored(members.select("doc_id", "n_shingles", "rep"), "nd-classes")
    reps = sk.join(ident.filter("n_shingles > 0").select(F.col("rep").alias("doc_id")), "doc_id", "left_semi")
    rows_ = reps.select("doc_id", "n_shingles", F.explode("bands").alias("band"))
    full = rows_.groupBy("band").agg(F.count(F.lit(1)).alias("n")).filter("n > 1").select("band")
    buckets = stored(rows_.join(full, "band", "left_semi"), "nd-buckets")
    sig = stored(reps.join(buckets.select("doc_id").distinct(), "doc_id", "left_semi").select("doc_id", "sig"), "nd-signatures")
    text = stored(docs.join(sig.select("doc_id"), "doc_id", "left_semi"), "nd-texts")

    def confirmed(pairs: DataFrame) -> DataFrame:
        """Those of the pairs (a, b) that are links."""
        s1, s2 = sig.select(F.col("doc_id").alias("a"), F.col("sig").alias("x")), sig.select(F.col("doc_id").alias("b"), F.col("sig").alias("y"))
        cut = per_cent / 100 - 4.5 * (0.16 / (bands * rows)) ** 0.5 - 0.01
        near = stored(pairs.join(s1, "a").join(s2, "b").select("a", "b", "x", "y").mapInArrow(frugal(_alike(cut)), "a long, b long"), "nd-near")
        t1, t2 = text.select(F.col("doc_id").alias("a"), F.col("text").alias("x")), text.select(F.col("doc_id").alias("b"), F.col("text").alias("y"))
        both = near.join(t2, "b").join(t1, "a").select("a", "b", "x", "y")
        return stored(both.mapInArrow(frugal(_confirm(words, per_cent)), "a long, b long"), "nd-links")

    fits = lambda p, q: (100 * F.least(p, q) >= per_cent * F.greatest(p, q))
    links, tried, live = None, None, buckets.withColumn("comp", F.col("doc_id"))
    for r in range(rounds + 1):
        if r < rounds:
            turn = F.xxhash64("doc_id", F.lit(r)) if r else F.col("doc_id")
            head = live.groupBy("band").agg(F.min_by(F.struct("doc_id", "comp", "n_shingles"), turn).alias("h"))
            at = live.join(head, "band").filter((F.col("comp") != F.col("h.comp")) & fits(F.col("n_shingles"), F.col("h.n_shingles")))
            pairs = at.select(F.least("doc_id", "h.doc_id").alias("a"), F.greatest("doc_id", "h.doc_id").alias("b"))
        else:
            single = live.select("doc_id", "comp").distinct().join(text, "doc_id").select("doc_id", "comp", "text")
            single = stored(single, "nd-open")
            keyed = single.mapInArrow(frugal(_shingles(words)), "doc_id long, comp long, n_shingles long, band long")
            pairs = rare_pairs(stored(keyed, "nd-shingles"), per_cent)
        pairs = pairs.distinct()
        pairs = stored(pairs.join(tried, ["a", "b"], "left_anti") if tried is not None else pairs, "nd-pairs")
        if pairs.isEmpty():
            if r < rounds:
                continue
            break
        found = confirmed(pairs)
        tried = pairs if tried is None else tried.union(pairs)
        links = found if links is None else links.union(found)
        comp = stored(components(links), "nd-components")
        if r < rounds:
            named = buckets.join(comp.withColumnRenamed("id", "doc_id").withColumnRenamed("component", "comp"), "doc_id", "left").withColumn("comp", F.coalesce("comp", "doc_id"))
            mixed = named.groupBy("band").agg(F.min("comp").alias("lo"), F.max("comp").alias("hi")).filter("lo < hi").select("band")
            live = stored(named.join(mixed, "band", "left_semi"), "nd-live")
            if live.isEmpty():
                break
    if links is None:
        out = classes.withColumn("component_id", F.col("rep"))
    else:
        out = classes.join(comp.withColumnRenamed("id", "rep"), "rep", "left").withColumn("component_id", F.coalesce("component", "rep"))
    out = out.select("doc_id", "n_shingles", "component_id")
    bare = sk.filter("n_shingles = 0").select("doc_id", "n_shingles", F.col("doc_id").alias("component_id"))
    return out.union(bare).withColumn("kept", F.col("doc_id") == F.col("component_id"))


def op4_neardup(spark: SparkSession, sf_dir: str) -> DataFrame:
    return near_duplicates(table(spark, sf_dir, "documents"), words=2)


#: The contract by all pairs of documents that share a shingle, and reachability.
OP4_SQL = r"""
WITH RECURSIVE d AS (SELECT doc_id, regexp_extract_all(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\x20\x09-\x0D]+') AS w FROM documents),
s AS MATERIALIZED (SELECT DISTINCT doc_id, CASE WHEN len(w) = 1 THEN w[1] ELSE w[i] || ' ' || w[i + 1] END AS g FROM (SELECT doc_id, w, unnest(range(1, greatest(len(w), 2))) AS i FROM d WHERE len(w) > 0)),
n AS MATERIALIZED (SELECT doc_id, count(*) AS n FROM s GROUP BY doc_id),
p AS (SELECT a.doc_id AS x, b.doc_id AS y, count(*) AS k FROM s a JOIN s b ON a.g = b.g AND a.doc_id < b.doc_id GROUP BY 1, 2),
l AS MATERIALIZED (SELECT x, y FROM p JOIN n a ON a.doc_id = x JOIN n b ON b.doc_id = y WHERE 100 * k >= 80 * (a.n + b.n - k)),
e AS MATERIALIZED (SELECT x, y FROM l UNION ALL SELECT y, x FROM l),
r(id, root) AS (SELECT doc_id, doc_id FROM d UNION SELECT e.y, r.root FROM r JOIN e ON e.x = r.id),
c AS (SELECT id, min(root) AS component_id FROM r GROUP BY id)
SELECT d.doc_id, coalesce(n.n, 0) AS n_shingles, c.component_id, d.doc_id = c.component_id AS kept FROM d JOIN c ON c.id = d.doc_id LEFT JOIN n ON n.doc_id = d.doc_id
"""
