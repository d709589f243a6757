"""Substring dedup by word windows found through content-chosen anchors.

Every run of ``words`` words (25) that stands at an earlier place too, whatever its punctuation and white space,
is a repeat. Two rounds find all of them. First, each window of 25 words names one anchor in it, the 13-word run
of least hash, so equal windows name equal anchors and neighbours mostly share one; anchor hashes are counted
over all documents, behind one shuffle. Second, only windows whose anchor stands at several places are hashed
themselves (64 bits); the windows of one anchor's place are neighbours and are shuffled together, by the anchor's hash.
The first place of each repeated hash is the least (doc_id, row, place), and the words under any other place are removed. Words beside a repeat that go with it by chance stay: of a sentence (cut at
sentence ends, commas before white space and line ends) that is covered in part, a stretch of fewer than five words is kept.

Defined results: null, empty and blank texts have no sentences; a text shorter than a window is never touched;
rows of equal doc_id are told apart by their text hash; a null doc_id sorts first; repeats within one document
count like others; an empty table stays empty; extra columns are ignored; words are runs of anything but white space; a sentence
counts as removed when any of its words is.
"""

from __future__ import annotations

import re
from collections.abc import Iterator
from itertools import chain

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from .common import stored, table

CUT = re.compile(r"(?<=[.!?,;:])\s+|\n+")
WORD = re.compile(r"\S+")
_BASE = np.uint64(0x9E3779B97F4A7C15)
_LEAST_PART = 5


def sentences(text: str | None) -> list[tuple[int, int]]:
    """(start, end) of each sentence, white space between them left out."""
    if not text:
        return []
    out, at = [], 0
    for m in CUT.finditer(text):
        if m.start() > at:
            out.append((at, m.start()))
        at = m.end()
    if at < len(text):
        out.append((at, len(text)))
    return out


def word_hashes(texts: list[str | None]) -> tuple[np.ndarray, np.ndarray]:
    """(hashes of all words of the texts in a row, words of each text)."""
    cut = [t.split() if t else [] for t in texts]
    size = np.fromiter(map(len, cut), np.int64, len(cut))
    return np.fromiter(map(xxhash.xxh3_64_intdigest, chain.from_iterable(cut)), np.uint64, int(size.sum())), size


def rolled(h: np.ndarray, k: int) -> np.ndarray:
    """A hash of each run of k words."""
    out = np.zeros(max(0, len(h) - k + 1), np.uint64)
    for i in range(k):
        out = out * _BASE + h[i : i + len(out)]
    for shift, times in ((30, 0xBF58476D1CE4E5B9), (27, 0x94D049BB133111EB)):
        out = (out ^ (out >> np.uint64(shift))) * np.uint64(times)
    return out ^ (out >> np.uint64(31))


def named(h: np.ndarray, size: np.ndarray, words: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(start of each window of ``words`` words within one text, place of its anchor, all anchor hashes)."""
    k = words // 2 + 1
    v = rolled(h, k)
    end = np.repeat(np.cumsum(size), size)
    start = np.flatnonzero(np.arange(len(h)) + words <= end)
    n = len(h) - words + 1
    if n <= 0:
        return start, start, v
    least, at = v[:n].copy(), np.arange(n)
    for j in range(1, words - k + 1):
        lower = v[j : j + n] <= least
        least[lower] = v[j : j + n][lower]
        at[lower] = np.flatnonzero(lower) + j
    return start, at[start], v


_PLACES = "doc_id long, row long, place int, hash long"


def _places(ids: pa.Array, rows: pa.Array, size: np.ndarray, at: np.ndarray, hashes: np.ndarray) -> list[pa.Array]:
    """doc_id, row, place in its text and hash of each place; ``hashes`` has one a place."""
    text = np.repeat(np.arange(len(size)), size)[at]
    first = np.cumsum(size) - size
    take = pa.array(text)
    return [ids.take(take), rows.take(take), pa.array((at - first[text]).astype(np.int32)), pa.array(hashes.view(np.int64))]


def anchor_table(docs: DataFrame, words: int) -> DataFrame:
    """(doc_id, row, place, hash) of every anchor; ``row`` tells rows of equal doc_id apart."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for begin in range(0, batch.num_rows, 256):
                part = batch.slice(begin, 256)
                h, size = word_hashes(part.column(2).to_pylist())
                _, at, v = named(h, size, words)
                at = np.unique(at)
                yield pa.RecordBatch.from_arrays(_places(part.column(0), part.column(1), size, at, v[at]), ["doc_id", "row", "place", "hash"])

    return docs.select("doc_id", "row", "text").mapInArrow(run, _PLACES)


def window_table(docs: DataFrame, words: int) -> DataFrame:
    """(doc_id, row, place, hash, windows) of each anchor whose place is in ``places``: its hash, the place of the first
    window that names it, and the hashes of that and the following windows that do."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for begin in range(0, batch.num_rows, 256):
                part = batch.slice(begin, 256)
                h, size = word_hashes(part.column(2).to_pylist())
                start, at, v = named(h, size, words)
                hit = np.zeros(len(h) + 1, bool)
                for f, own in zip((np.cumsum(size) - size).tolist(), part.column(3).to_pylist(), strict=True):
                    hit[np.array(own, np.int64) + f] = True
                start, at = start[hit[at]], at[hit[at]]
                edge = np.flatnonzero(np.diff(at, prepend=-1))
                windows = pa.ListArray.from_arrays(pa.array(np.append(edge, len(at)).astype(np.int32)), pa.array(rolled(h, words)[start].view(np.int64)))
                yield pa.RecordBatch.from_arrays([*_places(part.column(0), part.column(1), size, start[edge], v[at[edge]]), windows], ["doc_id", "row", "place", "hash", "windows"])

    return docs.select("doc_id", "row", "text", "places").mapInArrow(run, _PLACES + ", windows array<long>")


def removed(text: str, places: list[int], words: int) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(start of each word, whether it goes, number of the sentence it stands in)."""
    begin = np.fromiter((m.start() for m in WORD.finditer(text)), np.int64)
    drop = np.zeros(len(begin) + 1, np.int64)
    np.add.at(drop, np.array(places, np.int64), 1)
    np.add.at(drop, np.array(places, np.int64) + words, -1)
    out = np.cumsum(drop)[:-1] > 0
    own = np.searchsorted([a for a, _ in sentences(text)], begin, "right")
    # a stretch is a run of covered or uncovered words of one sentence
    edge = np.flatnonzero(np.concatenate(([True], (out[1:] != out[:-1]) | (own[1:] != own[:-1]))))
    long = np.diff(np.append(edge, len(begin)))
    of = own[edge]
    whole = np.bincount(of, minlength=of[-1] + 1)[of] == 1
    out &= np.repeat(whole | (long >= _LEAST_PART), long)
    return begin, out, own


def _keep(words: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for at in range(0, batch.num_rows, 256):
                part = batch.slice(at, 256)
                total, gone, kept = [], [], []
                for t, places in zip(part.column(1).to_pylist(), part.column(2).to_pylist(), strict=True):
                    total.append(len(sentences(t)))
                    if not places:
                        gone.append(0)
                        kept.append(t)
                        continue
                    begin, out, own = removed(t, places, words)
                    gone.append(len(np.unique(own[out])))
                    begin[0] = 0
                    edge = np.flatnonzero(np.concatenate(([True], out[1:] != out[:-1])))
                    cut = [*begin[edge].tolist(), len(t)]
                    kept.append("".join(t[a:b] for a, b, o in zip(cut, cut[1:], out[edge].tolist(), strict=False) if not o))
                yield pa.RecordBatch.from_arrays([part.column(0), pa.array(total, pa.int64()), pa.array(gone, pa.int64()), pa.array(kept, pa.string())], ["doc_id", "n_sentences", "n_removed", "text"])

    return run


def _per_row(places: DataFrame) -> DataFrame:
    return places.groupBy(F.col("doc_id").alias("d"), F.col("row").alias("r")).agg(F.collect_set("place").alias("places"))


def deduplicate(docs: DataFrame, words: int = 25) -> DataFrame:
    """(doc_id, n_sentences, n_removed, text): texts without the words of non-first repeated windows."""
    docs = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.xxhash64("text").alias("row"), "text")
    again = anchor_table(docs, words).withColumn("n", F.count(F.lit(1)).over(Window.partitionBy("hash"))).filter("n > 1")
    per = stored(_per_row(again), "span-anchors")
    same = docs["doc_id"].eqNullSafe(per["d"]) & (docs["row"] == per["r"])
    # equal windows name equal anchors, so what the anchors' hashes deal out need not be dealt again by window
    dealt = window_table(docs.join(per, same), words).repartition("hash")
    spans = dealt.select("hash", "doc_id", "row", "place", F.posexplode("windows").alias("nth", "window")).withColumn("place", F.col("place") + F.col("nth"))
    # rows of equal doc_id and text are one place, hence of one rank
    later = spans.withColumn("n", F.rank().over(Window.partitionBy("hash", "window").orderBy("doc_id", "row", "place"))).filter("n > 1")
    cover = stored(_per_row(later), "span-cover")
    both = docs.join(cover, docs["doc_id"].eqNullSafe(cover["d"]) & (docs["row"] == cover["r"]), "left")
    return both.select("doc_id", "text", "places").mapInArrow(_keep(words), "doc_id long, n_sentences long, n_removed long, text string")


def op5_substrings(spark: SparkSession, sf_dir: str) -> DataFrame:
    return deduplicate(table(spark, sf_dir, "documents"))
