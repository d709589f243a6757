"""Byte-level BPE: vectorised pre-tokenisation, cached pair merging, offsets, decoding.

Texts of a batch become one array of code points, each with a class. A finite transducer over classes decides
where a piece of the split pattern begins. Its transition functions are composed associatively: each stretch of
the input becomes one function from entry state to exit state, functions are combined by a doubling scan, and
known entry states then give all boundaries at once. No regular expression runs over the text.

The split pattern is that of ``public_tokenizers.PATTERN``: a contraction at the start of a piece, a run of
letters, of numbers or of other characters with at most one leading space, or white space of which the last
character before a non-space is left to what follows.

Defined results: a null or empty text has no tokens; every text is encoded whole; special tokens are ordinary
text; repeated rows give equal results; an empty table stays empty; extra columns are ignored.
"""

from __future__ import annotations

import base64
import hashlib
import heapq
import unicodedata
from collections.abc import Iterator
from functools import lru_cache
from itertools import chain

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession

from .common import Memo, frugal, slices, table

# Symbols of the transducer.
LETTER, NUMBER, OTHER, SHORT, LONG, SPACE, JOIN, BREAK, RESET = range(9)
# States: nothing pending, in a run of one class, in white space, behind a joined space, in a contraction.
FRESH, IN_L, IN_N, IN_O, IN_W, JOINED, ONE_LEFT, TWO_LEFT = range(8)
#: Characters with the White_Space property (fixed values).
WHITE = [0x9, 0xA, 0xB, 0xC, 0xD, 0x20, 0x85, 0xA0, 0x1680, *range(0x2000, 0x200B), 0x2028, 0x2029, 0x202F, 0x205F, 0x3000]
#: What may follow an apostrophe as a contraction (fixed values).
ENDINGS = ("s", "t", "re", "ve", "m", "ll", "d")

_NONE = 1 << 60


def _machine() -> tuple[np.ndarray, np.ndarray]:
    """(next state, piece begins here) for each symbol and state."""
    to, begins = np.zeros((9, 8), np.uint8), np.ones((9, 8), bool)
    for symbol, run in ((LETTER, IN_L), (NUMBER, IN_N), (OTHER, IN_O)):
        to[symbol] = run
        begins[symbol, [run, JOINED]] = False
    to[LETTER, ONE_LEFT], to[LETTER, TWO_LEFT] = FRESH, ONE_LEFT
    begins[LETTER, [ONE_LEFT, TWO_LEFT]] = False
    for symbol, left in ((SHORT, ONE_LEFT), (LONG, TWO_LEFT)):
        to[symbol] = left
        to[symbol, [IN_O, JOINED]] = IN_O
        begins[symbol, [IN_O, JOINED]] = False
    to[SPACE], to[JOIN], to[BREAK], to[RESET] = IN_W, JOINED, FRESH, FRESH
    begins[SPACE, IN_W] = False
    return to, begins


NEXT, BEGINS = _machine()


@lru_cache(1)
def classes() -> np.ndarray:
    """Symbol of each code point, without what its neighbours add."""
    out = np.full(0x110000, OTHER, np.uint8)
    for cp in range(0x110000):
        c = unicodedata.category(chr(cp))[0]
        if c == "L":
            out[cp] = LETTER
        elif c == "N":
            out[cp] = NUMBER
    out[WHITE] = SPACE
    return out


def symbols(points: np.ndarray, ends: np.ndarray) -> np.ndarray:
    """Symbols of concatenated texts, each closed by a separator at ``ends``; neighbours are looked at within a text."""
    sym = classes()[points]
    sym[ends] = RESET
    after = np.append(sym[1:], RESET)
    last = (sym == SPACE) & (after != SPACE) & (after != RESET)
    sym[last] = np.where(points[last] == 0x20, JOIN, BREAK)
    quote = np.flatnonzero((points == 0x27) & (sym == OTHER))
    if len(quote):
        n = len(points)
        one = np.where(sym[np.minimum(quote + 1, n - 1)] == LETTER, points[np.minimum(quote + 1, n - 1)], 0)
        two = np.where(sym[np.minimum(quote + 2, n - 1)] == LETTER, points[np.minimum(quote + 2, n - 1)], 0)
        two = np.where(one > 0, two, 0)
        for e in ENDINGS:
            hit = one == ord(e[0])
            if len(e) == 2:
                hit &= two == ord(e[1])
            sym[quote[hit]] = SHORT if len(e) == 1 else LONG
    return sym


def boundaries(sym: np.ndarray, stretch: int = 128) -> np.ndarray:
    """True where a piece begins: a blocked scan of composed transition functions."""
    n = len(sym)
    blocks = -(-n // stretch)
    grid = np.full(blocks * stretch, RESET, np.uint8)
    grid[:n] = sym
    grid = grid.reshape(blocks, stretch).T.copy()
    flat = NEXT.ravel()
    whole = np.tile(np.arange(8, dtype=np.uint8), (blocks, 1))  # function of each stretch, as its table
    for row in grid:
        whole = flat[(row.astype(np.intp) * 8)[:, None] + whole]
    gap = 1
    while gap < blocks:  # inclusive scan: later function after earlier function
        whole[gap:] = np.take_along_axis(whole[gap:], whole[:-gap].astype(np.intp), 1)
        gap *= 2
    state = np.concatenate((np.array([FRESH], np.uint8), whole[:-1, FRESH]))
    begin = np.empty((stretch, blocks), bool)
    flags = BEGINS.ravel()
    for j, row in enumerate(grid):
        at = row.astype(np.intp) * 8 + state
        begin[j] = flags[at]
        state = flat[at]
    return begin.T.ravel()[:n]


def split(texts: list[str]) -> list[list[str]]:
    """Pieces of each text."""
    return [[t[a:b] for a, b in zip(s, [*s[1:], len(t)])] for t, s in zip(texts, starts(texts), strict=True)]


def starts(texts: list[str]) -> list[list[int]]:
    """Code-point offsets at which the pieces of each text begin."""
    joined = "\n".join(texts) + "\n"
    points = np.frombuffer(joined.encode("utf-32-le"), np.uint32)
    ends = np.cumsum(np.fromiter((len(t) + 1 for t in texts), np.int64, len(texts))) - 1
    begin = boundaries(symbols(points, ends))
    begin[ends] = False
    at = np.flatnonzero(begin)
    first = np.concatenate(([0], ends[:-1] + 1))
    cut = np.searchsorted(at, np.append(first, len(points)))
    return [(at[a:b] - f).tolist() for a, b, f in zip(cut[:-1], cut[1:], first, strict=True)]


class Ranks:
    """A rank file: token bytes and ids, both ways, and the merge of one piece."""

    def __init__(self, path: str) -> None:
        with open(path, "rb") as f:
            self.rank = {base64.b64decode(a): int(b) for a, b in (line.split() for line in f if line.strip())}
        self.token = {v: k for k, v in self.rank.items()}

    def merge(self, piece: bytes) -> tuple[int, ...]:
        """Ids of a piece: again and again the adjacent pair of lowest rank is joined, the leftmost of equals first."""
        if piece in self.rank:
            return (self.rank[piece],)
        rank, n = self.rank, len(piece)
        if n <= 48:
            return self._merge_short(piece)
        end, after, before = list(range(1, n + 1)), list(range(1, n + 1)), list(range(-1, n - 1))
        alive, heap = [True] * n, []
        for i in range(n - 1):
            if (r := rank.get(piece[i : i + 2])) is not None:
                heap.append((r, i, i + 2))
        heapq.heapify(heap)
        while heap:
            r, i, stop = heapq.heappop(heap)
            j = after[i] if alive[i] else n
            if not alive[i] or j >= n or end[j] != stop:
                continue
            alive[j], end[i], after[i] = False, stop, after[j]
            if after[j] < n:
                before[after[j]] = i
            for a in (before[i], i):
                if a >= 0 and (b := after[a]) < n and (r := rank.get(piece[a : end[b]])) is not None:
                    heapq.heappush(heap, (r, a, end[b]))
        return tuple(rank[piece[i : end[i]]] for i in range(n) if alive[i])


    def _merge_short(self, piece: bytes) -> tuple[int, ...]:
        """The same by scanning all pairs each time, which is quicker for a short piece."""
        rank = self.rank
        parts = [piece[i : i + 1] for i in range(len(piece))]
        pairs = [rank.get(piece[i : i + 2], _NONE) for i in range(len(piece) - 1)]
        while pairs and (low := min(pairs)) < _NONE:
            i = pairs.index(low)
            parts[i : i + 2] = [parts[i] + parts[i + 1]]
            del pairs[i]
            if i < len(pairs):
                pairs[i] = rank.get(parts[i] + parts[i + 1], _NONE)
            if i:
                pairs[i - 1] = rank.get(parts[i - 1] + parts[i], _NONE)
        return tuple([rank[p] for p in parts])


class Encoder:
    """Encodes batches of texts; pieces met before come from a cache of bounded bytes."""

    def __init__(self, path: str, cache_bytes: int = 48 << 20) -> None:
        self.ranks = Ranks(path)
        self.cache = Memo(lambda piece: self.ranks.merge(piece.encode()), cache_bytes)
        top = max(self.ranks.token)
        self.bytes_of = [self.ranks.token.get(i, b"") for i in range(top + 1)]
        self.decimal = [str(i) for i in range(top + 1)]

    def encode(self, texts: list[str | None]) -> list[list[int]]:
        texts = [t or "" for t in texts]
        get = self.cache.__getitem__
        return [list(chain.from_iterable(map(get, pieces))) for pieces in split(texts)]

    def offsets(self, ids: list[int]) -> np.ndarray:
        """Byte offset at which each token begins."""
        sizes = np.fromiter((len(self.bytes_of[i]) for i in ids), np.int64, len(ids))
        return np.cumsum(sizes) - sizes

    def decode(self, ids: list[int]) -> bytes:
        return b"".join(map(self.bytes_of.__getitem__, ids))


@lru_cache(2)
def encoder(path: str) -> Encoder:
    return Encoder(path)


def encode(docs: DataFrame, path: str) -> DataFrame:
    """(doc_id, ids array<int>, offsets array<int>): token ids of each text and the byte at which each begins."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        enc = encoder(path)
        for batch in batches:
            for part in slices(batch, 1):
                ids = enc.encode(part.column(1).to_pylist())
                yield pa.RecordBatch.from_arrays([part.column(0), pa.array(ids, pa.list_(pa.int32())), pa.array([enc.offsets(x).astype(np.int32) for x in ids], pa.list_(pa.int32()))], ["doc_id", "ids", "offsets"])

    return docs.select("doc_id", "text").mapInArrow(frugal(run), f"doc_id {docs.schema['doc_id'].dataType.simpleString()}, ids array<int>, offsets array<int>")


def decode(tokens: DataFrame, path: str) -> DataFrame:
    """(doc_id, data binary) from rows with ``ids``."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        enc = encoder(path)
        for batch in batches:
            for at in range(0, batch.num_rows, 256):
                part = batch.slice(at, 256)
                yield pa.RecordBatch.from_arrays([part.column(0), pa.array([enc.decode(x or []) for x in part.column(1).to_pylist()], pa.binary())], ["doc_id", "data"])

    return tokens.select("doc_id", "ids").mapInArrow(frugal(run), f"doc_id {tokens.schema['doc_id'].dataType.simpleString()}, data binary")


def digests(docs: DataFrame, path: str) -> DataFrame:
    """(doc_id, n_tokens, ids_sha256, decoded_sha256): encode and decode as above, keeping only digests of both."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        enc = encoder(path)
        dec = enc.decimal.__getitem__
        sha = hashlib.sha256
        for batch in batches:
            for part in slices(batch, 1):
                ids = enc.encode(part.column(1).to_pylist())
                n = pa.array([len(x) for x in ids], pa.int64())
                i = pa.array([sha(" ".join(map(dec, x)).encode()).hexdigest() for x in ids])
                d = pa.array([sha(enc.decode(x)).hexdigest() for x in ids])
                yield pa.RecordBatch.from_arrays([part.column(0), n, i, d], ["doc_id", "n_tokens", "ids_sha256", "decoded_sha256"])

    return docs.select("doc_id", "text").mapInArrow(frugal(run), f"doc_id {docs.schema['doc_id'].dataType.simpleString()}, n_tokens long, ids_sha256 string, decoded_sha256 string")


def rank_file() -> str:
    import public_tokenizers

    return public_tokenizers.path("byte_bpe_50k.tiktoken")


def op2_bpe(spark: SparkSession, sf_dir: str) -> DataFrame:
    return digests(table(spark, sf_dir, "documents"), rank_file())
