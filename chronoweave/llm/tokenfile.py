"""Token-id output as patched frame-of-reference blocks, and reading them back.

A segment holds the ids of consecutive documents: ``payload`` is a run of blocks of up to 4,096 ids, ``index``
the byte at which each block starts. A block subtracts its minimum, packs the rest in the bit width that makes
the block smallest among the widths of a few percentiles, and keeps what does not fit in a list of exceptions.
Block layout, little-endian: count u16, width u8, exceptions u16, minimum u32, packed bits, then positions u16 and high parts u32.

Segments are written through Spark (committed by task, safe to lose executors) in ascending doc_id order: rows
are dealt out by ranges of doc_id and sorted, and each task encodes and packs what it holds, some 2**20 ids a
segment. The offset of a document is a prefix sum: over the tasks' totals, then within the task.

Defined results: a null or empty text is the end id alone; a null doc_id sorts first; documents of equal id are
neighbours in an order by text; an empty table gives no segments; extra columns are ignored.
"""

from __future__ import annotations

import zlib
from collections.abc import Iterator
from functools import lru_cache

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F
from pyspark.taskcontext import TaskContext

from .common import frugal, scratch, slices, table

BLOCK = 4096
PERCENTILES = (50, 75, 90, 95, 99, 100)
SEGMENT_SCHEMA = "task int, seq int, ids_before long, n_ids long, doc_ids binary, doc_null binary, doc_lens binary, index binary, payload binary"


def pack_block(ids: np.ndarray) -> bytes:
    low = int(ids.min())
    rest = (ids.astype(np.int64) - low).astype("<u4")
    n = len(ids)
    # bit lengths have the same percentiles as the values, and 33 of them need no sorting
    upto = np.cumsum(np.bincount(np.frexp(rest.astype(np.float64))[1], minlength=33))
    widths = {int(np.searchsorted(upto, min(n - 1, n * q // 100), "right")) for q in PERCENTILES}
    width = min(widths, key=lambda w: ((n * w + 7) // 8 + 6 * (n - int(upto[w])), w))
    over = np.flatnonzero(rest >> np.uint32(width)) if width < 32 else np.zeros(0, np.int64)
    head = np.array([n], "<u2").tobytes() + bytes([width]) + np.array([len(over)], "<u2").tobytes() + np.array([low], "<u4").tobytes()
    held = -(-width // 8)
    raw = np.ascontiguousarray(rest.view(np.uint8).reshape(n, 4)[:, :held])
    if width % 8:
        raw = np.packbits(np.unpackbits(raw, axis=1, bitorder="little")[:, :width], bitorder="little")
    high = (rest[over] >> np.uint32(width)).astype("<u4") if width < 32 else np.zeros(0, "<u4")
    return head + raw.tobytes() + over.astype("<u2").tobytes() + high.tobytes()


def unpack_block(data: bytes, at: int) -> np.ndarray:
    n, width = int(np.frombuffer(data, "<u2", 1, at)[0]), data[at + 2]
    k, low = int(np.frombuffer(data, "<u2", 1, at + 3)[0]), int(np.frombuffer(data, "<u4", 1, at + 5)[0])
    at += 9
    size = (n * width + 7) // 8
    held = -(-width // 8)
    raw = np.frombuffer(data, np.uint8, size, at)
    if width % 8:
        full = np.zeros((n, 8 * held), np.uint8)
        full[:, :width] = np.unpackbits(raw, bitorder="little", count=n * width).reshape(n, width)
        raw = np.packbits(full, axis=1, bitorder="little")
    wide = np.zeros((n, 4), np.uint8)
    wide[:, :held] = raw.reshape(n, held)
    out = wide.view("<u4").ravel().astype(np.int64)
    at += size
    where = np.frombuffer(data, "<u2", k, at)
    out[where] |= np.frombuffer(data, "<u4", k, at + 2 * k).astype(np.int64) << width
    return (out + low).astype(np.uint32)


def pack(ids: np.ndarray) -> tuple[bytes, bytes]:
    """(index, payload) of any number of ids."""
    blocks = [pack_block(ids[a : a + BLOCK]) for a in range(0, len(ids), BLOCK)]
    starts = np.cumsum([0, *map(len, blocks)])[:-1] if blocks else np.zeros(0)
    return starts.astype("<u8").tobytes(), b"".join(blocks)


def unpack(index: bytes, payload: bytes, lo: int = 0, hi: int | None = None) -> np.ndarray:
    """Ids ``lo`` to ``hi`` of a segment; only the blocks that hold them are read."""
    starts = np.frombuffer(index, "<u8")
    first = lo // BLOCK
    last = len(starts) if hi is None else -(-hi // BLOCK)
    parts = [unpack_block(payload, int(s)) for s in starts[first:last]]
    out = np.concatenate(parts) if parts else np.zeros(0, np.uint32)
    return out[lo - first * BLOCK : None if hi is None else hi - first * BLOCK]


def cuts(raw: np.ndarray, first: np.ndarray) -> np.ndarray:
    """Bytes of UTF-8 texts, the first of each at ``first``, at which a piece of the library's split begins whatever stands around.

    These are: a space behind a visible character; ASCII punctuation (no apostrophe) or a line end behind an ASCII
    letter; a letter behind a line end that stands behind a visible character. Behind a character outside ASCII a
    space only counts if no Unicode white space ends in the same two bytes.
    """
    before = np.concatenate((np.zeros(1, np.uint8), raw[:-1]))
    second = np.concatenate((np.zeros(1, np.uint8), before[:-1]))
    kind = _KIND[raw]
    old = _KIND[before]
    visible = old >= 2
    wide = np.flatnonzero(old == 4)
    visible[wide] = ~(_TAIL_LAST[before[wide]] & _TAIL_SECOND[second[wide]])
    begin = ((raw == 0x20) & visible) | ((old == 3) & ((kind == 2) | (raw == 0x0A)))
    begin |= (kind == 3) & (before == 0x0A) & ((_KIND[second] == 2) | (_KIND[second] == 3))
    begin[first[first < len(raw)]] = True
    return np.flatnonzero(begin)


def _byte_kinds() -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Kind of a byte (0 white space or control, 1 apostrophe and digits, 2 punctuation, 3 ASCII letter, 4 beyond ASCII),
    and the last two bytes of Unicode white space beyond ASCII."""
    kind = np.zeros(256, np.uint8)
    for c in range(0x21, 0x7F):
        kind[c] = 3 if chr(c).isalpha() else 2
    kind[0x30:0x3A], kind[0x27], kind[0x80:] = 1, 1, 4
    last, second = np.zeros(256, bool), np.zeros(256, bool)
    for c in filter(str.isspace, map(chr, range(0x80, 0x3001))):
        last[c.encode()[-1]] = second[c.encode()[-2]] = True
    return kind, last, second


_KIND, _TAIL_LAST, _TAIL_SECOND = _byte_kinds()


class ChunkEncoder:
    """Encodes through the tokenizers library, in chunks cut where a piece of its split always begins.

    The chunks of a batch become codes of a dictionary (Arrow), so that each different one is looked at once. Those met
    in earlier batches are known by their ids; the others go to the library, many together. What is known is held in
    flat arrays, up to ``limit`` chunks and ``room`` bytes, and starts anew beyond.
    """

    def __init__(self, path: str, limit: int = 1 << 20, room: int = 24 << 20) -> None:
        from tokenizers import Tokenizer

        self.tokenizer = Tokenizer.from_file(path)
        self.tokenizer.encode_special_tokens = True
        self.limit, self.room = limit, room
        self.line_end = self.tokenizer.encode("\n", add_special_tokens=False).ids[0]
        self.forget()

    def forget(self) -> None:
        self.known, self.ids, self.size = pa.array([], pa.string()), np.zeros(0, "<u4"), np.zeros(0, np.int64)

    def fresh(self, chunks: list[str], together: int = 256) -> tuple[np.ndarray, np.ndarray]:
        """(ids of all chunks in a row, ids of each). Plain chunks go to the library many at a time with line ends
        between, which are always a token of their own there; chunks with other white space go one by one."""
        out: list = [None] * len(chunks)
        plain, odd = [], []
        for i, c in enumerate(chunks):
            bare = c[1:] if c[0] == " " else c
            (plain if bare and not bare[0].isspace() and not bare[-1].isspace() and "\n" not in bare else odd).append(i)
        groups = [plain[a : a + together] for a in range(0, len(plain), together)]
        for group, e in zip(groups, self.tokenizer.encode_batch_fast(["\n".join([chunks[i] for i in g]) for g in groups], add_special_tokens=False), strict=True):
            ids = np.array(e.ids, "<u4")
            cut = np.flatnonzero(ids == self.line_end)
            if len(cut) != len(group) - 1:
                odd += group
                continue
            ends = [*cut.tolist(), len(ids)]
            for i, a, b in zip(group, [0, *(x + 1 for x in ends[:-1])], ends, strict=True):
                out[i] = ids[a:b]
        for i, e in zip(odd, self.tokenizer.encode_batch_fast([chunks[i] for i in odd], add_special_tokens=False), strict=True):
            out[i] = np.array(e.ids, "<u4")
        return np.concatenate(out) if out else np.zeros(0, "<u4"), np.fromiter(map(len, out), np.int64, len(out))

    def encode(self, texts: pa.Array) -> list[np.ndarray]:
        """Ids of each text; null has none."""
        texts = pc.fill_null(texts.cast(pa.string()), "")
        ends = np.cumsum(pc.binary_length(texts).to_numpy(zero_copy_only=False), dtype=np.int64)
        first = np.concatenate((np.zeros(1, np.int64), ends[:-1])) if len(ends) else ends
        raw = np.frombuffer(b"".join(t.as_buffer() for t in texts), np.uint8)
        if not len(raw):
            return [np.zeros(0, "<u4")] * len(texts)
        at = cuts(raw, first)
        bounds = np.append(at, len(raw)).astype(np.int32)
        chunks = pa.StringArray.from_buffers(len(at), pa.py_buffer(bounds), pa.py_buffer(raw)).dictionary_encode()
        names = chunks.dictionary
        code = pc.index_in(names, value_set=self.known)
        new = names.filter(code.is_null())
        if len(self.known) + len(new) > self.limit or self.known.nbytes + new.nbytes > self.room:
            self.forget()
            code, new = pa.nulls(len(names), pa.int32()), names
        flat, size = self.fresh(new.to_pylist())
        base = len(self.known)
        self.known = pa.concat_arrays([self.known, new])
        self.ids, self.size = np.concatenate((self.ids, flat)), np.concatenate((self.size, size))
        code = code.to_numpy(zero_copy_only=False).astype(np.float64)
        gap = np.isnan(code)
        code[gap] = base + np.arange(int(gap.sum()))
        use = code.astype(np.int64)[chunks.indices.to_numpy()]
        start = np.cumsum(self.size) - self.size
        n = self.size[use]
        stop = np.cumsum(n)
        ids = self.ids[np.repeat(start[use] - (stop - n), n) + np.arange(int(stop[-1]))]
        of = np.concatenate((np.zeros(1, np.int64), stop))[np.searchsorted(at, np.append(first, len(raw)))]
        return [ids[a:b] for a, b in zip(of[:-1].tolist(), of[1:].tolist(), strict=True)]


@lru_cache(2)
def chunk_encoder(path: str) -> ChunkEncoder:
    return ChunkEncoder(path)


def _segments(path: str, end_id: int, ids_per_segment: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        import os

        os.environ["TOKENIZERS_PARALLELISM"] = "false"
        enc = chunk_encoder(path)
        task = TaskContext.get().partitionId()
        seq, before, held, keys, nulls = 0, 0, [], [], []

        def flush() -> pa.RecordBatch:
            nonlocal seq, before, held, keys, nulls
            ids = np.concatenate(held)
            index, payload = pack(ids)
            lens = np.array([len(x) for x in held], "<u4")
            row = [task, seq, before, len(ids), np.array(keys, "<i8").tobytes(), np.array(nulls, np.uint8).tobytes(), lens.tobytes(), index, payload]
            seq, before, held, keys, nulls = seq + 1, before + len(ids), [], [], []
            kinds = [pa.int32(), pa.int32(), pa.int64(), pa.int64(), *[pa.binary()] * 5]
            return pa.RecordBatch.from_arrays([pa.array([v], k) for v, k in zip(row, kinds, strict=True)], [f.split()[0] for f in SEGMENT_SCHEMA.split(", ")])

        size = 0
        for batch in batches:
            for part in slices(batch, 1, 8192, 4 << 20):
                for key, ids in zip(part.column(0).to_pylist(), enc.encode(part.column(1)), strict=True):
                    held.append(np.append(ids, np.uint32(end_id)))
                    keys.append(0 if key is None else key)
                    nulls.append(key is None)
                    size += len(ids) + 1
                    if size >= ids_per_segment:
                        yield flush()
                        size = 0
        if held:
            yield flush()

    return run


def write_tokens(docs: DataFrame, out: str, tokenizer: str, end_id: int = 0, ids_per_segment: int = 1 << 20) -> None:
    """Encode every text and write its ids, with ``end_id`` after each document, to ``out``."""
    rows = docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text").repartitionByRange("doc_id").sortWithinPartitions("doc_id", "text")
    rows.mapInArrow(frugal(_segments(tokenizer, end_id, ids_per_segment)), SEGMENT_SCHEMA).write.option("compression", "none").parquet(out)


def _documents(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        for r in batch.to_pylist():
            ids = unpack(r["index"], r["payload"]).astype("<u4")
            lens = np.frombuffer(r["doc_lens"], "<u4").astype(np.int64)
            ends = np.cumsum(lens)
            null = np.frombuffer(r["doc_null"], np.uint8).astype(bool)
            raw, first = ids.tobytes(), ends - lens
            crc = [zlib.crc32(raw[4 * a : 4 * b]) for a, b in zip(first.tolist(), ends.tolist(), strict=True)]
            keys = pa.array(np.frombuffer(r["doc_ids"], "<i8"), pa.int64(), mask=null)
            yield pa.RecordBatch.from_arrays([keys, pa.array(r["base"] + r["ids_before"] + first, pa.int64()), pa.array(lens, pa.int64()), pa.array(crc, pa.int64())], ["doc_id", "start", "n_tokens", "ids_crc32"])


def segments(spark: SparkSession, path: str) -> DataFrame:
    """Segments with ``base``, the ids of all earlier tasks; the window runs over one row a task."""
    read = spark.read.schema(SEGMENT_SCHEMA).parquet(path)
    per = read.groupBy("task").agg(F.sum("n_ids").alias("n"))
    before = Window.orderBy("task").rowsBetween(Window.unboundedPreceding, -1)
    base = per.select("task", F.coalesce(F.sum("n").over(before), F.lit(0)).cast("long").alias("base"))
    return read.join(F.broadcast(base), "task")


def read_documents(spark: SparkSession, path: str) -> DataFrame:
    """(doc_id, start, n_tokens, ids_crc32) of each document, from the files alone."""
    return segments(spark, path).select("base", "ids_before", "doc_ids", "doc_null", "doc_lens", "index", "payload").mapInArrow(frugal(_documents), "doc_id long, start long, n_tokens long, ids_crc32 long")


def tokenizer_file() -> str:
    import public_tokenizers

    return public_tokenizers.path("byte_bpe_50k.json")


def op3_tokens(spark: SparkSession, sf_dir: str) -> DataFrame:
    out = scratch(spark, "tokens")
    write_tokens(table(spark, sf_dir, "documents"), out, tokenizer_file())
    return read_documents(spark, out)
