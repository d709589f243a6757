"""Language identification by interpolated Kneser-Ney character models in sorted hash arrays.

For each language the 4-grams of its words (padded by word boundaries) are counted over all training documents:
tasks count words, turn them into packed 4-grams (16 bits a character, beyond the basic plane hashed to 16) and
emit partial sums, which Spark adds up. From the 4-gram counts follow all continuation counts of the lower
orders. A model is a set of sorted key arrays with log-probabilities and back-off weights, read by binary
search. A text goes to the language of lowest cross-entropy per character; it is rejected when that lies
further above the language's own training entropy than its allowance: what the law of large numbers gives a text of its
length, and what the worst of the training texts of that language needed beyond, all of which are scored for it,
with a margin of half the spread of a character's information.

The model holds one entry for each distinct 4-gram of a language. Its size is checked before it is gathered: above
``max_entries`` rows it stays a set of tables, from which the same probabilities are joined to the distinct
4-grams of the texts and added up a text. The order is the same at every size.

Defined results: null texts and texts without a letter are ``und`` with score 0; a null doc_id is never trained on
and is not held out; null languages are never learned; no training rows make every text ``und``; ties go to
the language that sorts first; repeated rows count each time and get equal results; extra columns are ignored.
"""

from __future__ import annotations

import math
import re
from collections import Counter
from collections.abc import Iterator
from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import frugal, slices, stored, table

WORDS = re.compile(r"[^\W\d_]+")
EDGE = 0x20
DISCOUNT = 0.75
UNKNOWN = "und"
#: Deviations of the mean of a text's characters that its length explains, and the margin beyond the worst training text, in spreads of a character.
NOISE, MARGIN = 6.0, 0.5


def packed_grams(words: list[str], order: int) -> tuple[np.ndarray, np.ndarray]:
    """(keys, counts of grams a word): each word's characters and closing boundary, each behind order - 1 earlier ones."""
    text = "".join([" " * (order - 1) + w + " " for w in words])
    cp = np.frombuffer(text.encode("utf-32-le"), np.uint32).astype(np.uint64)
    cp = np.where(cp > 0xFFFF, (cp * np.uint64(40503)) & np.uint64(0xFFFF), cp)
    size = np.fromiter(map(len, words), np.int64, len(words)) + 1
    key = np.zeros(max(0, len(cp) - order + 1), np.uint64)
    for i in range(order):
        key = (key << np.uint64(16)) | cp[i : i + len(key)]
    at = np.arange(size.sum()) + np.repeat((order - 1) * np.arange(len(words)), size)  # the paddings' own positions are skipped
    return key[at], size


@dataclass
class Level:
    """Interpolated probabilities of one order: log-free values by key, back-off weight by context."""

    keys: np.ndarray
    mass: np.ndarray
    contexts: np.ndarray
    backoff: np.ndarray


def _level(keys: np.ndarray, counts: np.ndarray) -> Level:
    order = np.argsort(keys)
    keys, counts = keys[order], counts[order].astype(np.float64)
    ctx, first, kinds = np.unique(keys >> np.uint64(16), return_index=True, return_counts=True)
    total = np.add.reduceat(counts, first)
    return Level(keys, np.maximum(counts - DISCOUNT, 0) / np.repeat(total, kinds), ctx, DISCOUNT * kinds / total)


class Model:
    """One language's Kneser-Ney model."""

    def __init__(self, keys: np.ndarray, counts: np.ndarray, order: int) -> None:
        self.order, self.levels = order, []
        mask = np.uint64((1 << (16 * (order - 1))) - 1) if order > 1 else np.uint64(0)
        k, c = keys, counts
        for n in range(order, 0, -1):
            self.levels.append(_level(k, c))
            if n > 1:
                mask = np.uint64((1 << (16 * (n - 1))) - 1)
                k, c = np.unique(k & mask, return_counts=True)
        self.floor = 1.0 / (len(self.levels[-1].keys) + 1)
        own = -np.log(self.probability(keys))
        w = counts / counts.sum()
        self.entropy = float((w * own).sum())
        self.spread = float(math.sqrt(max(0.0, (w * (own - self.entropy) ** 2).sum())))
        self.worst = 0.0

    def probability(self, keys: np.ndarray) -> np.ndarray:
        p = np.full(len(keys), self.floor)
        for n, level in zip(range(1, self.order + 1), reversed(self.levels), strict=True):
            part = keys & np.uint64((1 << (16 * n)) - 1) if n < 4 else keys
            i = np.minimum(np.searchsorted(level.keys, part), len(level.keys) - 1)
            mass = np.where(level.keys[i] == part, level.mass[i], 0.0)
            ctx = part >> np.uint64(16)
            j = np.minimum(np.searchsorted(level.contexts, ctx), len(level.contexts) - 1)
            weight = np.where(level.contexts[j] == ctx, level.backoff[j], 1.0)
            p = mass + weight * p
        return p


class Scorer:
    """Cross-entropy of words under every model, with words met before kept (emptied when full)."""

    def __init__(self, models: dict[str, Model], limit: int = 1 << 17) -> None:
        self.names, self.models, self.limit = sorted(models), models, limit
        self.order = next(iter(models.values())).order if models else 1
        self.place: dict[str, int] = {}
        self.bits = np.zeros((0, len(self.names)), np.float32)
        self.sizes = np.zeros(0, np.int32)

    def add(self, words: list[str]) -> None:
        if len(self.place) + len(words) > self.limit:
            self.place = {}
            self.bits, self.sizes = self.bits[:0], self.sizes[:0]
        keys, size = packed_grams(words, self.order)
        start = np.cumsum(size) - size
        grams, of = np.unique(keys, return_inverse=True)  # far fewer than there are, so each is looked up once
        cols = [np.add.reduceat(-np.log(self.models[n].probability(grams))[of], start) for n in self.names]
        at = len(self.place)
        self.place.update(zip(words, range(at, at + len(words)), strict=True))
        self.bits = np.concatenate((self.bits, np.stack(cols, 1).astype(np.float32)))
        self.sizes = np.concatenate((self.sizes, size.astype(np.int32)))

    def score(self, texts: list[str | None]) -> tuple[list[str], list[float], list[bool], list[float]]:
        """(language, score, rejected, entropy above what its length explains) of each text."""
        cut = [WORDS.findall(t.lower()) if t else [] for t in texts]
        cut = [[w for w in ws if w.isascii() or any(map(str.isalpha, w))] for ws in cut]
        fresh = list(dict.fromkeys(w for ws in cut for w in ws if w not in self.place))
        if fresh and self.models:
            if len(self.place) + len(fresh) > self.limit:
                fresh = list(dict.fromkeys(w for ws in cut for w in ws))
            self.add(fresh)
        out: tuple[list, list, list, list] = ([], [], [], [])
        for ws in cut:
            if not ws or not self.names:
                for o, v in zip(out, (UNKNOWN, 0.0, True, 0.0), strict=True):
                    o.append(v)
                continue
            at = np.fromiter(map(self.place.__getitem__, ws), np.int64, len(ws))
            n = int(self.sizes[at].sum())
            h = self.bits[at].sum(0, dtype=np.float64) / n
            best = int(h.argmin())
            m = self.models[self.names[best]]
            odds = np.exp(-(h - h[best]) * min(n, 200))
            above = float(h[best] - m.entropy - NOISE * m.spread / math.sqrt(n))
            far = above > m.worst + MARGIN * m.spread
            for o, v in zip(out, (self.names[best], float(1 / odds.sum()), bool(far), above), strict=True):
                o.append(v)
        return out


def _counts(order: int, flush: int = 1 << 16):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: dict[str, Counter] = {}

        def emit() -> Iterator[pa.RecordBatch]:
            for lang, words in held.items():
                if not words:
                    continue
                names = list(words)
                keys, size = packed_grams(names, order)
                weight = np.repeat(np.fromiter(words.values(), np.int64, len(names)), size)
                k, inv = np.unique(keys, return_inverse=True)
                n = np.bincount(inv, weight).astype(np.int64)
                yield pa.RecordBatch.from_arrays([pa.array([lang] * len(k)), pa.array(k.view(np.int64)), pa.array(n)], ["lang", "gram", "n"])
            held.clear()

        for batch in batches:
            for part in slices(batch, 1):
                for lang, text in zip(part.column(0).to_pylist(), part.column(1).to_pylist(), strict=True):
                    held.setdefault(lang, Counter()).update(WORDS.findall(text.lower()))
                if sum(map(len, held.values())) > flush:
                    yield from emit()
        yield from emit()

    return run


@dataclass
class ModelTables:
    """The models of all languages as one table (lang, gram, n) of their 4-gram counts."""

    counts: DataFrame
    order: int
    worst: dict[str, float] = field(default_factory=dict)


def train(docs: DataFrame, order: int = 4, max_entries: int = 8_000_000) -> dict[str, Model] | ModelTables:
    """A model for each non-null ``lang`` of the rows; counts and rejection thresholds are over all of them. Too large a model stays in tables."""
    models = _fitted(docs, order, max_entries)
    rows = docs.select("lang", "text").filter("lang is not null and text is not null")
    told = predict(rows, models, ["lang"]).filter("lang = lang_pred")
    worst = {r["lang"]: r["w"] for r in told.groupBy("lang").agg(F.max("above").alias("w")).collect()}
    if isinstance(models, ModelTables):
        models.worst = worst
    else:
        for name, m in models.items():
            m.worst = max(0.0, worst.get(name, 0.0))
    return models


def _fitted(docs: DataFrame, order: int, max_entries: int) -> dict[str, Model] | ModelTables:
    rows = docs.select("lang", "text").filter("lang is not null and text is not null")
    counts = rows.mapInArrow(frugal(_counts(order)), "lang string, gram long, n long").groupBy("lang", "gram").agg(F.sum("n").alias("n"))
    counts = stored(counts, "lang-grams")
    if counts.count() > max_entries:
        return ModelTables(counts, order)
    got = counts.toArrow()
    names, code = np.unique(np.array(got["lang"].to_pylist(), dtype=object).astype(str), return_inverse=True) if got.num_rows else ([], np.zeros(0))
    keys, n = got["gram"].to_numpy().view(np.uint64), got["n"].to_numpy()
    return {str(name): Model(keys[code == i], n[code == i], order) for i, name in enumerate(names)}


def _text_grams(order: int):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for i, text in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), strict=True):
                words = [w for w in WORDS.findall(text.lower()) if w.isascii() or any(map(str.isalpha, w))] if text else []
                if words:
                    k, n = np.unique(packed_grams(words, order)[0], return_counts=True)
                    yield pa.RecordBatch.from_arrays([pa.array([i] * len(k), pa.int64()), pa.array(k.view(np.int64)), pa.array(n.astype(np.int64))], ["id", "gram", "n"])

    return run


def _by_key(rows: DataFrame, key: str, value: Column, name: str) -> DataFrame:
    """One row a key, with a map from language number to value."""
    return rows.groupBy(F.col(key).alias(f"__{name}")).agg(F.map_from_entries(F.collect_list(F.struct("i", value))).alias(name))


def _probabilities(counts: DataFrame, grams: DataFrame, order: int, size: int) -> DataFrame:
    """(gram, p) of each gram, ``p`` an array with one probability a language; as ``Model.probability``."""
    levels, level = {}, counts
    for n in range(order, 0, -1):
        levels[n] = level = stored(level, f"lang-level-{n}")
        if n > 1:
            level = level.select("i", F.col("gram").bitwiseAND(F.lit((1 << (16 * (n - 1))) - 1)).alias("gram")).groupBy("i", "gram").agg(F.count(F.lit(1)).alias("n"))
    kinds = {r["i"]: r["n"] for r in levels[1].groupBy("i").agg(F.count(F.lit(1)).alias("n")).collect()}
    out = grams.withColumn("p", F.array(*[F.lit(1.0 / (kinds[i] + 1)) for i in range(size)]))
    for n in range(1, order + 1):
        level = levels[n].withColumn("ctx", F.shiftrightunsigned("gram", 16))
        ctx = level.groupBy("i", "ctx").agg(F.sum("n").alias("total"), F.count(F.lit(1)).alias("kinds"))
        mass = level.join(ctx, ["i", "ctx"]).withColumn("m", F.greatest(F.col("n") - DISCOUNT, F.lit(0.0)) / F.col("total"))
        mass, back = _by_key(mass, "gram", F.col("m"), "mass"), _by_key(ctx, "ctx", F.col("kinds") * DISCOUNT / F.col("total"), "back")
        part = F.col("gram").bitwiseAND(F.lit((1 << (16 * n)) - 1)) if n < 4 else F.col("gram")
        out = out.withColumn("part", part).withColumn("ctx", F.shiftrightunsigned("part", 16))
        out = out.join(mass, F.col("part") == F.col("__mass"), "left").join(back, F.col("ctx") == F.col("__back"), "left")
        step = F.transform("p", lambda p, i: F.coalesce(F.col("mass")[i], F.lit(0.0)) + F.coalesce(F.col("back")[i], F.lit(1.0)) * p)
        out = stored(out.select("gram", step.alias("p")), "lang-probability")
    return out


def _predict_joined(docs: DataFrame, models: ModelTables, keep: list[str]) -> DataFrame:
    """As ``predict``, with models and texts joined on their grams; one row a language reaches the driver."""
    spark = docs.sparkSession
    names = sorted(r["lang"] for r in models.counts.select("lang").distinct().collect())
    number = spark.createDataFrame(list(enumerate(names)), "i int, lang string")
    counts = models.counts.join(F.broadcast(number), "lang").select("i", "gram", "n")
    held = stored(docs.select(*keep, F.col("text").alias("__text"), F.monotonically_increasing_id().alias("__id")), "lang-texts")
    grams = stored(held.select("__id", "__text").mapInArrow(frugal(_text_grams(models.order)), "id long, gram long, n long"), "lang-text-grams")
    p = _probabilities(counts, grams.select("gram").union(counts.select("gram")).distinct(), models.order, len(names))
    own = counts.join(p, "gram").select("i", "n", (-F.log(F.col("p")[F.col("i")])).alias("h"))
    mean = own.groupBy("i").agg((F.sum(F.col("n") * F.col("h")) / F.sum("n")).alias("mean"))
    off = own.join(F.broadcast(mean), "i").groupBy("i").agg(F.first("mean").alias("mean"), F.sqrt(F.sum(F.col("n") * (F.col("h") - F.col("mean")) ** 2) / F.sum("n")).alias("spread"))
    fit = {r["i"]: (r["mean"], r["spread"]) for r in off.collect()}
    sums = grams.join(p, "gram").groupBy("id").agg(F.sum("n").alias("__n"), *[F.sum(-F.log(F.col("p")[i]) * F.col("n")).alias(f"__{i}") for i in range(len(names))])
    sums = sums.select("id", "__n", F.array(*[F.col(f"__{i}") / F.col("__n") for i in range(len(names))]).alias("__h"))
    sums = sums.withColumn("__low", F.array_min("__h")).withColumn("__best", F.array_position("__h", F.col("__low")).cast("int") - 1)
    of = lambda values: F.array(*[F.lit(v) for v in values])[F.col("__best")]
    odds = F.aggregate("__h", F.lit(0.0), lambda a, h: a + F.exp(-(h - F.col("__low")) * F.least("__n", F.lit(200))))
    spread = of([fit[i][1] for i in range(len(names))])
    above = F.col("__low") - of([fit[i][0] for i in range(len(names))]) - NOISE * spread / F.sqrt("__n")
    far = above > of([max(0.0, models.worst.get(n, 0.0)) for n in names]) + MARGIN * spread
    got = sums.select("id", of(names).alias("__lang"), (1 / odds).alias("__score"), far.alias("__far"), above.alias("__above"))
    rows = held.join(got, F.col("__id") == F.col("id"), "left")
    return rows.select(*[held[c] for c in keep], F.coalesce("__lang", F.lit(UNKNOWN)).alias("lang_pred"), F.coalesce("__score", F.lit(0.0)).alias("score"), F.coalesce("__far", F.lit(True)).alias("rejected"), F.coalesce("__above", F.lit(0.0)).alias("above"))


def predict(docs: DataFrame, models: dict[str, Model] | ModelTables, keep: list[str]) -> DataFrame:
    """``keep`` columns with lang_pred, score, rejected and ``above`` (entropy beyond what the length explains), from the text alone."""
    if isinstance(models, ModelTables):
        return _predict_joined(docs, models, keep)
    shared = docs.sparkSession.sparkContext.broadcast(models)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        scorer = Scorer(shared.value)
        for batch in batches:
            for part in slices(batch, len(keep)):
                lang, score, far, above = scorer.score(part.column(len(keep)).to_pylist())
                yield pa.RecordBatch.from_arrays([*part.columns[: len(keep)], pa.array(lang, pa.string()), pa.array(score, pa.float64()), pa.array(far, pa.bool_()), pa.array(above, pa.float64())], [*keep, "lang_pred", "score", "rejected", "above"])

    fields = ", ".join(f"`{f.name}` {f.dataType.simpleString()}" for f in docs.select(*keep).schema)
    return docs.select(*keep, F.col("text").alias("__text")).mapInArrow(frugal(run), f"{fields}, lang_pred string, score double, rejected boolean, above double")


def fold() -> tuple:
    """(training row, held-out row) conditions by crc32 of the id as text."""
    r = F.crc32(F.col("doc_id").cast("string").cast("binary")) % 4
    return F.coalesce(r != 2, F.lit(False)), F.coalesce(r == 2, F.lit(False))


def op7_language(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = table(spark, sf_dir, "documents")
    learn, out = fold()
    return predict(docs.withColumn("held_out", out), train(docs.filter(learn)), ["doc_id", "held_out"]).select("doc_id", "held_out", "lang_pred", "score", "rejected")
