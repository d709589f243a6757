"""A corpus pipeline: language ID, near-duplicates, personal data, mixing, byte-level BPE."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from chronoweave import ship
from chronoweave.llm import bpe, langid, mixing, neardup, pii
from chronoweave.llm.common import identified, scratch, stored

COLUMNS = ["doc_id", "text", "lang", "source", "n_chars"]


def columns(docs: DataFrame) -> list[str]:
    return [c for c in COLUMNS if c in docs.columns]


def language(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Drops documents that the language models reject; trained on the labelled rows of the stage's own input.

    Texts that are null or have no letter are rejected; rows are judged one by one, whatever their ids; equal rows get equal verdicts.
    """
    ship(spark)
    rows = langid.predict(docs, langid.train(docs), columns(docs))
    return rows.filter("NOT rejected").select(*columns(docs))


def near_duplicates(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Keeps one document, the one of least doc_id, of each group of near copies (five words, similarity 0.8).

    Null, empty and blank texts have no copies and stay. Where doc_ids are null or repeated, rows are judged by their
    place in the table instead, so each row is a document of its own and the first of a group stays, equal rows included.
    """
    ship(spark)
    rows = identified(docs.select(*columns(docs)))
    told = neardup.near_duplicates(rows.select(F.col("__row").alias("doc_id"), "text"))
    gone = told.filter("NOT kept").select(F.col("doc_id").alias("__row"))
    return rows.join(gone, "__row", "left_anti").select(*columns(docs))


def personal_data(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Replaces personal data by the name of its kind; no document goes, null and empty texts stay as they are."""
    clean = pii.redact(docs.select(*columns(docs)))
    return clean.withColumn("n_chars", F.length("text").cast("long")).select(*columns(docs))


def mixture(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Repeats each document as often as the mix reads it; a partly read one gives its first words as read.

    A document without a word is read by no slot and goes, as does one beyond its source's target. Null and repeated
    doc_ids, equal rows and null sources are mixed like others.
    """
    rows = identified(docs.select(*columns(docs)))
    taken = stored(mixing.mix(rows.select(F.col("__row").alias("row"), "doc_id", "source", "text"))[0].filter("taken > 0").select("row", "size", "taken"), "pipeline-mix")
    turns = F.sequence(F.lit(1), F.ceil(F.col("taken") / F.col("size")).cast("int"))
    words = F.transform(turns, lambda i: F.least(F.col("size"), F.col("taken") - (i - 1) * F.col("size")))
    plan = taken.select("row", "size", F.explode(words).alias("words"))
    both = rows.join(plan, rows["__row"] == plan["row"])
    text = F.when(F.col("words") >= F.col("size"), F.col("text")).otherwise(mixing.first_words(F.col("text"), F.col("words").cast("int")))
    return both.withColumn("text", text).withColumn("n_chars", F.length("text").cast("long")).select(*columns(docs))


def tokens(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Token ids of each text by the public byte-level vocabulary, with digests of ids and of the decoded bytes; a null text has none. One row for each row."""
    ship(spark)
    return bpe.digests(docs, bpe.rank_file())


STAGES = [("language", language), ("near_duplicates", near_duplicates), ("personal_data", personal_data), ("mixture", mixture), ("tokens", tokens)]
ORACLE_SQL = None


def run(spark: SparkSession, sf_dir: str) -> DataFrame:
    """All stages over ``documents``, each written as Parquet and read again."""
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    for name, stage in STAGES[:-1]:
        path = scratch(spark, f"stage-{name}")
        stage(spark, docs, sf_dir).write.parquet(path)
        docs = spark.read.parquet(path)
    return STAGES[-1][1](spark, docs, sf_dir)
