"""Sources: the given tables, edges in other formats, JSON payloads and HTML links; sinks for edges."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..model.graph import EDGE


def load(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def read_edges(spark: SparkSession, fmt: str, path: str, mapping: dict[str, str] | None = None, schema: str = "s string, p string, o string, ts timestamp_ntz, te timestamp_ntz", **options) -> DataFrame:
    """Edges from CSV, JSON, ORC or Parquet; ``mapping`` names the source column of each edge column."""
    reader = spark.read.options(**options)
    df = (reader if fmt in ("parquet", "orc") else reader.schema(schema)).format(fmt).load(path)
    m = mapping or {c: c for c in EDGE}
    return df.select(*[F.col(m[c]).alias(c) for c in EDGE])


def with_layout(edges: DataFrame, labels: int = 64) -> DataFrame:
    """Adds what files are pruned by: a hash class of the label, the month of the start and the class of the length."""
    long_ = F.col("ts").cast("timestamp")
    width = F.unix_micros(F.col("te").cast("timestamp")) - F.unix_micros(long_)
    return edges.withColumns({"label_class": F.pmod(F.xxhash64("p"), F.lit(labels)).cast("int"), "month": F.date_format("ts", "yyyy-MM"), "length_class": F.floor(F.log2(width.cast("double"))).cast("int")})


def write_edges(edges: DataFrame, path: str, labels: int = 64) -> None:
    """Partitioned by label class and month, sorted by (p, s, o, ts) within files."""
    laid = with_layout(edges, labels)
    laid.repartition("label_class", "month").sortWithinPartitions("p", "s", "o", "ts").write.partitionBy("label_class", "month").parquet(path)


def save_bucketed(edges: DataFrame, table: str, by: str, buckets: int = 64) -> None:
    """A catalogue table clustered by one node column, for joins without a shuffle."""
    edges.write.bucketBy(buckets, by).sortBy(by, "ts").format("parquet").saveAsTable(table)


def stops(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Consecutive stops of each user: the stop and the next one come from the events' JSON payload."""
    from pyspark.sql import Window

    w = Window.partitionBy("user_id").orderBy("ts", "event_id")
    k = F.get_json_object("props", "$.k").cast("int")
    e = load(spark, sf_dir, "events").withColumn("k", k)
    return e.withColumn("nk", F.lead("k").over(w)).withColumn("nts", F.lead("ts").over(w)).filter("nts IS NOT NULL")


def page_links(spark: SparkSession, sf_dir: str) -> DataFrame:
    links = F.regexp_extract_all("html", F.lit('href="([^"]*)"'), F.lit(1))
    return load(spark, sf_dir, "pages").select("page_id", F.explode(links).alias("target"))
