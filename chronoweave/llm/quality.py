"""Quality rules with adaptive thresholds from mergeable quantile sketches; DataFrame operations only.

Base rules look at each text alone. The adaptive rules compare a document with its own language and source:
quartiles of four ratios come from Spark's mergeable quantile summaries (``percentile_approx``, merged over
partial aggregates), give outer fences for each (lang, source), and the documents are filtered by a join with
those fences. Only what lies far outside its group's spread fails, so a clean group loses nothing.

Defined results: a null or blank text has no words and fails the base rule; a very long text is measured whole, in time
that grows with its length like a sort; null languages and sources are groups of their own; a value that ties with its
fence stays; repeated rows are judged alike; an empty table stays empty; extra columns are ignored.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import ASCII_SPACE, WORD, stored, table

SYMBOLS = "#*$%&|<>"
RATIOS = ("symbol_ratio", "dup_line_ratio", "repeat_ratio", "word_length")


def text_measures(docs: DataFrame) -> DataFrame:
    """Columns n_words, word_chars, n_symbols, n_dup_lines, n_repeat_words for each row; other columns stay.

    Repeated 3-word windows: windows are hashed to 64 bits; most texts repeat none, which a distinct count shows.
    For the rest, hashes are sorted together with their places, equal neighbours are kept, and the union of their
    3-word ranges is measured over the sorted places.
    """
    text = F.coalesce(F.col("text"), F.lit(""))
    bare = F.translate(text, ASCII_SPACE, "")
    lines = F.filter(F.split(text, "\n"), lambda x: x.rlike(WORD))
    out = docs.withColumn("__w", F.filter(F.split(text, r"[\x20\x09-\x0D]+"), lambda x: x != ""))
    out = out.withColumn("n_words", F.size("__w").cast("long")).withColumn("word_chars", F.length(bare).cast("long"))
    out = out.withColumn("n_symbols", (F.length(bare) - F.length(F.translate(bare, SYMBOLS, ""))).cast("long"))
    out = out.withColumn("__l", lines).withColumn("n_dup_lines", (F.size("__l") - F.size(F.array_distinct("__l"))).cast("long")).drop("__l")
    out = out.withColumn("__h", F.expr("IF(n_words < 4, array(), transform(sequence(0, CAST(n_words AS INT) - 3), i -> xxhash64(__w[i], __w[i + 1], __w[i + 2])))")).drop("__w")
    # places of repeated windows: hashes are sorted together with their places, and equal ones stand side by side
    out = out.withColumn("__s", F.expr("IF(size(array_distinct(__h)) = size(__h), CAST(array() AS ARRAY<STRUCT<h: BIGINT, i: INT>>), sort_array(transform(__h, (h, i) -> struct(h AS h, i AS i))))"))
    same = "(i > 0 AND x.h = __s[i - 1].h) OR (i + 1 < size(__s) AND x.h = __s[i + 1].h)"
    out = out.withColumn("__p", F.expr(f"sort_array(transform(filter(__s, (x, i) -> {same}), x -> x.i))"))
    out = out.withColumn("n_repeat_words", F.expr("CAST(IF(size(__p) = 0, 0, 3 + aggregate(sequence(1, size(__p)), 0, (a, i) -> a + IF(i < size(__p), least(3, __p[i] - __p[i - 1]), 0))) AS LONG)"))
    return out.drop("__h", "__s", "__p")


def fences(measured: DataFrame, accuracy: int = 10_000, reach: float = 6.0, floors: tuple[float, ...] = (0.10, 0.50, 0.35, 3.0)) -> DataFrame:
    """One row a (lang, source): for each ratio the upper outer fence q3 + max(reach * IQR, floor)."""
    quart = [F.percentile_approx(r, [0.25, 0.75], accuracy).alias(r) for r in RATIOS]
    q = measured.groupBy("lang", "source").agg(*quart)
    high = [(F.col(r)[1] + F.greatest(reach * (F.col(r)[1] - F.col(r)[0]), F.lit(f))).alias(f"hi_{r}") for r, f in zip(RATIOS, floors, strict=True)]
    low = (F.col("word_length")[0] - F.greatest(reach * (F.col("word_length")[1] - F.col("word_length")[0]), F.lit(floors[3]))).alias("lo_word_length")
    return q.select(F.col("lang").alias("g_lang"), F.col("source").alias("g_source"), *high, low)


def judge(docs: DataFrame) -> DataFrame:
    """Measures, base_failed and kept for each document."""
    ids = [c for c in ("doc_id", "lang", "source") if c in docs.columns]
    m = text_measures(docs.select(*ids, "text")).drop("text")
    n = F.greatest("n_words", F.lit(1))
    m = m.withColumns({"symbol_ratio": F.col("n_symbols") / F.greatest("word_chars", F.lit(1)), "dup_line_ratio": F.col("n_dup_lines") / n * 10, "repeat_ratio": F.col("n_repeat_words") / n, "word_length": F.col("word_chars") / n})
    m = m.withColumn("base_failed", (F.col("n_words") < 50) | (100 * F.col("n_repeat_words") > 50 * F.col("n_words")))
    m = stored(m, "quality-measures")
    f = fences(m.filter(~F.col("base_failed")))
    inside = F.lit(True)
    for r in RATIOS:
        inside = inside & (F.col(r) <= F.coalesce(F.col(f"hi_{r}"), F.lit(float("inf"))))
    inside = inside & (F.col("word_length") >= F.coalesce(F.col("lo_word_length"), F.lit(0.0)))
    out = m.join(f, m["lang"].eqNullSafe(f["g_lang"]) & m["source"].eqNullSafe(f["g_source"]), "left")
    return out.withColumn("kept", ~F.col("base_failed") & inside).drop(*[c for c in f.columns])


def op9_quality(spark: SparkSession, sf_dir: str) -> DataFrame:
    return judge(table(spark, sf_dir, "documents")).select("doc_id", "n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "base_failed", "kept")


#: The contract's figures by unnested windows and lines, and the fences from discrete quantiles.
OP9_SQL = r"""
WITH d AS (SELECT row_number() OVER () AS r, doc_id, lang, source, coalesce(text, '') AS text, regexp_extract_all(coalesce(text, ''), '[^\x20\x09-\x0D]+') AS w FROM documents),
g AS (SELECT r, i, w[i] AS a, w[i + 1] AS b, w[i + 2] AS c FROM (SELECT r, w, unnest(range(1, len(w) - 1)) AS i FROM d WHERE len(w) >= 3)),
twice AS (SELECT r, i FROM (SELECT *, count(*) OVER (PARTITION BY r, a, b, c) AS k FROM g) WHERE k > 1),
rep AS (SELECT r, count(DISTINCT i + j) AS n FROM twice, (SELECT unnest([0, 1, 2]) AS j) GROUP BY r),
ln AS (SELECT r, count(*) - count(DISTINCT line) AS n FROM (SELECT r, unnest(string_split(text, chr(10))) AS line FROM d) WHERE regexp_matches(line, '[^\x20\x09-\x0D]') GROUP BY r),
m AS (SELECT doc_id, lang, source, CAST(len(w) AS BIGINT) AS n_words, CAST(length(regexp_replace(text, '[\x20\x09-\x0D]+', '', 'g')) AS BIGINT) AS word_chars,
      CAST(length(regexp_replace(text, '[^#*$%&|<>]+', '', 'g')) AS BIGINT) AS n_symbols, coalesce(ln.n, 0) AS n_dup_lines, coalesce(rep.n, 0) AS n_repeat_words FROM d LEFT JOIN rep USING (r) LEFT JOIN ln USING (r)),
x AS (SELECT *, n_words < 50 OR 100 * n_repeat_words > 50 * n_words AS base_failed, n_symbols / greatest(word_chars, 1) AS r0, n_dup_lines / greatest(n_words, 1) * 10 AS r1,
      n_repeat_words / greatest(n_words, 1) AS r2, word_chars / greatest(n_words, 1) AS r3 FROM m),
q AS (SELECT lang, source, quantile_disc(r0, [0.25, 0.75]) AS q0, quantile_disc(r1, [0.25, 0.75]) AS q1, quantile_disc(r2, [0.25, 0.75]) AS q2, quantile_disc(r3, [0.25, 0.75]) AS q3 FROM x WHERE NOT base_failed GROUP BY lang, source),
f AS (SELECT lang, source, q0[2] + greatest(6 * (q0[2] - q0[1]), 0.10) AS h0, q1[2] + greatest(6 * (q1[2] - q1[1]), 0.50) AS h1, q2[2] + greatest(6 * (q2[2] - q2[1]), 0.35) AS h2,
      q3[2] + greatest(6 * (q3[2] - q3[1]), 3.0) AS h3, q3[1] - greatest(6 * (q3[2] - q3[1]), 3.0) AS l3 FROM q)
SELECT doc_id, n_words, word_chars, n_symbols, n_dup_lines, n_repeat_words, base_failed,
       NOT base_failed AND coalesce(r0 <= h0 AND r1 <= h1 AND r2 <= h2 AND r3 <= h3 AND r3 >= l3, TRUE) AS kept
FROM x LEFT JOIN f ON x.lang IS NOT DISTINCT FROM f.lang AND x.source IS NOT DISTINCT FROM f.source
"""
