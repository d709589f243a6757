import corpus_pipeline as pipeline

SCHEMA = "doc_id long, text string, lang string, source string, n_chars long, clash int"


def test_mixture_repeats_and_cuts_whole_rows(spark):
    long = " ".join(f"v{i}" for i in range(20_000))
    rows = [(None, "one two three", "en", "a", 13, 1), (1, "four five", "en", None, 9, 1), (1, "four five", "en", None, 9, 1), (1, "six", "en", "a", 3, 1), (2, None, "en", "a", 0, 1), (3, " \n", None, "a", 2, 1), (4, long, "en", "c", len(long), 1)]
    docs = spark.createDataFrame(rows, SCHEMA)
    out = pipeline.mixture(spark, docs, "").collect()
    words = {}
    for r in out:
        assert r["n_chars"] == len(r["text"])
        words[r["source"]] = words.get(r["source"], 0) + len(r["text"].split())
        assert any((t or "").startswith(r["text"]) for _, t, *_ in rows)
    sizes = {"a": 4, "c": 20_000, None: 4}
    targets = {"a": 8, None: 8}
    targets["c"] = 1.5 * 20_008 - 16
    assert sizes.keys() == words.keys()
    for s, t in targets.items():
        assert abs(words[s] - t) <= 1
    partly = [r for r in out if r["source"] == "c" and len(r["text"].split()) < 20_000]
    assert len(partly) == 1 and long.startswith(partly[0]["text"])
    assert {r["doc_id"] for r in out} == {None, 1, 4}
    assert pipeline.mixture(spark, spark.createDataFrame([], SCHEMA), "").count() == 0


def test_near_duplicates_keep_one_row_of_each_group_whatever_the_ids(spark):
    text = " ".join(f"w{i}" for i in range(60))
    other = " ".join(f"z{i}" for i in range(60))
    rows = [(1, text, "en", "a", 0, 1), (1, other, "en", "a", 0, 1), (2, text, "en", "a", 0, 1), (None, other + " end", "en", "a", 0, 1), (None, None, "en", "a", 0, 1), (5, "", "en", "a", 0, 1), (1, text, "en", "a", 0, 1)]
    out = pipeline.near_duplicates(spark, spark.createDataFrame(rows, SCHEMA), "").collect()
    assert sorted((r["text"] or "")[:2] for r in out) == ["", "", "w0", "z0"]
    unique = [(i, *r[1:]) for i, r in enumerate(rows)]
    out = pipeline.near_duplicates(spark, spark.createDataFrame(unique, SCHEMA), "").collect()
    assert {r["doc_id"] for r in out} == {0, 1, 4, 5}
    assert pipeline.near_duplicates(spark, spark.createDataFrame([], SCHEMA), "").count() == 0


def test_all_stages_on_odd_rows(spark, tmp_path):
    text = "The order of the day was that the men and the women should be there with all that they had. " * 3
    rows = [(i, text + f" number {i} " + "abc def " * i, "en", "a", 0) for i in range(40)] + [(None, text, "en", None, 0), (7, None, None, None, None), (8, "", "en", "a", 0), (9, "mail me at a.b@c.org now " + text, "en", "b", 0)]
    spark.createDataFrame(rows, SCHEMA.replace(", clash int", "")).write.parquet(str(tmp_path / "documents.parquet"))
    out = pipeline.run(spark, str(tmp_path))
    assert out.columns[:2] == ["doc_id", "n_tokens"] and out.count() > 0
    spark.createDataFrame([], SCHEMA.replace(", clash int", "")).write.parquet(str(tmp_path / "empty/documents.parquet"))
    assert pipeline.run(spark, str(tmp_path / "empty")).count() == 0
