"""Operators that SQL cannot express, against plain versions of their methods."""

import random
from collections import Counter, defaultdict

import numpy as np

from chronoweave.llm import langid, quality, sharding

SCHEMA = "doc_id long, text string, lang string, source string, clash int"


def plain_kneser_ney(counts, order):
    """Interpolated probabilities by dictionaries: text keys, recursion over shorter contexts."""
    levels = {order: dict(counts)}
    for n in range(order - 1, 0, -1):
        levels[n] = Counter(k[1:] for k in levels[n + 1])
    total, kinds = defaultdict(float), defaultdict(int)
    for n, level in levels.items():
        for k, c in level.items():
            total[n, k[:-1]] += c
            kinds[n, k[:-1]] += 1

    def p(key):
        n = len(key)
        if n == 0:
            return 1 / (len(levels[1]) + 1)
        ctx = (n, key[:-1])
        if ctx not in total:
            return p(key[1:])
        d = langid.DISCOUNT
        return max(levels[n].get(key, 0) - d, 0) / total[ctx] + d * kinds[ctx] / total[ctx] * p(key[1:])

    return p


def test_models_against_plain_kneser_ney():
    rng = random.Random(1)
    words = Counter("".join(rng.choice("abcdé") for _ in range(rng.randint(1, 6))) for _ in range(300))
    grams = Counter()
    for w, c in words.items():
        padded = "   " + w + " "
        for i in range(len(padded) - 3):
            grams[padded[i : i + 4]] += c
    keys, size = langid.packed_grams(list(words), 4)
    k, inv = np.unique(keys, return_inverse=True)
    model = langid.Model(k, np.bincount(inv, np.repeat(np.array(list(words.values())), size)).astype(np.int64), 4)
    plain = plain_kneser_ney(grams, 4)
    probes = [*grams, *("".join(rng.choice("abcdéxy ") for _ in range(4)) for _ in range(300))]
    packed = np.array([sum(ord(c) << (16 * (3 - i)) for i, c in enumerate(x)) for x in probes], np.uint64)
    assert np.allclose(model.probability(packed), [plain(x) for x in probes], rtol=1e-12)
    for ctx in {g[:3] for g in grams}:  # a distribution over what is known and one unknown
        assert 0 < sum(plain(ctx + c) for c in {g[-1] for g in grams}) <= 1 + 1e-9


def test_rejection_keeps_what_it_was_calibrated_on(spark):
    rng = random.Random(3)
    sounds = {"en": ["the", "ing", "th", "er", "and"], "de": ["sch", "ung", "ein", "ver", "ich"]}
    write = lambda lg, n: " ".join("".join(rng.choice(sounds[lg]) for _ in range(rng.randint(1, 3))) for _ in range(n))
    rows = [(i, write(lg, rng.randint(3, 60)), lg, "a", 1) for i in range(400) for lg in ["en" if i % 2 else "de"]]
    odd = [(900 + i, " ".join("".join(rng.choice("qxzjkvwpy") for _ in range(6)) for _ in range(40)), None, "a", 1) for i in range(20)]
    df = spark.createDataFrame(rows + odd, SCHEMA)
    models = langid.train(df)
    got = {r["doc_id"]: r for r in langid.predict(df, models, ["doc_id", "lang"]).collect()}
    assert not any(got[r[0]]["rejected"] for r in rows) and all(got[r[0]]["rejected"] for r in odd)
    assert all(m.worst >= 0 for m in models.values())
    scores = [got[r[0]]["lang_pred"] == r[2] for r in rows]
    assert sum(scores) > 0.97 * len(scores)


def plain_tree(points, depth):
    """Shards by sorting: each node's points in the order of its widest dimension, cut at half of its bytes."""
    nodes = {0: list(range(len(points)))}
    extent = [max(1, max(p[d] for p in points) - min(p[d] for p in points)) for d in range(3)]
    for _ in range(depth):
        nxt = {}
        for node, ids in nodes.items():
            wide = max(range(3), key=lambda d: (max(points[i][d] for i in ids) - min(points[i][d] for i in ids)) / extent[d])
            ids = sorted(ids, key=lambda i: (points[i][wide], points[i][3], points[i][4]))
            half, at, best = sum(points[i][5] for i in ids) / 2, 0, (float("inf"), 0)
            for k, i in enumerate(ids + [None]):
                best = min(best, (abs(at - half), k))
                at += points[i][5] if i is not None else 0
            nxt[2 * node], nxt[2 * node + 1] = ids[: best[1]], ids[best[1] :]
        nodes = nxt
    return {i: n for n, ids in nodes.items() for i in ids}


def test_shards_against_medians_by_sorting(spark, monkeypatch):
    rng = random.Random(9)
    rows = [(i, "x" * rng.randint(0, 400) + str(i), rng.choice(["en", "de", None]), rng.choice("abcde"), 1) for i in range(300)]
    seen = {}
    real = sharding.stored

    def keep(df, label, *a):
        out = real(df, label, *a)
        if label == "kd-points":
            seen["points"] = [(r["doc_id"], r["c0"], r["c1"], r["c2"], r["h_text"], r["h_id"], r["size"]) for r in out.collect()]
        return out

    monkeypatch.setattr(sharding, "stored", keep)
    got = {r["doc_id"]: r["shard"] for r in sharding.kd_shards(spark.createDataFrame(rows, SCHEMA), depth=3, tolerance=0).collect()}
    points = [p[1:] for p in seen["points"]]
    want = plain_tree(points, 3)
    size = lambda of: sorted(sum(points[i][5] for i in range(300) if of(i) == s) for s in range(8))
    ids = [p[0] for p in seen["points"]]
    assert all(abs(a - b) <= 450 for a, b in zip(size(lambda i: got[ids[i]]), size(lambda i: want[i]), strict=True))
    total = sum(p[5] for p in points)
    target = sharding.shard(spark.createDataFrame(rows, SCHEMA), target_bytes=-(-total // 4))
    assert target.select("shard").distinct().count() == 4
    far = {r["shard"]: r["b"] for r in target.groupBy("shard").agg({"size": "sum"}).withColumnRenamed("sum(size)", "b").collect()}
    assert max(far.values()) <= total / 4 + 450


def test_quality_fences_of_each_group(spark):
    rng = random.Random(5)
    word = lambda n: "".join(rng.choice("abcdefghij") for _ in range(n))
    rows = [(i, " ".join(word(rng.randint(4, 7)) for _ in range(80)), lang, src, 1) for i in range(240) for lang, src in [(["en", None][i % 2], ["a", "b"][i // 2 % 2])]]
    rows += [(1000, " ".join(word(40) for _ in range(80)), "en", "a", 1), (1001, " ".join(word(5) + "#$%&" for _ in range(80)), None, "b", 1)]
    got = {r["doc_id"]: r for r in quality.judge(spark.createDataFrame(rows, SCHEMA)).collect()}
    assert all(got[i]["kept"] for i in range(240)) and not got[1000]["kept"] and not got[1001]["kept"]
    for r in (got[0], got[1]):
        mine = [g for g in got.values() if (g["lang"], g["source"]) == (r["lang"], r["source"]) and not g["base_failed"]]
        lengths = sorted(g["word_chars"] / max(1, g["n_words"]) for g in mine)
        q1, q3 = lengths[max(0, -(-len(lengths) // 4) - 1)], lengths[max(0, -(-3 * len(lengths) // 4) - 1)]
        for g in mine:
            v = g["word_chars"] / g["n_words"]
            if v > q3 + max(6 * (q3 - q1), 3.0) or v < q1 - max(6 * (q3 - q1), 3.0):
                assert not g["kept"]


def test_repeated_windows_of_a_long_text(spark):
    rng = random.Random(6)
    words = [rng.choice("abcdefghijklmnopqrstuvwxyz") + str(rng.randrange(60)) for _ in range(60_000)]
    seen, marked = defaultdict(list), set()
    for k in range(len(words) - 2):
        seen[tuple(words[k : k + 3])].append(k)
    for places in seen.values():
        if len(places) > 1:
            marked |= {p + j for p in places for j in range(3)}
    df = spark.createDataFrame([(1, " ".join(words), "en", "a", 1)], SCHEMA)
    assert quality.text_measures(df).first()["n_repeat_words"] == len(marked)


def test_rejection_thresholds_take_every_training_text(spark):
    from pyspark.sql import functions as F

    rng = np.random.default_rng(5)
    words = ["".join(rng.choice(list("abcdefgh"), 6)) for _ in range(300)]
    rows = [(" ".join(rng.choice(words, 8)), "en") for _ in range(8999)]
    strange = [" ".join("".join(rng.choice(list("ijklmnopqrstuvwxyz"), 6)) for _ in range(600)) for _ in range(12)]
    odd = spark.createDataFrame([(t,) for t in strange], "text string").filter(F.pmod(F.xxhash64("text"), F.lit(2)) == 1).first()[0]
    docs = spark.createDataFrame([*rows, (odd, "en")], "text string, lang string")
    models = langid.train(docs)
    told = langid.predict(docs, models, ["lang"])
    top, rejected = told.agg(F.max("above"), F.count_if("rejected")).first()
    assert models["en"].worst == max(0.0, top) > 0 and rejected == 0
