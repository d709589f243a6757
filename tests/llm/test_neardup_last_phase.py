import random

from chronoweave.llm import components, neardup


def test_rare_prefixes_alone_find_every_link(spark):
    rng = random.Random(4)
    rows = []
    for _ in range(4):
        base = [f"w{rng.randrange(400)}" for _ in range(80)]
        for _ in range(25):
            text = list(base)
            for at in rng.sample(range(80), rng.randint(0, 12)):
                text[at] = f"w{rng.randrange(400)}"
            rows.append((len(rows), " ".join(text[: rng.randint(70, 80)])))
    sets = {i: {*zip(t.split(), t.split()[1:], strict=False)} for i, t in rows}
    comp = {i: i for i in sets}
    for i in sets:
        for j in range(i):
            if 100 * len(sets[i] & sets[j]) >= 80 * len(sets[i] | sets[j]):
                a, b = comp[i], comp[j]
                comp = {k: min(a, b) if c in (a, b) else c for k, c in comp.items()}
    got = neardup.near_duplicates(spark.createDataFrame(rows, "doc_id long, text string"), words=2, rounds=0)
    assert {r["doc_id"]: r["component_id"] for r in got.collect()} == comp


def test_components_go_on_until_nothing_changes(spark, monkeypatch):
    done = []

    def slow(edges):
        done.append(1)
        return spark.createDataFrame([(0 if i <= len(done) + 1 else i - 1, i) for i in range(1, 46)], "a long, b long").coalesce(1)

    monkeypatch.setattr(components, "large_star", lambda edges: edges)
    monkeypatch.setattr(components, "small_star", slow)
    path = spark.createDataFrame([(i - 1, i) for i in range(1, 46)], "a long, b long")
    assert {r["component"] for r in components.components(path).collect()} == {0}
