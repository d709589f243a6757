"""The timing experiments: query logs and shapes on stored graphs under several strategies, with their summaries.

    python -m chronoweave.workloads.experiments /root/testdata/sf0.01 log 60
    python -m chronoweave.workloads.experiments /root/testdata/sf0.01 shapes 100
    python -m chronoweave.workloads.experiments /root/testdata/sf0.01 index

``log``: patterns of 1 to 5 quads at one shared instant, answers limited, with a timeout. ``shapes``: queries with random
labels of live embeddings and random windows of 1, 10 and 100 % of the span. ``index``: space and build time as the graph grows.
Prints one JSON object: box plots, wins of each strategy over each other, and the mean of the query-wise best.
"""

from __future__ import annotations

import json
import random
import sys
from collections.abc import Callable
from datetime import datetime

from pyspark.sql import DataFrame, SparkSession

from ..index import store
from ..measures import cost
from ..model.query import Const, OrderClause, PatternQuery, TimeVar
from ..operators import solve
from ..sources.graphs import graph
from . import logs, shapes

STRATEGIES = ("JF", "TF", "LC")


def timings(spark: SparkSession, queries: list[PatternQuery], run: Callable[[PatternQuery, str], DataFrame], limit: int | None = 1000, timeout: float | None = 60.0, strategies: tuple[str, ...] = STRATEGIES) -> DataFrame:
    """One row a query and strategy; the first query is run once before, for what a session does once."""
    cost.timed(lambda: run(queries[0], strategies[0]), limit, timeout)
    rows = []
    for i, q in enumerate(queries):
        for s in strategies:
            ms, n, late = cost.timed(lambda q=q, s=s: run(q, s), limit, timeout)
            rows.append((i, s, float(ms), n, late))
    return spark.createDataFrame(rows, cost.TIMING)


def summary(times: DataFrame) -> dict:
    """Box plot, win matrix and best of some timings, and the timeouts."""
    times = times.cache()
    out = {"boxplot": {r["strategy"]: {k: round(v, 1) for k, v in r.asDict().items() if k != "strategy"} for r in cost.boxplot(times).collect()}}
    out["wins"] = {r["strategy"]: {k: v for k, v in r.asDict().items() if k != "strategy" and v is not None} for r in cost.wins(times).collect()}
    out["best_mean"] = round(cost.best(times).first()["best_mean"], 1)
    out["timeouts"] = times.filter("timed_out").count()
    out["answers"] = {r["qid"]: r["rows"] for r in times.filter("strategy = 'JF'").select("qid", "rows").collect()}
    times.unpersist()
    return out


def log(spark: SparkSession, sf_dir: str, n: int = 60, name: str = "KG") -> DataFrame:
    """The fixed templates and as many random walks as make ``n``, without those whose constants do not occur."""
    path = store.shared_folder(spark, f"log-{name}")
    store.save(graph(spark, sf_dir, name), path)
    g = store.open_store(spark, path).graph
    fixed = logs.kg_log() if name == "KG" else logs.kgt_log()
    queries = logs.filter_by_constants([*fixed, *logs.more(max(0, n - len(fixed)), 7)][:n], g)
    return timings(spark, queries, lambda q, s: solve.solve(q, g, s, route="pairwise"))


def shape_log(spark: SparkSession, sf_dir: str, n: int, shape: str, share: float, name: str = "TRIP10", seed: int = 1) -> tuple[list[PatternQuery], DataFrame]:
    """``n`` queries of a shape with labels of embeddings at random instants, each over a random window of a share of the span."""
    path = store.shared_folder(spark, f"shape-{name}")
    store.save(graph(spark, sf_dir, name), path)
    g = store.open_store(spark, path).graph
    lo, hi = shapes.month()
    rng = random.Random(seed)
    out: list[PatternQuery] = []
    for i, (a, b) in enumerate(shapes.windows(lo, hi, share, n, seed)):
        labels = shapes.sample_labels(g, shape, a + (b - a) * rng.random(), seed + i)
        if labels is None:
            continue
        q, t = shapes.shape_query(shape, labels), TimeVar("t")
        out.append(q if share >= 1 else q.with_clauses(OrderClause(Const(a), t), OrderClause(t, Const(b))))
    return out, timings(spark, out, lambda q, s: solve.solve(q, g, s, route="pairwise"), None if share >= 1 else 100_000, 120.0) if out else spark.createDataFrame([], cost.TIMING)


def index_growth(spark: SparkSession, sf_dir: str, name: str = "MONO") -> dict:
    g = graph(spark, sf_dir, name)
    index = store.tries.build(g, ("ptso", "otps"))
    n = g.frame.count()
    space = [r.asDict() for r in cost.space(index, n).collect()]
    tables = [r.asDict() for r in cost.table_space(g, ("otps",)).collect()]
    return {"edges": n, "matrices": space, "tables": tables, "growth": cost.build_time(g, (0.25, 0.5, 1.0), ("otps",))}


def main(sf_dir: str, what: str, n: int) -> None:
    spark = SparkSession.builder.master("local[8]").config("spark.sql.shuffle.partitions", "8").config("spark.driver.memory", "8g").config("spark.ui.enabled", "false").config("spark.sql.session.timeZone", "UTC").getOrCreate()
    spark.sparkContext.setLogLevel("ERROR")
    if what == "index":
        out: dict = index_growth(spark, sf_dir)
    elif what == "log":
        out = {name: summary(log(spark, sf_dir, n, name)) for name in ("KG", "KGT")}
    else:
        out = {}
        for shape in shapes.SHAPES:
            for share in (1.0, 0.1, 0.01):
                queries, times = shape_log(spark, sf_dir, n, shape, share)
                if queries:
                    out[f"{shape} {share:g}"] = {"queries": len(queries)} | summary(times)
    print(json.dumps({"sf": sf_dir, "at": f"{datetime.now():%Y-%m-%d}", what: out}))


if __name__ == "__main__":
    main(sys.argv[1], sys.argv[2], int(sys.argv[3]) if len(sys.argv) > 3 else 60)
