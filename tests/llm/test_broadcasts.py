"""What Spark sizes too low (by a compressed file, or before an explode) is not broadcast."""

import random

from pyspark.sql import functions as F

from relmodel.llm import _common, simhash


def joins(df):
    return [x.strip(" :+-")[:200] for x in df._jdf.queryExecution().sparkPlan().toString().splitlines() if "Join" in x]


def codes_of(spark, n, seed=3):
    r = random.Random(seed)
    return _common.written(spark.createDataFrame([(i, [r.getrandbits(63)]) for i in range(n)], "node long, fp array<long>"))


def test_probes_and_balls_are_not_broadcast(spark):
    codes, parts = codes_of(spark, 400), [list(range(i, i + 16)) for i in range(0, 64, 16)]
    for found in (simhash.links(codes, 4, 1, parts, [0, 0, 0, 1]), simhash.balls(codes)):
        inner = [x for x in joins(found) if "Inner" in x]
        assert inner and all(x.startswith("SortMergeJoin") for x in inner), inner


def test_many_edges_are_not_broadcast(spark, monkeypatch):
    plans, own = [], _common.written
    monkeypatch.setattr(_common, "MOST_SENT", 50)
    monkeypatch.setattr(_common, "written", lambda df: (plans.extend(joins(df)), own(df))[1])
    edges = spark.range(100).select(F.col("id").alias("a"), (F.col("id") + F.when(F.col("id") % 10 == 9, 0).otherwise(1)).alias("b"))
    got = {r.node: r.component for r in _common.components(edges).collect()}
    assert got == {i: i - i % 10 for i in range(100)}
    assert plans and "SortMergeJoin" in plans[0]
