"""Calibrated proxies: all models, against brute force, and without pairing all scores."""

import random

from relmodel.operators_queries import QUERIES, _proxies
from relmodel.plans.dispatch import calibrate

SCHEMA = "model_id string, proxy string, raw double"


def test_mid_ranks_against_brute_force(spark):
    r = random.Random(2)
    past = [(f"m{i}", r.choice("ab"), float(r.randrange(40))) for i in range(300)] + [("m", "a", None)]
    raw = past[:50] + [("n", "a", -5.0), ("n", "b", 99.5), ("n", "a", 7.5), ("n", "none", 1.0), ("z", "a", None)]
    want = {}
    for m, p, v in raw:
        old = [o for _, q, o in past if q == p and o is not None]
        want[m, p, v] = round(sum(0.0 if v is None else (o < v) + 0.5 * (o == v) for o in old) / len(old), 9) if old else 0.5
    got = calibrate(spark.createDataFrame(raw, SCHEMA), spark.createDataFrame(past, SCHEMA))
    assert {(x.model_id, x.proxy, x.raw): round(x.score, 9) for x in got.collect()} == want


def test_one_large_proxy_group_is_not_paired(spark):
    """100,000 scores of one proxy: 10**10 pairs if each met all."""
    x = spark.range(100_000).selectExpr("concat('m', id) AS model_id", "'p' AS proxy", "double(id) AS raw")
    got = calibrate(x, x).selectExpr("count(*) AS n", "min(score) AS lo", "max(score) AS hi").first()
    assert (got.n, round(got.lo, 9), round(got.hi, 9)) == (100_000, 0.000005, 0.999995)


def test_query_covers_every_model(spark, sf):
    x = _proxies(spark, sf)
    got = QUERIES["proxy_calibrated"](spark, sf)
    assert sorted(map(tuple, got.select("model_id", "proxy").collect())) == sorted(map(tuple, x.select("model_id", "proxy").collect()))
