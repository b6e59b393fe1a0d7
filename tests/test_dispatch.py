"""Dispatch from a ledger of runs; boosting on ordered statistics; text vectors; bucketed tables."""

import random

from pyspark.sql import functions as F

from relmodel.functions.embed import text_vector
from relmodel.nn import boost
from relmodel.plans import dispatch


def test_expected_skill_lies_between_past_skills(spark):
    past = spark.createDataFrame([("a", 0.5), ("a", 0.7), ("b", 0.9), ("b", 0.9)], "model_id string, perf double")
    shares = spark.createDataFrame([("a", "p", 0.25), ("a", "q", 0.75), ("b", "p", 0.0), ("c", "p", 1.0)], "model_id string, proxy string, score double")
    assert {r.model_id: round(r.score, 9) for r in dispatch.expected_skill(shares, past).collect()} == {"a": 0.6, "b": 0.9}


def test_strategies(spark):
    runs = spark.createDataFrame([("x", "a", 0.6, 0.9), ("x", "b", 0.5, 0.8), ("y", "a", 0.95, 0.9), ("y", "b", 0.9, 0.7)], "task_key string, model_id string, direct double, augmented double")
    decided = spark.createDataFrame([("x", "a", "augment"), ("y", "a", "direct")], "task_key string, model_id string, decision string")
    static = spark.createDataFrame([("x", "a", 0.55, 0.4), ("x", "b", 0.45, 0.6), ("y", "a", 0.8, 0.9), ("y", "b", 0.7, 0.1)], "task_key string, model_id string, stale double, past double")
    got = {(r.strategy, r.task_key): (r.decision, r.skill, r.trained) for r in dispatch.strategies(runs, decided, static, "b").collect()}
    assert got["conditional", "x"] == ("augment", 0.9, 1) and got["conditional", "y"] == ("direct", 0.95, 1) == got["never", "y"]
    assert got["retrain", "x"] == ("augment", 0.8, 1) and got["retrain", "y"] == ("augment", 0.7, 1)
    assert got["static_pool", "x"] == ("direct", 0.45, 0) and got["static_pool", "y"] == ("direct", 0.8, 0)
    assert got["best", "x"][:2] == ("augment", 0.9) and got["always", "y"][1] == 0.9


def test_ordered_statistic_in_slots(spark):
    r = random.Random(2)
    rows = [(i, r.choice(["a", "b", None]), float(r.random() < 0.4), f"{r.randrange(16**4):04x}{i:04x}") for i in range(300)]
    df = spark.createDataFrame(rows, "i int, c string, y double, h string")
    got = {x.i: x.stat for x in boost.ordered_target_statistic(df, "c", "y", "h").collect()}
    for i, c, _, h in rows:
        seen = [y for _, c2, y, h2 in rows if c2 == c and h2 < h]
        assert abs(got[i] - (sum(seen) + 0.5) / (len(seen) + 1)) < 1e-12


def test_boosting_uses_categories_and_many_leaves(spark):
    r = random.Random(3)
    rows = [(r.choice("abcdefgh"), r.random()) for _ in range(800)]
    df = spark.createDataFrame([(c, x, float((c in "aceg") == (x > 0.5))) for c, x in rows], "c string, x double, y double")
    m = boost.boost(df, ["x"], "y", kind="symmetric", rounds=4, depth=4, categorical=("c",))
    out = m.predict(df.unionByName(spark.createDataFrame([("new", 0.5, 0.0), (None, 0.5, 0.0)], df.schema)))
    assert out.columns == ["c", "x", "y", "score"] and out.count() == 802
    deep = boost.boost(df, ["x"], "y", kind="leafwise", rounds=1, leaves=31, bins=64)
    assert len(deep.expression) < 20_000  # linear in the leaves


def test_text_vector_is_frozen_and_of_length_one(spark):
    rows = spark.createDataFrame([("Blue anvil",), ("anvil, BLUE!",), ("red",), (None,), ("",)], "t string")
    a, b, c, d, e = (r.v for r in rows.select(text_vector(F.col("t"), "t").alias("v")).collect())
    assert a == b != c and len(a) == 16 and abs(sum(x * x for x in a) - 1) < 1e-9 or set(a) == {0.0}
    assert set(d) == set(e) == {0.0}


def test_bucketed_tables_join_without_shuffle(spark, sf):
    from relmodel.operators_queries import QUERIES

    df = QUERIES["bucketed_join"](spark, sf)
    df.count()
    assert "Exchange hashpartitioning" not in df._jdf.queryExecution().executedPlan().toString()


def test_arrow_batches_unroll_as_rows_do(spark, sf):
    import numpy as np

    from relmodel import learned
    from relmodel.nn.relational import Config, unroll, unroll_arrow
    from relmodel.nn.train import rows_of

    steps = (*learned.STEPS, learned.Step("event_customer", "customer", "events"))
    (packed,), plan = learned.packed_parts(spark, sf, "pl1", ["fit"], seeds=60, steps=steps)
    packed = packed.orderBy("split", "seed_id")
    c = Config("customer", plan.schemas(), plan.steps)
    batch = packed.toArrow().combine_chunks().to_batches()[0].slice(3)  # a slice, so offsets count
    a, b = unroll_arrow(batch, c), unroll(rows_of(packed.collect())[3:], c)
    for n in c.schemas:
        assert np.allclose(a.num[n], b.num[n], equal_nan=True) and np.array_equal(a.cat[n], b.cat[n])
    assert np.array_equal(a.y, b.y) and a.seeds == b.seeds
    for x, y in zip(a.edges, b.edges):
        assert x[:3] == y[:3] and np.array_equal(x[3], y[3]) and np.array_equal(x[4], y[4])
    for n in b.owner:
        assert a.owner[n][0] == b.owner[n][0] and all(np.array_equal(p, q) for p, q in zip(a.owner[n][1:], b.owner[n][1:]))


def test_layers_cut_or_not_give_the_same_states(spark, sf):
    from relmodel import queries as Q
    from relmodel.operators import passing

    s = Q._slice(spark, sf)
    got = []
    for cut in (None, passing.saved):
        df = passing.message_layers(Q._states(s), Q._relations(s), 2, target="customer", cut=cut)["customer"]
        got.append(sorted((r[0], *(round(x, 9) for x in r[1:])) for r in df.collect()))
    assert got[0] == got[1] and got[0]


def test_quantiles_are_exact(spark):
    import numpy as np

    from relmodel.functions.quantile import quantiles

    r = random.Random(4)
    rows = [(r.choice(["a", "b", None]), r.choice([None, r.randrange(50) / 7, r.gauss(0, 1)])) for _ in range(900)] + [("one", 2.5), ("none", None)]
    df = spark.createDataFrame(rows, "g string, x double")
    q = {"lo": 0.05, "mid": 0.5, "hi": 0.9}
    got = {x.g: (x.lo, x.mid, x.hi) for x in quantiles(df, "x", q, ("g",), parts=5).collect()}
    for g in ("a", "b", None, "one"):
        assert np.allclose(got[g], np.quantile([x for k, x in rows if k == g and x is not None], list(q.values())))
    assert "none" not in got
    assert np.allclose(tuple(quantiles(df, "x", q).first()), np.quantile([x for _, x in rows if x is not None], list(q.values())))


def test_partials_are_added_in_levels(spark):
    import numpy as np

    from relmodel.nn.train import _tree

    def partial(frames):
        rows = [x for pdf in frames for x in pdf["id"]]
        return len(rows), float(sum(rows)), {"w": np.array([len(rows), sum(rows)], float)}

    n, loss, total = _tree(spark.range(0, 500, numPartitions=37), partial, width=3)
    assert n == 500 and loss == sum(range(500)) and list(total["w"]) == [500, sum(range(500))]
