"""Studies prepare a task once; what they find stays the same."""

import numpy as np
import pytest
from pyspark.sql import Window
from pyspark.sql import functions as F

from relmodel import learned
from relmodel.catalog import LINE_ID, load
from relmodel.nn.relational import Step

PARTS = {"steps": (Step("line_part", "part", "lineitem"),), "target": "part"}


def test_latest_rows_break_ties_by_id(spark, sf):
    from relmodel.operators.graph import latest_rows

    lines = load(spark, sf, ["lineitem"])["lineitem"].withColumn("day", F.when(F.col("l_linenumber") > 1, F.date_trunc("year", "l_shipdate")))
    order = F.row_number().over(Window.partitionBy("l_partkey").orderBy(F.desc("day"), F.expr(LINE_ID)))
    want = lines.withColumn("rn", order).where("rn <= 6").select(F.expr(LINE_ID).alias("id"), "rn")
    got = latest_rows(lines, 6, "l_partkey", "day", LINE_ID).select(F.expr(LINE_ID).alias("id"), "rn")
    assert sorted(map(tuple, got.collect())) == sorted(map(tuple, want.collect()))


def test_sampling_study_prepares_its_task_once(spark, sf, monkeypatch):
    labels, parts, own = [], [], (learned.task_labels, learned.packed_parts)
    monkeypatch.setattr(learned, "task_labels", lambda *a: (labels.append(a[0]), own[0](*a))[1])
    monkeypatch.setattr(learned, "packed_parts", lambda *a, **k: (parts.append(k["k"]), own[1](*a, **k))[1])
    got = learned.w16_sampling(spark, sf).collect()
    assert labels == ["pl3"] and parts == [32, 32]
    assert [(r.k, r.strategy) for r in got] == [(8, "latest"), (8, "uniform"), (32, "latest"), (32, "uniform")]


@pytest.mark.parametrize("how", ["latest", "uniform"])
def test_a_sample_begins_with_the_smaller_ones(spark, sf, how):
    spec = {"use_passing": False, "train": {"epochs": 2, "batch": 64}}
    one = learned.study(spark, sf, "pl3", [spec], seeds=60, k=3, strategy=how, **PARTS).first()
    two = learned.study(spark, sf, "pl3", [spec | {"first": 3}], seeds=60, k=9, strategy=how, **PARTS).first()
    assert np.isclose(one.metric, two.metric) and np.isclose(one.valid, two.valid) and one.top == two.top


def test_strategies_pack_each_part_once(spark, sf, monkeypatch):
    """The stale pool and the new runs are measured in one pass of the test rows; both rounds share the past."""
    parts, own = [], learned.packed_parts
    monkeypatch.setattr(learned, "packed_parts", lambda s, d, name, p, **k: (parts.extend((name, x) for x in p), own(s, d, name, p, **k))[1])
    got = learned.dispatch_strategies(spark, sf)
    for name in ("pl1", "pl5"):
        assert parts.count((name, "test")) == 1 and parts.count((name, "past")) == 1
    assert {r.strategy for r in got.collect()} == {"never", "always", "conditional", "best", "retrain", "static_pool"}


def test_areas_of_many_models_at_once(spark):
    from relmodel.operators.metrics import mae, roc_area

    r = np.random.default_rng(7)
    rows = [(i, float(y), float(s)) for i in range(3) for y, s in zip(r.random(200) < 0.4, r.integers(0, 30, 200))] + [(9, 1.0, 0.5)]
    df = spark.createDataFrame(rows, "i int, y double, s double")
    for how in (roc_area, mae):
        got = {x.i: x[1] for x in how(df, "y", "s", by=("i",)).collect()}
        for i in (0, 1, 2, 9):
            want = how(df.where(F.col("i") == i), "y", "s").first()[0]
            assert got[i] == want or np.isclose(got[i], want)


def test_natural_part_studies_make_labels_once(spark, sf, monkeypatch):
    """Every packing of w11_part_positive reads stored labels, not the lines again."""
    from relmodel.plans import packing

    seen, own = [], packing.pack
    monkeypatch.setattr(learned, "pack", lambda seeds, *a, **k: (seen.extend(seeds.inputFiles()), own(seeds, *a, **k))[1])
    learned.packed_parts(spark, sf, "part_positive", ["fit", "test"], seeds=20, **PARTS)
    assert seen and not [f for f in seen if "/root/testdata" in f]


def test_repeated_seeds_get_each_neighbour_once(spark, sf):
    """First hops are numbered by their sample alone, without meeting the seeds again."""
    from relmodel.plans.packing import fit_plan, pack

    t = load(spark, sf, ["part", "lineitem"])
    plan = fit_plan(t, "part", list(PARTS["steps"]), k=3)
    seeds = spark.createDataFrame([("1", 0.0, "train"), ("1", 1.0, "valid"), ("2", 0.0, "train")], "seed_id string, y double, split string")
    for how in (True, False):
        got = {(r.seed_id, r.split): r.line_part for r in pack(seeds, t, plan, few=how).collect()}
        assert {k: len(v) for k, v in got.items()} == {("1", "train"): 3, ("1", "valid"): 3, ("2", "train"): 3}
        assert got["1", "train"] == got["1", "valid"]
