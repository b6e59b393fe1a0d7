"""Predictions and studies cover whole tables; only fitting is bounded. Nothing after a cutoff reaches
the rows or the statistics before it."""

import pytest
from pyspark.sql import functions as F

from relmodel import learned
from relmodel.catalog import load
from relmodel.operators.slices import at


@pytest.fixture(scope="module")
def labels(spark, sf):
    return learned.task_labels("pl1", load(spark, sf, learned.TABLES)).cache()


def test_predictions_cover_every_entity(spark, sf, labels):
    got = learned._trained(spark, sf, augmented=False, base="mlp")
    assert sorted(r.seed_id for r in got.select("seed_id").collect()) == sorted(str(r.entity_id) for r in labels.where("split = 'test'").collect())


def test_studies_measure_every_test_entity(spark, sf, labels, monkeypatch):
    from relmodel.nn import grid

    seen, own = [], grid.test_figures
    monkeypatch.setattr(grid, "test_figures", lambda test, *more: (seen.append(test.count()), own(test, *more))[1])
    got = learned.study(spark, sf, "pl1", [{"base": "constant"}, {"train": {"epochs": 1, "batch": 64}}], seeds=20).collect()
    assert seen == [labels.where("split = 'test'").count()] and len(got) == 2
    assert got[0].metric == 0.5 and 0 <= got[1].metric <= 1 and got[1].top.count(",") == 3


def test_rows_after_the_cutoff_change_nothing_before_it(spark, sf, monkeypatch):
    """Orders and lines after the valid cutoff are altered: encoder, train and valid rows stay as they were."""
    (before,), plan = learned.packed_parts(spark, sf, "pl1", ["fit"], seeds=40)
    before = sorted(map(str, before.collect()))

    def altered(spark, sf, names):
        t = load(spark, sf, names)
        late = at(learned.ORDER_CUTOFFS[1])
        t["orders"] = t["orders"].withColumn("o_totalprice", F.when(F.col("o_orderdate") > late, F.col("o_totalprice") * 1000).otherwise(F.col("o_totalprice")))
        t["orders"] = t["orders"].withColumn("o_orderpriority", F.when(F.col("o_orderdate") > late, F.lit("new")).otherwise(F.col("o_orderpriority")))
        t["lineitem"] = t["lineitem"].where(F.col("l_shipdate") <= late)
        return t

    monkeypatch.setattr(learned, "load", altered)
    (after,), other = learned.packed_parts(spark, sf, "pl1", ["fit"], seeds=40)
    assert other.encoders == plan.encoders and sorted(map(str, after.collect())) == before


def test_labels_are_chronological(spark, sf):
    """Each split has its own cutoff; regressions are in units of the train part."""
    t = load(spark, sf, learned.TABLES)
    own = learned.task_labels("pl2", t).groupBy("split").agg(F.avg("y").alias("m"), F.stddev_pop("y").alias("s")).collect()
    by = {r.split: (r.m, r.s) for r in own}
    assert set(by) == set(learned.SPLITS) and abs(by["train"][0]) < 1e-9 and abs(by["train"][1] - 1) < 1e-9
    assert by["test"][0] > by["valid"][0] > 0  # customers spend more and more


@pytest.mark.parametrize("how", ["fit_sync", "fit_local_sgd"])
def test_epochs_read_stored_rows(spark, sf, monkeypatch, how):
    """No epoch packs the tables again."""
    from relmodel.nn import train

    class Seen(Exception):
        pass

    def fit(packed, *_):
        raise Seen(packed.inputFiles())

    monkeypatch.setattr(train, how, fit)
    with pytest.raises(Seen) as e:
        learned.QUERIES["train_" + how[4:]](spark, sf)
    assert e.value.args[0] and not [f for f in e.value.args[0] if "/root/testdata" in f]
