"""The sampling study runs the model whose neighbourhoods it samples."""

from relmodel import learned
from relmodel.nn import grid


def test_messages_pass_over_the_samples(spark, sf, monkeypatch):
    seen, own = [], grid.model_of
    monkeypatch.setattr(grid, "model_of", lambda c, augmented: (seen.append((c.extra["first"], c.use_passing, c.use_fusion, augmented)), own(c, augmented))[1])

    def fitted(packed, specs, schemas, steps):
        rows = packed.collect()
        return [grid.fit_one(grid.rows_of(rows), spec | {"train": {"epochs": 1}}, schemas, steps) for spec in specs]

    monkeypatch.setattr(grid, "run_grid", lambda packed, specs, schemas, steps, test: (fitted(packed, specs, schemas, steps), spark.createDataFrame([('{"first": 8}', 0.0)], "config string, metric double"))[1])
    learned.w16_sampling(spark, sf)
    assert seen == 2 * [(8, True, True, True), (32, True, True, True)]
