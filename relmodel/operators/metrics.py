"""Measures (A1-A15), exact and distributed."""

from __future__ import annotations

import time

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F


def roc_area(df: DataFrame, y: str = "y", score: str = "score", parts: int = 64, by: tuple[str, ...] = ()) -> DataFrame:
    """A1: one row (area), or one for each value of ``by``; ties counted half, null without both classes.

    Counts per distinct score, then prefix sums in two levels: ranges of the score are summed, the
    ranges' offsets (``parts`` numbers) are broadcast, and each range runs on its own."""
    g = df.groupBy(*by, F.col(score).cast("double").alias("s")).agg(F.sum(F.when(F.col(y) > 0, 1).otherwise(0)).alias("p"), F.sum(F.when(F.col(y) > 0, 0).otherwise(1)).alias("n"))
    cuts = g.groupBy(*by).agg(F.percentile_approx("s", [i / parts for i in range(1, parts)], 10_000).alias("cuts"))
    g = (g.join(F.broadcast(cuts), [*by]) if by else g.crossJoin(F.broadcast(cuts))).withColumn("part", F.size(F.filter(F.coalesce("cuts", F.array().cast("array<double>")), lambda c: c < F.col("s")))).drop("cuts")
    totals = g.groupBy(*by, "part").agg(F.sum("n").alias("m")).select(*by, "part", F.coalesce(F.sum("m").over(Window.partitionBy(*by).orderBy("part").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0)).alias("before"))
    run = F.sum("n").over(Window.partitionBy(*by, "part").orderBy("s").rowsBetween(Window.unboundedPreceding, 0)) - F.col("n")
    own = g.withColumn("below", run).join(F.broadcast(totals), [*by, "part"])
    out = own.groupBy(*by).agg(F.sum(F.col("p") * (2 * (F.col("before") + F.col("below")) + F.col("n"))).alias("a"), F.sum("p").alias("p"), F.sum("n").alias("n"))
    return out.select(*by, F.when((F.col("p") > 0) & (F.col("n") > 0), F.col("a") / (2.0 * F.col("p") * F.col("n"))).alias("area"))


def mae(df: DataFrame, y: str = "y", score: str = "score", by: tuple[str, ...] = ()) -> DataFrame:
    """A2, T2."""
    return df.groupBy(*by).agg(F.avg(F.abs(F.col(score) - F.col(y))).alias("mae"))


def bce(df: DataFrame, y: str = "y", logit: str = "logit") -> DataFrame:
    """Cross-entropy on logits in its stable form."""
    z = F.col(logit)
    return df.agg(F.avg(F.greatest(z, F.lit(0.0)) - z * F.col(y) + F.log1p(F.exp(-F.abs(z)))).alias("bce"))


def relative_gain(base, augmented, higher_is_better):
    """A3 as a column: relative improvement, or relative reduction for errors."""
    return F.when(higher_is_better, (augmented - base) / base).otherwise((base - augmented) / base)


def mean_of_runs(runs: DataFrame) -> DataFrame:
    """A4: (model_id, task, n, mean, sd)."""
    return runs.groupBy("model_id", "task").agg(F.count("*").alias("n_runs"), F.round(F.avg("metric"), 6).alias("mean_metric"), F.round(F.stddev_pop("metric"), 6).alias("sd_metric"))


def gain_summary(gains: DataFrame) -> DataFrame:
    """Gains by group and task type."""
    return gains.groupBy("grp", "kind").agg(F.count("*").alias("n"), F.round(F.avg("gain"), 6).alias("mean_gain"), F.round(F.expr("percentile(gain, 0.5)"), 6).alias("median_gain"))


def budget_curve(trials: DataFrame) -> DataFrame:
    """Best skill so far against the number of trials of a search."""
    w = Window.partitionBy("search").orderBy("trial").rowsBetween(Window.unboundedPreceding, 0)
    return trials.select("search", "trial", F.max("skill").over(w).alias("best"))


def one_hot_width(stats: DataFrame) -> DataFrame:
    """Columns a one-hot coding needs, from (column_name, kind, n_distinct)."""
    return stats.agg(F.sum(F.when(F.col("kind") == "categorical", F.col("n_distinct")).otherwise(1)).alias("width"))


def dispatch_report(decisions: DataFrame) -> DataFrame:
    """Share augmented and skill lost against the better choice, from (direct, augmented, decision)."""
    got = F.when(F.col("decision") == "augment", F.col("augmented")).otherwise(F.col("direct"))
    return decisions.agg(F.round(F.avg(F.when(F.col("decision") == "augment", 1.0).otherwise(0.0)), 6).alias("augment_rate"), F.round(F.avg(F.greatest("direct", "augmented") - got), 6).alias("regret"))


def latency(df: DataFrame, repeats: int = 3) -> float:
    """Seconds to produce all rows, best of ``repeats`` after a warm-up."""
    df.write.format("noop").mode("overwrite").save()
    best = float("inf")
    for _ in range(repeats):
        t = time.perf_counter()
        df.write.format("noop").mode("overwrite").save()
        best = min(best, time.perf_counter() - t)
    return best


def plan_costs(df: DataFrame) -> dict[str, int]:
    """Operators of the physical plan that cost most at scale."""
    text = df._jdf.queryExecution().executedPlan().toString()
    return {k: text.count(k) for k in ("Exchange", "BroadcastExchange", "SortMergeJoin", "BroadcastHashJoin", "WindowGroupLimit", "CartesianProduct", "ArrowEvalPython", "MapInPandas")}
