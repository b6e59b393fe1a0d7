"""Exact quantiles without one buffer of all values: counts per value, ranges of the value, prefix sums."""

from __future__ import annotations

from functools import reduce

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F


def quantiles(df: DataFrame, value: str, q: dict[str, float], by: tuple[str, ...] = (), parts: int = 64) -> DataFrame:
    """(*by, *q): interpolated quantiles of a number per group, nulls left out; a group without values is
    absent. A group is dealt out over ``parts`` ranges of its values, so its size has no bound."""
    by = list(by)
    g = df.where(F.col(value).isNotNull()).groupBy(*by, F.col(value).alias("_v")).agg(F.count("*").alias("_n"))
    if not by:
        g, by = g.withColumn("_all", F.lit(0)), ["_all"]

    def meet(a, b, more=()):
        cols = [*by, *more]
        b = b.select(*(F.col(c).alias(f"_r{i}") for i, c in enumerate(cols)), *(c for c in b.columns if c not in cols))
        on = reduce(lambda x, y: x & y, (a[c].eqNullSafe(b[f"_r{i}"]) for i, c in enumerate(cols)))
        return a.join(b, on).drop(*(f"_r{i}" for i in range(len(cols))))

    cuts = g.groupBy(*by).agg(F.percentile_approx("_v", [i / parts for i in range(1, parts)], 1000).alias("_cuts"))
    g = meet(g, cuts).withColumn("_part", F.size(F.filter("_cuts", lambda c: c < F.col("_v")))).drop("_cuts")
    sums = g.groupBy(*by, "_part").agg(F.sum("_n").alias("_m"))  # at most ``parts`` rows a group
    own = Window.partitionBy(*by)
    before = F.coalesce(F.sum("_m").over(own.orderBy("_part").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0))
    sums = sums.select(*by, "_part", before.alias("_before"), F.sum("_m").over(own).alias("_total"))
    run = F.sum("_n").over(Window.partitionBy(*by, "_part").orderBy("_v").rowsBetween(Window.unboundedPreceding, 0))
    g = meet(g.withColumn("_run", run), sums, ["_part"]).withColumn("_upto", F.col("_before") + F.col("_run"))
    place = {n: F.lit(float(x)) * (F.col("_total") - 1) for n, x in q.items()}
    at = lambda p: F.min(F.when(F.col("_upto") > p, F.col("_v").cast("double")))
    ends = [c for n, p in place.items() for c in (at(F.floor(p)).alias(f"{n}_lo"), at(F.ceil(p)).alias(f"{n}_hi"), F.max(p - F.floor(p)).alias(f"{n}_w"))]
    out = g.groupBy(*by).agg(*ends)
    made = [(F.col(f"{n}_lo") + F.col(f"{n}_w") * (F.col(f"{n}_hi") - F.col(f"{n}_lo"))).alias(n) for n in q]
    return out.select(*(c for c in by if c != "_all"), *made)
