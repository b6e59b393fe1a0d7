"""Contextual signals, their sequence and importance."""

from __future__ import annotations

from functools import reduce

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from relmodel.functions.quantile import quantiles

SIGNALS = ("max", "min", "sum", "mean")


def context_signals(nbrs: DataFrame, columns: list[str], prefix: str, exact: bool = False) -> DataFrame:
    """per node the four aggregates of each neighbour column, in one shuffle. ``exact`` sums
    two-digit money as decimals, so the order of addition cannot show."""
    out = [F.count("*").alias(f"{prefix}_n")]
    for c in columns:
        total = F.sum(F.col(c).cast("decimal(18,2)")).cast("double") if exact else F.sum(F.col(c).cast("double"))
        mean = total / F.count(c) if exact else F.avg(F.col(c).cast("double"))
        for a, x in zip(SIGNALS, (F.max(F.col(c).cast("double")), F.min(F.col(c).cast("double")), total, mean)):
            out.append(x.alias(f"{prefix}_{a}_{c}"))
    return nbrs.groupBy("node_id").agg(*out)


def relational_features(target: DataFrame, signals: list[DataFrame]) -> DataFrame:
    """a target table (node_id, …) with the signals of each relation beside it."""
    return reduce(lambda a, b: a.join(b, "node_id", "left"), signals, target)


def signal_sequence(target: DataFrame, relations: dict[str, DataFrame]) -> DataFrame:
    """(node_id, pos, signal) in fixed order: itself, then per relation by name the four
    aggregates; relations without neighbours are left out."""
    names = F.array(F.lit("self"))
    out = target.select("node_id")
    for r, nbrs in sorted(relations.items()):
        out = out.join(nbrs.select("node_id").distinct().withColumn(f"has_{r}", F.lit(True)), "node_id", "left")
        names = F.concat(names, F.when(F.col(f"has_{r}"), F.array(*(F.lit(f"{r}({a})") for a in SIGNALS))).otherwise(F.array().cast("array<string>")))
    return out.select("node_id", F.posexplode(names).alias("pos", "signal"))


def recalibrate(alpha, n):
    """excess of a weight over the uniform one, on a scale that does not depend on the length."""
    share = F.lit(1.0) / n
    return F.when(n > 1, F.greatest((alpha - share) / (1 - share), F.lit(0.0))).otherwise(0.0)


def rank_signals(importance: DataFrame, top: int = 4) -> DataFrame:
    """(signal, n, mean, q25, q75, place) of the ``top`` signals by mean importance."""
    own = importance.groupBy("signal").agg(F.count("*").alias("n"), F.round(F.avg("importance"), 6).alias("mean_importance"))
    spread = quantiles(importance, "importance", {"q25": 0.25, "q75": 0.75}, ("signal",)).withColumnRenamed("signal", "name")
    own = own.join(spread, own.signal.eqNullSafe(spread.name), "left").select("signal", "n", "mean_importance", F.round("q25", 6).alias("q25"), F.round("q75", 6).alias("q75"))
    from pyspark.sql import Window

    return own.withColumn("place", F.dense_rank().over(Window.orderBy(F.desc("mean_importance")))).where(F.col("place") <= top)  # one row a signal
