"""Choosing between a base model alone and its augmentation."""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from relmodel.nn import tape as t
from relmodel.nn.relational import Batch

BETA, EPSILON, PROBE = 0.3, 0.05, 256


def probe_batch(labels: DataFrame, n: int = PROBE, stratify: bool = True, seed: int = 0) -> DataFrame:
    """A small labelled batch in a fixed pseudo-random order, half of each class if stratified."""
    h = F.md5(F.concat(F.lit(f"{seed}:"), F.col("entity_id").cast("string")).cast("binary"))
    if not stratify:
        return labels.orderBy(h, "entity_id").limit(n)
    w = Window.partitionBy(F.col("y") > 0).orderBy("h", "entity_id")
    return labels.withColumn("h", h).withColumn("rn", F.row_number().over(w)).where(F.col("rn") <= n // 2).drop("h", "rn")


def _grads(model, params, batch):
    loss, p = model.loss(params, batch)
    t.backward(loss)
    return {k: v.g for k, v in p.items() if v.g is not None}


def proxies(model, batch: Batch, params: dict | None = None) -> dict[str, float]:
    """Training-free scores at the starting weights, from one labelled batch.

    grad_norm: sum over parameters of the gradient's length. snip: sum of |w g|. synflow: sum of w g
    for all-one inputs and absolute weights. naswot: log-determinant of how often two examples'
    hidden signs agree. fisher: squared activation times gradient, here of the native vector. grasp:
    -w (H g), the Hessian product by a difference of gradients."""
    params = params or model.start()
    g = _grads(model, params, batch)
    out = {"grad_norm": float(sum(np.linalg.norm(x) for x in g.values())), "snip": float(sum(np.abs(params[k] * x).sum() for k, x in g.items()))}
    ones = Batch({n: np.ones_like(v) for n, v in batch.num.items()}, {n: np.zeros_like(v) for n, v in batch.cat.items()}, batch.edges, batch.seeds, batch.y, batch.owner)
    p = {k: t.Var(np.abs(v)) for k, v in params.items()}
    z, y = model.base.run(p, ones.num[model.c.target], ones.cat[model.c.target])
    t.backward(t.total(y))
    flow = sum((v.v * v.g).sum() for v in p.values() if v.g is not None)
    out["synflow"] = float(np.sign(flow) * np.log1p(abs(flow)))
    p = {k: t.Var(v) for k, v in params.items()}
    z, y = model.base.run(p, batch.num[model.c.target], batch.cat[model.c.target])
    sign = (z.v > 0).astype(float)
    same = sign @ sign.T + (1 - sign) @ (1 - sign).T
    out["naswot"] = float(np.linalg.slogdet(same + 1e-6 * np.eye(len(same)))[1])
    loss = t.mean(t.softplus(y) - y * batch.y) if model.c.task == "binary" else t.mean(t.absolute(y - batch.y))
    t.backward(loss)
    out["fisher"] = float(((z.v * z.g).mean(axis=0) ** 2).sum())
    step = 1e-3 / (np.sqrt(sum((x**2).sum() for x in g.values())) + 1e-12)
    moved = _grads(model, {k: v + step * g.get(k, 0.0) for k, v in params.items()}, batch)
    out["grasp"] = float(-sum((params[k] * (moved[k] - g[k]) / step).sum() for k in g if k in moved))
    return out


def holdout_probe(fit_predict, x: np.ndarray, y: np.ndarray, task: str) -> float:
    """C8, for bases without gradients: fitted on half of the batch, skill on the other half."""
    from relmodel.nn.grid import area

    half = len(y) // 2
    s = fit_predict(x[:half], y[:half], x[half:])
    if task == "binary":
        return area(y[half:], s)
    floor = np.abs(y[half:] - np.median(y[:half])).mean()
    return float(1 - np.abs(y[half:] - s).mean() / floor) if floor else 0.0


def score_pool(spark, configs: list[tuple[str, object]], rows: list[dict], augmented: bool = False) -> DataFrame:
    """(model_id, proxy, raw), one task a candidate; the batch (at most PROBE rows) is broadcast."""
    import pandas as pd

    from relmodel.nn.relational import unroll
    from relmodel.nn.train import model_of

    shared = spark.sparkContext.broadcast((dict(configs), rows))
    todo = spark.createDataFrame([(m,) for m, _ in configs], "model_id string").repartition(len(configs), "model_id")

    def run(frames):
        models, batch = shared.value
        for pdf in frames:
            for m in pdf["model_id"]:
                got = proxies(model_of(models[m], augmented), unroll(batch, models[m]))
                yield pd.DataFrame({"model_id": m, "proxy": list(got), "raw": list(got.values())})

    return todo.mapInPandas(run, "model_id string, proxy string, raw double")


def combine_proxies(raw: DataFrame, which=("grad_norm", "naswot")) -> DataFrame:
    """(model_id, score): mean of the percent ranks within the chosen proxies."""
    w = Window.partitionBy("proxy").orderBy("raw")
    own = raw.where(F.col("proxy").isin(*which)).withColumn("r", F.percent_rank().over(w))
    return own.groupBy("model_id").agg(F.round(F.avg("r"), 9).alias("score"))


def calibrate(raw: DataFrame, past: DataFrame, parts: int = 64) -> DataFrame:
    """A raw proxy as its mid-rank share among past raw values of the same proxy; 0.5 without.

    Counts per value and prefix sums in two levels (ranges of the value, then within a range), so no
    score meets every past score. A null raw value is above nothing."""
    asked = raw.select("model_id", "proxy", "raw").distinct()
    known = past.where("raw IS NOT NULL").select("proxy", "raw", F.lit(1).alias("n"))
    g = known.union(asked.where("raw IS NOT NULL").select("proxy", "raw", F.lit(0))).groupBy("proxy", "raw").agg(F.sum("n").alias("n"))
    cuts = g.groupBy("proxy").agg(F.percentile_approx("raw", [i / parts for i in range(1, parts)], 10_000).alias("cuts"))
    g = g.join(cuts, "proxy").withColumn("part", F.size(F.filter("cuts", lambda c: c < F.col("raw")))).drop("cuts")
    sums = g.groupBy("proxy", "part").agg(F.sum("n").alias("m"))
    own = Window.partitionBy("proxy")
    sums = sums.select("proxy", "part", F.coalesce(F.sum("m").over(own.orderBy("part").rowsBetween(Window.unboundedPreceding, -1)), F.lit(0)).alias("before"), F.sum("m").over(own).alias("total"))  # at most ``parts`` rows a proxy
    run = F.sum("n").over(Window.partitionBy("proxy", "part").orderBy("raw").rowsBetween(Window.unboundedPreceding, 0))
    rank = g.withColumn("upto", run).join(sums, ["proxy", "part"]).select("proxy", "raw", (F.col("before") + F.col("upto") - F.col("n") / 2).alias("rank"))
    out = asked.join(rank, ["proxy", "raw"], "left").join(known.groupBy("proxy").agg(F.count("*").alias("total")), "proxy", "left")
    share = F.when(F.col("total") > 0, F.coalesce("rank", F.lit(0.0)) / F.col("total"))
    return out.select("model_id", "proxy", "raw", F.coalesce(share, F.lit(0.5)).alias("score"))


def expected_skill(shares: DataFrame, past: DataFrame) -> DataFrame:
    """D13 on the ledger's scale: (model_id, score) from calibrated proxies (model_id, proxy, score) and
    the skills (model_id, perf) that the base alone reached before: the mean share of its proxies, read
    as a place between the least and the greatest of them. A model without past runs has no score."""
    own = past.groupBy("model_id").agg(F.min("perf").alias("lo"), F.max("perf").alias("hi"))
    mean = shares.groupBy("model_id").agg(F.avg("score").alias("share"))
    return mean.join(own, "model_id").select("model_id", (F.col("lo") + F.col("share") * (F.col("hi") - F.col("lo"))).alias("score"))


def strategies(runs: DataFrame, decided: DataFrame, static: DataFrame, general: str) -> DataFrame:
    """(strategy, task_key, decision, skill, trained) of each way to answer the tasks.

    ``runs`` (task_key, model_id, direct, augmented): skills after training for the task. ``decided``
    (task_key, model_id, decision): the dispatcher's choice. ``static`` (task_key, model_id, stale, past):
    the stored pool without new training. Never, always and best keep to the dispatcher's base;
    ``retrain`` trains one general model, augmented, for every task; ``static_pool`` runs the stored
    model that did best before. ``trained`` counts the trainings that the answer needs."""
    own = decided.join(runs, ["task_key", "model_id"])

    def rows(name, df, choice, skill, trained):
        return df.select(F.lit(name).alias("strategy"), "task_key", choice.alias("decision"), skill.alias("skill"), trained.alias("trained"))

    best = F.when(F.col("direct") >= F.col("augmented"), "direct").otherwise("augment")
    skill = lambda c: F.when(c == "augment", F.col("augmented")).otherwise(F.col("direct"))
    pool = static.groupBy("task_key").agg(F.max(F.struct("past", "model_id", "stale")).alias("b"))
    out = rows("never", own, F.lit("direct"), F.col("direct"), F.lit(1)).unionAll(rows("always", own, F.lit("augment"), F.col("augmented"), F.lit(1)))
    out = out.unionAll(rows("conditional", own, F.col("decision"), skill(F.col("decision")), F.lit(1))).unionAll(rows("best", own, best, skill(best), F.lit(2)))
    out = out.unionAll(rows("retrain", runs.where(F.col("model_id") == general), F.lit("augment"), F.col("augmented"), F.lit(1)))
    return out.unionAll(rows("static_pool", pool, F.lit("direct"), F.col("b.stale"), F.lit(0)))


def select_base(scores: DataFrame) -> DataFrame:
    """C11: the best candidate; ties go to the first name."""
    return scores.orderBy(F.desc("score"), "model_id").limit(1)


def ema(ledger: DataFrame, beta: float = BETA) -> DataFrame:
    """(model_id, task_key, ema) in closed form: one weighted sum, no recursion."""
    n = Window.partitionBy("model_id", "task_key")
    age = F.count("*").over(n) - F.row_number().over(n.orderBy("step"))
    first = F.row_number().over(n.orderBy("step")) == 1
    weight = F.pow(F.lit(1 - beta), age) * F.when(first, 1.0).otherwise(beta)
    return ledger.withColumn("w", weight).groupBy("model_id", "task_key").agg(F.sum(F.col("w") * F.col("perf")).alias("ema"))


def ema_running(ledger: DataFrame, beta: float = BETA) -> DataFrame:
    """C12 after every step: (model_id, task_key, step, ema)."""
    w = Window.partitionBy("model_id", "task_key").orderBy("step").rowsBetween(Window.unboundedPreceding, 0)
    own = ledger.withColumn("xs", F.collect_list("perf").over(w))
    run = F.aggregate(F.slice("xs", 2, F.greatest(F.size("xs") - 1, F.lit(0))), F.col("xs")[0], lambda m, x: m * F.lit(1 - beta) + x * F.lit(beta))
    return own.select("model_id", "task_key", "step", run.alias("ema"))


@dataclass(frozen=True)
class Decision:
    model_id: str
    score: float
    threshold: float | None
    action: str  # direct or augment
    reason: str


def decisions(best: DataFrame, averages: DataFrame, epsilon: float = EPSILON, mode: str = "conditional") -> DataFrame:
    """(model_id, task_key, score, threshold, decision, reason); ``best`` has model_id,
    task_key, score. No history: augment. Modes always/never are the two ends of the trade-off."""
    own = best.join(averages, ["model_id", "task_key"], "left").withColumn("threshold", (1 - F.lit(epsilon)) * F.col("ema"))
    ok = F.col("score") >= F.col("threshold")
    if mode != "conditional":
        return own.select("model_id", "task_key", "score", "threshold", F.lit("augment" if mode == "always" else "direct").alias("decision"), F.lit(mode).alias("reason"))
    choice = F.when(F.col("ema").isNull(), "augment").when(ok, "direct").otherwise("augment")
    reason = F.when(F.col("ema").isNull(), "no_history").when(ok, "direct").otherwise("augment")
    return own.select("model_id", "task_key", "score", "threshold", choice.alias("decision"), reason.alias("reason"))


def decide(score: float, average: float | None, model_id: str = "", epsilon: float = EPSILON) -> Decision:
    """The same rule for one model on the driver."""
    if average is None:
        return Decision(model_id, score, None, "augment", "no_history")
    limit = (1 - epsilon) * average
    return Decision(model_id, score, limit, *(("direct", "direct") if score >= limit else ("augment", "augment")))
