"""Many small trainings at once: configurations are rows, each task trains one on the broadcast,
bounded set of packed rows (T5, T7, B13, B14, W11-W17)."""

from __future__ import annotations

import json
import pickle
import time

import numpy as np
import pandas as pd
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import functions as F

from relmodel.nn.bases import Constant, InContext, TwoStage, UnsupportedTask
from relmodel.nn.relational import Config, importance, param_count, unroll, unroll_arrow
from relmodel.nn.train import TrainConfig, fit, model_of, packed_parts, rows_of
from relmodel.operators.metrics import mae, roc_area

MOST = 100_000


def area(y, s) -> float:
    """A1 on arrays; ties count half."""
    y, s = np.asarray(y) > 0, np.asarray(s, float)
    if y.all() or not y.any():
        return float("nan")
    _, inv, n = np.unique(s, return_inverse=True, return_counts=True)
    rank = (np.cumsum(n) - (n - 1) / 2)[inv]
    return float((rank[y].sum() - y.sum() * (y.sum() + 1) / 2) / (y.sum() * (~y).sum()))


def measure(task: str, y, s) -> float:
    return area(y, s) if task == "binary" else float(np.abs(np.asarray(y) - s).mean())


def flat_features(rows) -> np.ndarray:
    """x and c of packed rows (dicts, or an Arrow batch) side by side."""
    if isinstance(rows, pa.RecordBatch):
        return np.hstack([rows.column(k).flatten().to_numpy(zero_copy_only=False).astype(float).reshape(rows.num_rows, -1) for k in ("x", "c")])
    return np.array([list(r["x"]) + list(r.get("c", ())) for r in rows], float)


def fit_one(rows: list[dict], spec: dict, schemas, steps) -> tuple[dict, tuple | None]:
    """Trains one configuration: (figures, what ``predict_one`` needs or None where the model cannot
    do the task)."""
    spec = dict(spec)
    kind, augmented, train = spec.pop("base", "residual"), spec.pop("augmented", True), spec.pop("train", {})
    part = {s: [r for r in rows if r["split"] == s] for s in ("train", "valid")}
    began = time.perf_counter()
    simple = {"constant": Constant, "incontext": InContext, "two_stage_incontext": TwoStage}
    if kind in simple:
        try:
            m = simple[kind](spec.get("task", "binary")).fit(flat_features(part["train"]), [r["y"] for r in part["train"]])
        except UnsupportedTask:
            return {"valid": float("nan"), "n_params": 0, "seconds": 0.0}, None
        return {"valid": float("nan"), "n_params": 0, "seconds": time.perf_counter() - began}, (m, None, None)
    if (first := spec.pop("first", None)) is not None:  # of a sample of one hop, which holds the smaller ones
        part = {s: [r | {u.relation: (r.get(u.relation) or [])[:first] for u in steps} for r in v] for s, v in part.items()}
        spec["extra"] = {"first": first}
    hops = spec.pop("hops", None)
    use = steps if hops is None else tuple(s for s in steps if hops >= 2 or s.source == spec["target"])
    c = Config(schemas={n: s for n, s in schemas.items() if n == spec["target"] or any(n == u.table for u in use)}, steps=use, base=kind, **spec)
    params, hist = fit(model_of(c, augmented), part["train"], part["valid"], TrainConfig(**({"seed": c.seed} | train)))
    return {"valid": float(min(hist)), "n_params": param_count(params), "seconds": time.perf_counter() - began}, (params, c, augmented)


def predict_one(state: tuple, rows, known: dict | None = None) -> tuple:
    """(scores, importance of signals or None, their names). ``known`` keeps what models that read the
    same tables unroll from the same rows."""
    fitted, c, augmented = state
    if c is None:
        return np.asarray(fitted.predict(flat_features(rows)), float), None, []
    known, key = {} if known is None else known, (c.steps, c.use_relations, tuple(c.schemas), c.extra.get("first"))
    if key not in known:
        known[key] = unroll_arrow(_shortened(rows, c), c) if isinstance(rows, pa.RecordBatch) else unroll(rows, c)
    s, alpha, names = model_of(c, augmented).predict(fitted, known[key])
    return np.asarray(s, float), None if alpha is None else importance(alpha), names


def _shortened(rows, c: Config):
    """The first ``extra["first"]`` neighbours of each packed row of an Arrow batch."""
    if (first := c.extra.get("first")) is None:
        return rows
    cut = {s.relation: pc.list_slice(rows.column(s.relation), 0, first) for s in c.steps}
    return pa.RecordBatch.from_pydict({n: cut.get(n, rows.column(n)) for n in rows.schema.names})


def strongest(mean, names) -> str:
    return ",".join(names[i] for i in np.argsort(-np.asarray(mean, float))[:4])


def run_one(rows: list[dict], spec: dict, schemas, steps) -> dict:
    """Trains and tests one configuration; metric is NaN where the model cannot do the task."""
    out, state = fit_one(rows, spec, schemas, steps)
    test = [r for r in rows if r["split"] == "test"]
    if state is None:
        return {"metric": float("nan"), **out, "top": ""}
    s, imp, names = predict_one(state, test)
    top = "" if imp is None else strongest(np.nanmean(imp, axis=0), names)
    return {"metric": measure(spec.get("task", "binary"), [r["y"] for r in test], s), **out, "top": top}


def run_grid(packed, specs: list[dict], schemas, steps, test=None):
    """(config, metric, valid, n_params, seconds, top) per configuration.

    Trained on ``packed``, which one worker must hold. With ``test``, packed rows of any number, all
    of these are scored in executors and the metric is theirs; else it is that of the test part of
    ``packed``."""
    if test is not None:
        return tested(packed.sparkSession, fitted(packed, specs, schemas, steps), test)
    rows, todo = _trainings(packed, specs)

    def run(frames):
        for pdf in frames:
            for config in pdf["config"]:
                yield pd.DataFrame([{"config": config} | run_one(rows.value, json.loads(config), schemas, steps)])

    return todo.mapInPandas(run, OUT)


def _trainings(packed, specs: list[dict]):
    """(broadcast rows, one row a configuration)."""
    spark = packed.sparkSession
    got = packed.limit(MOST + 1).collect()
    if len(got) > MOST:
        raise ValueError("more packed rows than one worker trains on; sample seeds first")
    got = sorted(got, key=lambda r: (r["split"], r["seed_id"]))  # mini-batches do not hang on the plan
    rows = spark.sparkContext.broadcast(rows_of(got))
    todo = spark.sparkContext.parallelize([(i, json.dumps(s)) for i, s in enumerate(specs)], len(specs))  # one a task; by hash some would meet
    return rows, spark.createDataFrame(todo, "i int, config string")


def fitted(packed, specs: list[dict], schemas, steps) -> list:
    """The configurations trained on ``packed``: one row each, its model in ``state``."""
    rows, todo = _trainings(packed, specs)

    def train(frames):
        for pdf in frames:
            for i, config in zip(pdf["i"], pdf["config"]):
                out, state = fit_one(rows.value, json.loads(config), schemas, steps)
                yield pd.DataFrame([{"i": i, "config": config, **out, "state": pickle.dumps(state)}])

    return sorted(todo.mapInPandas(train, "i int, config string, valid double, n_params long, seconds double, state binary").collect(), key=lambda r: r.i)  # one row a configuration


def tested(spark, models: list, test):
    """Rows of ``OUT`` of fitted configurations, in their order, over one pass of ``test``."""
    found = test_figures(test, {i: pickle.loads(r.state) for i, r in enumerate(models)}, {i: json.loads(r.config).get("task", "binary") for i, r in enumerate(models)})
    return spark.createDataFrame([(r.config, found[i][0], r.valid, r.n_params, r.seconds, found[i][1]) for i, r in enumerate(models)], OUT)


OUT = "config string, metric double, valid double, n_params long, seconds double, top string"


def test_figures(test, states: dict, tasks: dict) -> dict[int, tuple[float, str]]:
    """{i: (metric, strongest signals)} of fitted models over all rows of ``test``; only scores and sums of
    importances (one a part of the rows, in its first row) leave Python and only figures the executors."""
    shared = test.sparkSession.sparkContext.broadcast(states)

    def run(batches):
        for part in packed_parts(batches):
            known: dict = {}
            for i, state in shared.value.items():
                if state is None:
                    continue
                s, imp, names = predict_one(state, part, known)
                sums = [] if imp is None else [{"name": n, "v": float(np.nansum(v)), "n": int((~np.isnan(v)).sum())} for n, v in zip(names, imp.T)]
                kind = pa.list_(pa.struct([("name", pa.string()), ("v", pa.float64()), ("n", pa.int64())]))
                signals = pa.array([sums] + [None] * (part.num_rows - 1), kind)
                yield pa.RecordBatch.from_arrays([pa.array([i] * part.num_rows, pa.int32()), part.column("y").cast(pa.float64()), pa.array(s), signals], names=["i", "y", "s", "signals"])

    scored = test.mapInArrow(run, "i int, y double, s double, signals array<struct<name:string,v:double,n:long>>").persist()
    tops: dict[int, list] = {}
    for r in scored.select("i", F.explode("signals").alias("g")).groupBy("i", "g.name").agg(F.try_divide(F.sum("g.v"), F.sum("g.n")).alias("v")).collect():  # one row a signal
        tops.setdefault(r.i, []).append((-(r.v if r.v is not None else -np.inf), r.name))
    binary = [i for i in states if tasks[i] == "binary"]
    figures = {}
    if binary:
        figures |= {r.i: r.area for r in roc_area(scored.where(F.col("i").isin(binary)), "y", "s", by=("i",)).collect()}  # one row a model
    if len(binary) < len(states):
        figures |= {r.i: r.mae for r in mae(scored.where(~F.col("i").isin(binary)), "y", "s", by=("i",)).collect()}
    scored.unpersist()
    nan = float("nan")
    return {i: (nan if figures.get(i) is None else figures[i], ",".join(n for _, n in sorted(tops.get(i, []))[:4])) for i in states}


# ---- search (B13, B14) --------------------------------------------------------------------------


def tpe_order(trials: list[tuple[dict, float]], space: dict[str, list], n: int, seed: int = 0, gamma: float = 0.25) -> list[dict]:
    """The next ``n`` points to try: sampled from the density of the good trials, ranked by the
    ratio of good to other density (discrete space, one count per value added)."""
    r = np.random.default_rng(seed)
    if len(trials) < 4:
        return [{k: v[r.integers(len(v))] for k, v in space.items()} for _ in range(n)]
    ranked = sorted(trials, key=lambda x: x[1])
    cut = max(1, int(np.ceil(gamma * len(ranked))))
    density = []
    for part in (ranked[:cut], ranked[cut:]):
        density.append({k: np.array([1 + sum(c[k] == x for c, _ in part) for x in v], float) for k, v in space.items()})
    good, rest = ({k: v / v.sum() for k, v in d.items()} for d in density)
    points = [{k: v[r.choice(len(v), p=good[k])] for k, v in space.items()} for _ in range(8 * n)]
    ratio = lambda p: sum(np.log(good[k][v.index(p[k])] / rest[k][v.index(p[k])]) for k, v in space.items())
    seen, out = set(), []
    for p in sorted(points, key=ratio, reverse=True):
        if (key := json.dumps(p, sort_keys=True)) not in seen:
            seen.add(key)
            out.append(p)
    return out[:n]


def tpe_search(packed, base_spec: dict, space: dict[str, list], schemas, steps, rounds: int = 3, width: int = 4) -> list[tuple[dict, float]]:
    """B13 on Spark: each round's trials run in parallel, one a row."""
    trials: list[tuple[dict, float]] = []
    for k in range(rounds):
        points = tpe_order(trials, space, width, seed=k)
        out = run_grid(packed, [base_spec | p for p in points], schemas, steps).collect()
        trials += [({k2: json.loads(r.config)[k2] for k2 in space}, r.valid) for r in out]
    return sorted(trials, key=lambda x: x[1])


def two_phase_search(packed, base_spec: dict, space: dict[str, list], schemas, steps, sample: int = 12, keep: int = 4, seed: int = 0) -> list[tuple[dict, float]]:
    """Training-free scores, one task a point, filter a sample of points; then successive halving
    with doubled epochs."""
    from relmodel.plans.dispatch import score_pool

    r = np.random.default_rng(seed)
    drawn = [{k: v[r.integers(len(v))] for k, v in space.items()} for _ in range(sample)]
    points = [json.loads(x) for x in dict.fromkeys(json.dumps(p) for p in drawn)]
    rows = rows_of(packed.where("split = 'train'").limit(256).collect())  # the probe batch, bounded
    pool = [(str(i), Config(schemas=schemas, steps=steps, **{k: v for k, v in (base_spec | p).items() if k not in ("augmented", "train", "hops")})) for i, p in enumerate(points)]
    raw = score_pool(packed.sparkSession, pool, rows, base_spec.get("augmented", True)).where("proxy = 'grad_norm'").collect()  # one row a point
    left = [points[int(x.model_id)] for x in sorted(raw, key=lambda x: (-x.raw, int(x.model_id)))[:keep]]
    epochs, trials = 4, []
    while left:
        out = run_grid(packed, [base_spec | p | {"train": {"epochs": epochs}} for p in left], schemas, steps).collect()
        trials = sorted((({k: json.loads(x.config)[k] for k in space}, x.valid) for x in out), key=lambda x: x[1])
        if len(left) == 1:
            break
        left, epochs = [p for p, _ in trials[: max(1, len(left) // 2)]], 2 * epochs
    return trials
