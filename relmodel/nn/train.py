"""Training (T3-T11): AdamW, early stopping, and three ways to spread it over Spark."""

from __future__ import annotations

import pickle
from dataclasses import dataclass

import numpy as np

from relmodel.nn import tape as t
from relmodel.nn.relational import BaseModel, Config, RelationalModel, unroll, unroll_arrow


@dataclass(frozen=True)
class TrainConfig:
    rate: float = 0.01
    decay: float = 1e-4
    batch: int = 256
    epochs: int = 40
    patience: int = 5
    seed: int = 0
    freeze: tuple[str, ...] = ()  # parameter name prefixes (P10, T3)


class AdamW:
    """T4: decoupled weight decay."""

    def __init__(self, rate: float, decay: float):
        self.rate, self.decay, self.m, self.v, self.n = rate, decay, {}, {}, 0

    def step(self, p: dict[str, np.ndarray], g: dict[str, np.ndarray]) -> dict[str, np.ndarray]:
        self.n += 1
        out = dict(p)
        for k, x in g.items():
            m = self.m[k] = 0.9 * self.m.get(k, 0.0) + 0.1 * x
            v = self.v[k] = 0.999 * self.v.get(k, 0.0) + 0.001 * x * x
            out[k] = p[k] - self.rate * (m / (1 - 0.9**self.n) / (np.sqrt(v / (1 - 0.999**self.n)) + 1e-8) + self.decay * p[k])
        return out


class EarlyStop:
    """Keeps the best parameters; ``done`` after ``patience`` rounds without a better one."""

    def __init__(self, patience: int):
        self.patience, self.best, self.params, self.bad = patience, np.inf, None, 0

    def see(self, loss: float, params) -> bool:
        if loss < self.best - 1e-9:
            self.best, self.params, self.bad = loss, params, 0
        else:
            self.bad += 1
        return self.bad >= self.patience


def model_of(c: Config, augmented: bool = True):
    return RelationalModel(c) if augmented else BaseModel(c)


def gradients(model, params, batch, freeze=()):
    loss, p = model.loss(params, batch)
    t.backward(loss)
    g = {k: v.g for k, v in p.items() if v.g is not None and not k.startswith(freeze or ("\0",))}
    return float(loss.v), g


def mean_loss(model, params, rows, size: int = 512) -> float:
    n = s = 0
    for i in range(0, len(rows), size):
        part = rows[i : i + size]
        s += float(model.loss(params, unroll(part, model.c))[0].v) * len(part)
        n += len(part)
    return s / max(n, 1)


def fit(model, train: list[dict], valid: list[dict], cfg: TrainConfig, start: dict | None = None) -> tuple[dict, list[float]]:
    """One worker, mini-batches; returns the best parameters by validation loss and the history."""
    params, opt, stop, r = start or model.start(), AdamW(cfg.rate, cfg.decay), EarlyStop(cfg.patience), np.random.default_rng(cfg.seed)
    history = []
    for _ in range(cfg.epochs):
        order = r.permutation(len(train))
        for i in range(0, len(order), cfg.batch):
            _, g = gradients(model, params, unroll([train[j] for j in order[i : i + cfg.batch]], model.c), cfg.freeze)
            params = opt.step(params, g)
        history.append(mean_loss(model, params, valid or train))
        if stop.see(history[-1], params):
            break
    return stop.params or params, history


def pretrain(model, rows: list[dict], cfg: TrainConfig, share: float = 0.3) -> tuple[dict, list[float]]:
    """The encoder learns to fill in masked attributes; the result starts later tasks."""
    from relmodel.nn.layers import dense

    r, c = np.random.default_rng(cfg.seed), model.c
    params, opt, history = model.start(), AdamW(cfg.rate, cfg.decay), []
    dense(r, params, "pre.out", 2 * c.d, len(c.schemas[c.target].numerical))
    for _ in range(cfg.epochs):
        order, losses = r.permutation(len(rows)), []
        for i in range(0, len(order), cfg.batch):
            b = unroll([rows[j] for j in order[i : i + cfg.batch]], c)
            loss, p = model.reconstruct(params, b, r.random(b.num[c.target].shape) < share)
            t.backward(loss)
            params = opt.step(params, {k: v.g for k, v in p.items() if v.g is not None})
            losses.append(float(loss.v))
        history.append(float(np.mean(losses)))
    return {k: v for k, v in params.items() if not k.startswith("pre.")}, history


def rate_search(model, train: list[dict], valid: list[dict], cfg: TrainConfig, rates=(0.001, 0.00316, 0.01, 0.0316, 0.1)) -> tuple[float, dict]:
    """T5: the learning rate of a log grid with the least validation loss, and its parameters."""
    got = [(min(h), x, p) for x in rates for p, h in [fit(model, train, valid, TrainConfig(**(cfg.__dict__ | {"rate": x})))]]
    _, rate, params = min(got, key=lambda g: g[:2])
    return rate, params


def rows_of(pdf) -> list[dict]:
    """Packed rows of a pandas frame (or list of Row) as plain dicts."""
    out = []
    for r in pdf.to_dict("records") if hasattr(pdf, "to_dict") else [x.asDict(recursive=True) for x in pdf]:
        row = {}
        for k, v in r.items():
            if isinstance(v, (list, np.ndarray)) and len(v) and isinstance(v[0], (dict, tuple)):
                v = [(g["at"], g["x"], g["c"]) if isinstance(g, dict) else tuple(g) for g in v]
            row[k] = v
        out.append(row)
    return out


def fit_grouped(packed, c: Config, cfg: TrainConfig, augmented: bool = True, most: int = 100_000):
    """T7, T8 on Spark: one training per value of column ``run``, each on one executor. The set must
    fit a worker, so its size is checked first. Returns (run, valid_loss, params)."""
    import pandas as pd

    biggest = packed.groupBy("run").count().agg({"count": "max"}).first()[0] or 0
    if biggest > most:
        raise ValueError(f"{biggest} rows a run; use fit_local_sgd beyond {most}")

    def one(pdf: pd.DataFrame) -> pd.DataFrame:
        rows = rows_of(pdf)
        run = int(pdf["run"].iloc[0])
        c2 = Config(**(c.__dict__ | {"seed": run}))
        params, hist = fit(model_of(c2, augmented), [r for r in rows if r["split"] == "train"], [r for r in rows if r["split"] == "valid"], TrainConfig(**(cfg.__dict__ | {"seed": run})))
        return pd.DataFrame({"run": [run], "valid_loss": [min(hist)], "params": [pickle.dumps(params)]})

    return packed.groupBy("run").applyInPandas(one, "run long, valid_loss double, params binary")


def fit_sync(packed, c: Config, cfg: TrainConfig, augmented: bool = True) -> tuple[dict, list[float]]:
    """One step per job: partitions sum their gradients, the sums are added in a tree on the
    executors, the driver steps and broadcasts again."""
    model, sc = model_of(c, augmented), packed.sparkSession.sparkContext
    params, opt, history = model.start(), AdamW(cfg.rate, cfg.decay), []
    for _ in range(cfg.epochs):
        now = sc.broadcast(params)
        n, loss, g = _tree(packed, _partial_gradient(c, augmented, now, cfg.freeze))
        history.append(loss / max(n, 1))
        params = opt.step(params, {k: v / max(n, 1) for k, v in g.items()})
        now.unpersist()
    return params, history


def fit_local_sgd(packed, c: Config, cfg: TrainConfig, augmented: bool = True) -> tuple[dict, list[float]]:
    """One job per epoch: partitions train on their rows, the driver gets the weighted mean."""
    model, sc = model_of(c, augmented), packed.sparkSession.sparkContext
    params, history, stop = model.start(), [], EarlyStop(cfg.patience)
    for epoch in range(cfg.epochs):
        now = sc.broadcast(params)
        n, loss, total = _tree(packed, _partial_epoch(c, augmented, now, cfg, epoch))
        history.append(loss / max(n, 1))
        params = {k: v / max(n, 1) for k, v in total.items()} if n else params
        now.unpersist()
        if stop.see(history[-1], params):
            break
    return stop.params or params, history


def _partial_gradient(c, augmented, now, freeze):
    def run(frames):
        model, n, loss, total = model_of(c, augmented), 0, 0.0, {}
        for pdf in frames:
            rows = rows_of(pdf)
            if not rows:
                continue
            x, g = gradients(model, now.value, unroll(rows, c), freeze)
            n, loss = n + len(rows), loss + x * len(rows)
            total = {k: total.get(k, 0.0) + v * len(rows) for k, v in g.items()}
        return n, loss, total

    return run


def _partial_epoch(c, augmented, now, cfg, epoch):
    def run(frames):
        model, rows = model_of(c, augmented), [r for pdf in frames for r in rows_of(pdf)]
        if not rows:
            return 0, 0.0, {}
        one = TrainConfig(**(cfg.__dict__ | {"epochs": 1, "seed": cfg.seed + 1000 * epoch}))
        params, hist = fit(model, rows, [], one, dict(now.value))
        return len(rows), hist[0] * len(rows), {k: v * len(rows) for k, v in params.items()}

    return run


def _tree(packed, partial, width: int = 8):
    """Partials per partition, added ``width`` at a time, level by level, before the last ``width`` reach
    the driver: no task and no driver holds more than that many."""
    import pandas as pd
    from pyspark.sql import functions as F

    def first(frames):
        yield pd.DataFrame({"x": [pickle.dumps(partial(frames))]})

    def add(key: tuple, pdf: pd.DataFrame) -> pd.DataFrame:
        return pd.DataFrame({"g": [int(key[0])], "x": [pickle.dumps(_plus(map(pickle.loads, pdf["x"])))]})

    left = packed.rdd.getNumPartitions()
    parts = packed.mapInPandas(first, "x binary").select(F.spark_partition_id().alias("g"), "x")
    while left > width:
        left = -(-left // width)
        parts = parts.groupBy(F.pmod("g", F.lit(left)).alias("g")).applyInPandas(add, "g int, x binary")
    return _plus(pickle.loads(r.x) for r in parts.collect())


def _plus(parts):
    n, loss, total = 0, 0.0, {}
    for a, b, g in parts:
        n, loss = n + a, loss + b
        for k, v in g.items():
            total[k] = total.get(k, 0.0) + v
    return n, loss, total


def score(packed, c: Config, params: dict, augmented: bool = True):
    """(seed_id, score, signals): one pass over packed rows, nothing but scores leaves Python."""
    import pyarrow as pa
    from relmodel.nn.relational import importance

    shared = packed.sparkSession.sparkContext.broadcast(params)

    def run(batches):
        model = model_of(c, augmented)
        for part in packed_parts(batches):
            s, alpha, names = model.predict(shared.value, unroll_arrow(part, c))
            imp = importance(alpha) if alpha is not None else np.zeros((len(s), 0))
            sig = [[{"signal": n, "importance": float(v)} for n, v in zip(names, row) if not np.isnan(v)] for row in imp]
            kind = pa.list_(pa.struct([("signal", pa.string()), ("importance", pa.float64())]))
            yield pa.RecordBatch.from_arrays([part.column("seed_id"), pa.array(np.asarray(s, float)), pa.array(sig, kind)], names=["seed_id", "score", "signals"])

    return packed.mapInArrow(run, "seed_id string, score double, signals array<struct<signal:string,importance:double>>")


def packed_parts(batches, most: int = 512):
    """Slices of at most ``most`` packed rows, so ego graphs of any number fit."""
    for b in batches:
        for i in range(0, b.num_rows, most):
            yield b.slice(i, most)
