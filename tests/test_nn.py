"""Tape, layers, base models and training (N oracles): differences, loops and planted signals."""

import numpy as np
import pytest

from relmodel.nn import layers as L
from relmodel.nn import tape as t
from relmodel.nn.bases import NEURAL, Constant, InContext, TwoStage, UnsupportedTask, hashed_text, magnitude_tokens, pairwise
from relmodel.nn.grid import area, tpe_order
from relmodel.nn.relational import BaseModel, Config, RelationalModel, Step, importance, param_count, passing_params, unroll
from relmodel.nn.train import AdamW, EarlyStop, TrainConfig, fit

R = np.random.default_rng(0)


def numeric(f, x, eps=1e-6):
    g = np.zeros_like(x)
    for i in np.ndindex(x.shape):
        a, b = x.copy(), x.copy()
        a[i] += eps
        b[i] -= eps
        g[i] = (f(a) - f(b)) / (2 * eps)
    return g


W = R.standard_normal((4, 3))
IDS = np.array([0, 2, 2, 0, 3])
OPS = {
    "matmul": lambda x: x @ t.Var(W), "relu": t.relu, "tanh": t.tanh, "exp": t.exp, "sigmoid": t.sigmoid, "softplus": t.softplus, "absolute": t.absolute,
    "softmax": t.softmax, "layer_norm": t.layer_norm, "entmax": L.entmax, "take": lambda x: t.take(x, np.array([1, 1, 4])),
    **{f"segment_{h}": (lambda h: lambda x: t.segment(x, IDS, 5, h))(h) for h in ("sum", "mean", "max", "min")},
    "concat": lambda x: t.concat([x, x * 2.0], axis=1), "mean": lambda x: t.mean(x, axis=0), "swap": lambda x: t.swap(x, 0, 1), "mul": lambda x: x * x, "log": lambda x: t.log(x * x + 1.0),
}


@pytest.mark.parametrize("name", OPS)
def test_gradients_equal_differences(name):
    x = R.standard_normal((5, 4))
    weight = R.standard_normal(OPS[name](t.Var(x)).shape)
    v = t.Var(x)
    t.backward(t.total(OPS[name](v) * weight))
    assert np.allclose(v.g, numeric(lambda a: float((OPS[name](t.Var(a)).v * weight).sum()), x), atol=1e-5)


def test_attention_equals_loops_and_ignores_order():
    p = {}
    L.attention_params(R, p, "a", 6)
    v = {k: t.Var(x) for k, x in p.items()}
    x = R.standard_normal((2, 5, 6))
    out, w = L.attention(v, "a", t.Var(x), 2)
    assert np.allclose(w.v.sum(-1), 1)
    q, k, u = (x @ p[f"a.{c}.w"] + p[f"a.{c}.b"] for c in "qkv")
    for b in range(2):
        rows = np.zeros((5, 6))
        for h in range(2):
            s = slice(3 * h, 3 * h + 3)
            z = q[b, :, s] @ k[b, :, s].T / np.sqrt(3)
            e = np.exp(z - z.max(1, keepdims=True))
            rows[:, s] = e / e.sum(1, keepdims=True) @ u[b, :, s]
        assert np.allclose(out.v[b], rows @ p["a.o.w"] + p["a.o.b"])
    order = [0, 3, 1, 4, 2]
    again, _ = L.attention(v, "a", t.Var(x[:, order]), 2)
    assert np.allclose(again.v[:, 0], out.v[:, 0])


def test_pairwise_identity():
    e = R.standard_normal((3, 5, 4))
    want = sum(e[:, i] * e[:, j] for i in range(5) for j in range(i))
    assert np.allclose(pairwise(t.Var(e)).v, want)


def test_tuple_embedding_ignores_attribute_order_and_takes_nulls():
    s = L.Schema(["a", "b", "c"], [("k", 3)])
    p = {}
    L.table_params(R, p, "x", s, 4)
    L.block_params(R, p, "enc0", 4, 8)
    L.norm_params(p, "tuple", 8)
    num, cat = R.standard_normal((6, 3)), R.integers(0, 4, (6, 1))
    num[2, 1] = np.nan
    a = L.tuple_embedding({k: t.Var(v) for k, v in p.items()}, "x", s, num, cat, 1, 2).v
    o = [2, 0, 1]
    q = p | {f"x.{n}": p[f"x.{n}"][o] for n in ("dir", "off", "null")}
    b = L.tuple_embedding({k: t.Var(v) for k, v in q.items()}, "x", s, num[:, o], cat, 1, 2).v
    assert np.allclose(a, b) and np.isfinite(a).all() and a.shape == (6, 8)


def config(**more):
    steps = (Step("order_customer", "customer", "orders"), Step("line_order", "orders", "lineitem"))
    schemas = {"customer": L.Schema(["bal"], [("seg", 3)]), "orders": L.Schema(["price"]), "lineitem": L.Schema(["qty"])}
    return Config(**({"target": "customer", "schemas": schemas, "steps": steps, "d": 4} | more))


def rows(n, seed=0, degree=None):
    r, out = np.random.default_rng(seed), []
    for _ in range(n):
        k = degree if degree is not None else int(r.integers(0, 8))
        orders = [(0, [r.standard_normal()], []) for _ in range(k)]
        lines = [(int(j), [r.standard_normal()], []) for j in range(k) for _ in range(2)]
        out.append({"x": [r.standard_normal()], "c": [int(r.integers(1, 4))], "order_customer": orders, "line_order": lines, "y": float(k > 3)})
    return out


def test_layers_see_exactly_their_hops():
    data = rows(4, degree=3)
    for layers, seen in ((1, False), (2, True)):
        c = config(layers=layers, use_fusion=False)
        m = RelationalModel(c)
        p = m.start()
        a = m.predict(p, unroll(data, c))[0]
        far = [dict(r, line_order=[(at, [x[0] + 5], k) for at, x, k in r["line_order"]]) for r in data]
        assert (not np.allclose(a, m.predict(p, unroll(far, c))[0])) == seen


def test_batching_does_not_matter():
    c = config()
    m = RelationalModel(c)
    p, data = m.start(), rows(12)
    whole = m.predict(p, unroll(data, c))[0]
    assert np.allclose(whole, np.concatenate([m.predict(p, unroll([r], c))[0] for r in data]))


@pytest.mark.parametrize("more", [dict(), dict(use_passing=False), dict(use_fusion=False), dict(use_relations=False), dict(agg="max"), dict(combine="add"), *(dict(base=b) for b in NEURAL)])
def test_model_gradients(more):
    c = config(**more)
    m = RelationalModel(c)
    p, b = m.start(), unroll(rows(5, 3), c)
    loss, v = m.loss(p, b)
    t.backward(loss)
    for k in ("customer.dir", "head.out.w", next(k for k in p if k.startswith("base."))):
        i = tuple(0 for _ in p[k].shape)
        a, z = {**p, k: p[k].copy()}, {**p, k: p[k].copy()}
        a[k][i] += 1e-5
        z[k][i] -= 1e-5
        want = (float(m.loss(a, b)[0].v) - float(m.loss(z, b)[0].v)) / 2e-5
        assert abs(want - (v[k].g[i] if v[k].g is not None else 0)) < 1e-5


def test_degree_is_learned_only_with_relations():
    train, valid, test = rows(400, 1), rows(100, 2), rows(300, 3)
    y = [r["y"] for r in test]
    cfg = TrainConfig(rate=0.01, epochs=15, batch=64)
    c = config(layers=1)
    m = RelationalModel(c)
    p, hist = fit(m, train, valid, cfg)
    assert hist[-1] < hist[0] and area(y, m.predict(p, unroll(test, c))[0]) > 0.9
    base = BaseModel(c)
    q, _ = fit(base, train, valid, cfg)
    assert 0.35 < area(y, base.predict(q, unroll(test, c))[0]) < 0.65


def test_importance_cases():
    nan = np.nan
    a = np.array([[1.0, nan, nan, nan], [1 / 3, 1 / 3, 1 / 3, nan], [0.5, 0.25, 0.25, nan], [1.0, 0, 0, 0]])
    out = importance(a)
    assert out[0, 0] == 0 and np.allclose(out[1, :3], 0) and abs(out[2, 0] - 0.25) < 1e-12 and out[3, 0] == 1


def test_optimiser_and_stop():
    o = AdamW(0.1, 0.01)
    p = o.step({"w": np.array([1.0])}, {"w": np.array([2.0])})
    assert abs(p["w"][0] - (1 - 0.1 * (2 / (2 + 1e-8) + 0.01))) < 1e-12
    s = EarlyStop(3)
    assert [s.see(x, i) for i, x in enumerate([1.0, 0.9, 0.95, 0.95, 0.95])] == [False, False, False, False, True] and s.params == 1


def test_baselines():
    r = np.random.default_rng(1)
    x = r.standard_normal((400, 3))
    y = (x[:, 0] > 0).astype(float)
    for m in (InContext(), TwoStage()):
        assert area(y[200:], m.fit(x[:200], y[:200]).predict(x[200:])) > 0.85
    with pytest.raises(UnsupportedTask):
        TwoStage("regression")
    assert Constant("regression").fit(x, [1, 2, 9]).value == 2
    assert magnitude_tokens({"a": 3.0, "b": "x y"}, {"a": np.array([1.0, 2.0])}) == ["a", "a#2", "b", "x", "y"]
    assert magnitude_tokens({"b": "w " * 600}, {}) is None
    assert np.allclose(hashed_text("one two"), hashed_text("One  two")) and hashed_text("abc", grams="char", norm=True).shape == (768,)


def test_counts_and_area():
    c = config(layers=2)
    p = RelationalModel(c).start()
    assert sum(v.size for k, v in p.items() if k.startswith("pass") and k.endswith((".own", ".nbr"))) == passing_params(4, 2, 2)
    assert param_count(p) < param_count(p, embeddings=True)
    assert area([1, 0, 1, 0], [0.9, 0.8, 0.8, 0.1]) == 0.875
    points = tpe_order([({"w": w}, abs(w - 64)) for w in (16, 32, 64, 128, 16, 128)], {"w": [16, 32, 64, 128]}, 2)
    assert points[0]["w"] in (32, 64)


@pytest.mark.parametrize("more", [dict(directed=True), dict(task="multiclass", classes=3), dict(task="ranking")])
def test_more_heads_and_directions(more):
    c = config(**more)
    m, data = RelationalModel(c), rows(8, 4)
    for i, r in enumerate(data):
        r["y"] = float(i % 3)
    p, b = m.start(), unroll(data, c)
    loss, v = m.loss(p, b)
    t.backward(loss)
    k = "pass0.line_order.down.own" if "directed" in more else "head.out.w"
    i = tuple(0 for _ in p[k].shape)
    a, z = {**p, k: p[k].copy()}, {**p, k: p[k].copy()}
    a[k][i] += 1e-5
    z[k][i] -= 1e-5
    assert abs((float(m.loss(a, b)[0].v) - float(m.loss(z, b)[0].v)) / 2e-5 - v[k].g[i]) < 1e-5
    if more.get("task") == "multiclass":
        assert np.allclose(m.predict(p, b)[0].sum(axis=1), 1)


def test_pretraining_and_rate_search():
    from relmodel.nn.train import pretrain, rate_search

    c = config(schemas={"customer": L.Schema(["a", "b"], [("seg", 3)]), "orders": L.Schema(["price"]), "lineitem": L.Schema(["qty"])})
    data = rows(200, 5)
    for r in data:
        r["x"] = [r["x"][0], 2 * r["x"][0]]
    params, hist = pretrain(RelationalModel(c), data, TrainConfig(epochs=15, batch=64))
    assert hist[-1] < hist[0] and not any(k.startswith("pre.") for k in params)
    rate, _ = rate_search(RelationalModel(c), data[:100], data[100:], TrainConfig(epochs=2, batch=64), (0.001, 0.03))
    assert rate in (0.001, 0.03)


def test_learned_time():
    p = {"x.lin.w": np.ones((1, 1)), "x.lin.b": np.zeros(1), "x.freq": np.array([[1.0, 2.0]]), "x.phase": np.zeros(2)}
    out = L.time_learned(np.array([0.0, 86400.0]), {k: t.Var(v) for k, v in p.items()}, "x")
    assert np.allclose(out.v[1], [1, np.sin(1), np.sin(2)]) and np.allclose(out.v[0], 0)
