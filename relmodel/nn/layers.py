"""Layers of the relational model on the tape (E1-E11, P1-P7, F1-F9) and of the base models.

A parameter store is a dict of arrays; layers take a dict of ``Var`` with the same names.
"""

from __future__ import annotations

import math

import numpy as np

from relmodel.nn import tape as t

AGGS = ("max", "min", "sum", "mean")


def dense(r, p: dict, name: str, a: int, b: int) -> None:
    p[f"{name}.w"] = r.standard_normal((a, b)) / math.sqrt(a)
    p[f"{name}.b"] = np.zeros(b)


def apply_dense(p, name, x):
    return x @ p[f"{name}.w"] + p[f"{name}.b"]


def norm_params(p: dict, name: str, d: int) -> None:
    p[f"{name}.g"], p[f"{name}.o"] = np.ones(d), np.zeros(d)


def apply_norm(p, name, x):
    return t.layer_norm(x) * p[f"{name}.g"] + p[f"{name}.o"]


def attention_params(r, p: dict, name: str, d: int) -> None:
    for k in "qkvo":
        dense(r, p, f"{name}.{k}", d, d)


def attention(p, name, x, heads: int, mask=None):
    """Scaled dot-product attention of (B, M, d) with itself; returns the output and the
    weights (B, H, M, M). ``mask`` (B, M) tells which positions exist."""
    b, m, d = x.shape
    split = lambda z: t.swap(t.reshape(z, (b, m, heads, d // heads)), 1, 2)
    q, k, v = (split(apply_dense(p, f"{name}.{c}", x)) for c in "qkv")
    w = t.softmax((q @ t.swap(k, 2, 3)) * (1 / math.sqrt(d // heads)), None if mask is None else mask[:, None, None, :])
    out = t.reshape(t.swap(w @ v, 1, 2), (b, m, d))
    return apply_dense(p, f"{name}.o", out), w


def block_params(r, p: dict, name: str, d: int, wide: int) -> None:
    attention_params(r, p, f"{name}.att", d)
    norm_params(p, f"{name}.n1", d)
    norm_params(p, f"{name}.n2", d)
    dense(r, p, f"{name}.f1", d, wide)
    dense(r, p, f"{name}.f2", wide, d)


def encoder_block(p, name, x, heads):
    """Attention and feed-forward, each with a residual and a normalisation."""
    x = apply_norm(p, f"{name}.n1", x + attention(p, f"{name}.att", x, heads)[0])
    return apply_norm(p, f"{name}.n2", x + apply_dense(p, f"{name}.f2", t.relu(apply_dense(p, f"{name}.f1", x))))


class Schema:
    """Attributes of one table: names of numbers and (name, vocabulary size) of categorical ones. The
    last numbers belong together as ``vectors`` (name, width): one attribute each (E4, E5)."""

    def __init__(self, numerical: list[str], categorical: list[tuple[str, int]] = (), vectors: list[tuple[str, int]] = ()):
        self.numerical, self.categorical, self.vectors = list(numerical), list(categorical), list(vectors)

    @property
    def width(self):
        return len(self.numerical) + len(self.categorical)

    @property
    def single(self) -> int:
        """How many numbers are attributes of their own."""
        return len(self.numerical) - sum(n for _, n in self.vectors)


def table_params(r, p: dict, name: str, s: Schema, d: int) -> None:
    """A direction and a bias per numerical column, a lookup table (row 0: unknown) and
    a null vector per column, a projection per vector (E4, E5), and a summary vector."""
    p[f"{name}.dir"] = r.standard_normal((s.single, d)) / math.sqrt(d)
    p[f"{name}.off"] = r.standard_normal((s.single, d)) / math.sqrt(d)
    p[f"{name}.null"] = r.standard_normal((s.single, d)) / math.sqrt(d)
    for c, n in s.vectors:
        dense(r, p, f"{name}.vector.{c}", n, d)
    for c, n in s.categorical:
        p[f"{name}.embedding.{c}"] = r.standard_normal((n + 1, d)) / math.sqrt(d)
    p[f"{name}.cls"] = r.standard_normal((1, 1, d)) / math.sqrt(d)


def attributes(p, name: str, s: Schema, num: np.ndarray, cat: np.ndarray):
    """(B, M, d) attribute embeddings; NaN in a numerical column is a null."""
    out, at = [], s.single
    if at:
        gone = np.isnan(num[:, :at])[:, :, None]
        x = np.nan_to_num(num[:, :at])[:, :, None]
        z = t.lift(x) * p[f"{name}.dir"] + p[f"{name}.off"]
        out.append(z * (1.0 - gone) + p[f"{name}.null"] * gone.astype(float))
    for c, n in s.vectors:
        z = apply_dense(p, f"{name}.vector.{c}", t.lift(np.nan_to_num(num[:, at : at + n])))
        out.append(t.reshape(z, (len(num), 1, z.shape[1])))
        at += n
    for i, (c, _) in enumerate(s.categorical):
        e = t.take(p[f"{name}.embedding.{c}"], cat[:, i].astype(int))
        out.append(t.reshape(e, (e.shape[0], 1, e.shape[1])))
    return t.concat(out, axis=1)


def tuple_embedding(p, name: str, s: Schema, num, cat, layers: int, heads: int):
    """Summary vector in front, encoder blocks, then summary beside the attributes' mean."""
    x = attributes(p, name, s, num, cat)
    b, m, d = x.shape
    x = t.concat([t.lift(np.ones((b, 1, 1))) * p[f"{name}.cls"], x], axis=1)
    for k in range(layers):
        x = encoder_block(p, f"enc{k}", x, heads)
    flat = t.reshape(x, (b * (m + 1), d))
    first = t.take(flat, np.arange(b) * (m + 1))
    rest = t.take(flat, (np.arange(b)[:, None] * (m + 1) + np.arange(1, m + 1)).reshape(-1))
    return apply_norm(p, "tuple", t.concat([first, t.mean(t.reshape(rest, (b, m, d)), axis=1)], axis=1))


def tuple_values(p, name: str, s: Schema, num, cat, layers: int, heads: int, most: int = 1024):
    """``tuple_embedding`` without gradients. Rows are the last axis and ``most`` of them go at a time, so
    every operation runs along rows and stays in the cache."""
    out = np.empty((len(num), 2 * p[f"{name}.cls"].shape[-1]))
    for i in range(0, len(num), most):
        out[i : i + most] = _tuple_values(p, name, s, num[i : i + most], cat[i : i + most], layers, heads).T
    return t.lift(out)


def _tuple_values(p, name, s, num, cat, layers, heads):
    def dense(q, x):
        return p[f"{q}.w"].v.T @ x + p[f"{q}.b"].v[:, None]

    def norm(q, x):
        c = x - x.mean(axis=-2, keepdims=True)
        c *= 1 / np.sqrt((c * c).mean(axis=-2, keepdims=True) + 1e-5)
        return c * p[f"{q}.g"].v[:, None] + p[f"{q}.o"].v[:, None]

    def attend(q, x):
        m, d, n = x.shape
        a, b, v = (dense(f"{q}.{c}", x).reshape(m, heads, d // heads, n) for c in "qkv")
        a *= 1 / math.sqrt(d // heads)
        z = np.empty_like(a)
        for i in range(m):  # one place's weights at a time: they stay in the nearest cache
            w = a[i, :, 0] * b[:, :, 0]
            for c in range(1, d // heads):
                w += a[i, :, c] * b[:, :, c]
            w -= w.max(axis=0)
            np.exp(w, out=w)
            for c in range(d // heads):
                z[i, :, c] = (w * v[:, :, c]).sum(axis=0)
            z[i] /= w.sum(axis=0)[:, None]
        return dense(f"{q}.o", z.reshape(m, d, n))

    at, parts = s.single, [p[f"{name}.cls"].v.reshape(1, -1, 1) + np.zeros(len(num))]
    if at:
        own = num[:, :at].T[:, None, :]
        z = np.nan_to_num(own) * p[f"{name}.dir"].v[:, :, None] + p[f"{name}.off"].v[:, :, None]
        parts.append(np.where(np.isnan(own), p[f"{name}.null"].v[:, :, None], z))
    for c, k in s.vectors:
        parts.append(dense(f"{name}.vector.{c}", np.nan_to_num(num[:, at : at + k]).T)[None])
        at += k
    for i, (c, _) in enumerate(s.categorical):
        parts.append(p[f"{name}.embedding.{c}"].v[cat[:, i].astype(int)].T[None])
    x = np.concatenate(parts)
    for k in range(layers):
        x = norm(f"enc{k}.n1", x + attend(f"enc{k}.att", x))
        x = norm(f"enc{k}.n2", x + dense(f"enc{k}.f2", np.maximum(dense(f"enc{k}.f1", x), 0)))
    return norm("tuple", np.concatenate([x[0], x[1:].mean(axis=0)]))


def message_layer(p, k: int, states: dict, relations: list, how: str, directed: bool = False):
    """``relations`` holds (name, child, parent, child index, parent index). ``directed``
    gives the way down to the child weights of its own."""
    got: dict[str, list] = {n: [] for n in states}
    for name, child, parent, ci, pi in relations:
        for to, frm, ti, fi in ((parent, child, pi, ci), (child, parent, ci, pi)):
            n = states[to].shape[0]
            if not len(ti) or not n:
                continue
            s = t.segment(t.take(states[frm], fi), ti, n, how)
            has = (np.bincount(ti, minlength=n) > 0).astype(float)[:, None]
            way = f"pass{k}.{name}" + (".down" if directed and to == child else "")
            got[to].append(((states[to] @ p[f"{way}.own"] + s @ p[f"{way}.nbr"]) * has, has))
    out = {}
    for n, h in states.items():
        if got[n]:
            present = sum(x for _, x in got[n])
            mixed = got[n][0][0]
            for x, _ in got[n][1:]:
                mixed = mixed + x
            mixed = mixed * (1 / np.maximum(present, 1)) + h * (present == 0).astype(float)
        else:
            mixed = h
        out[n] = apply_norm(p, f"pass{k}.{n}", t.relu(mixed))
    return out


def signal_stack(h, seeds: int, relations: dict):
    """(B, 1 + 4 R, D) own vector and neighbourhood aggregates, a mask and the names.
    ``relations`` gives per name (states, seed index of each neighbour row)."""
    d = h.shape[1]
    rows, mask, names = [t.reshape(h, (seeds, 1, d))], [np.ones((seeds, 1), bool)], ["self"]
    for name, (states, ids) in sorted(relations.items()):
        has = np.bincount(ids, minlength=seeds)[:, None] > 0
        for a in AGGS:
            rows.append(t.reshape(t.segment(states, ids, seeds, a), (seeds, 1, d)))
            mask.append(has)
            names.append(f"{name}({a})")
    return t.concat(rows, axis=1), np.concatenate(mask, axis=1), names


def entmax(x, alpha: float = 1.7, steps: int = 50):
    """Sparse weights over the last axis by bisection (B11); the gradient uses its closed form."""
    z = x.v * (alpha - 1)
    lo, hi = z.max(axis=-1, keepdims=True) - 1, z.max(axis=-1, keepdims=True)
    for _ in range(steps):
        mid = (lo + hi) / 2
        s = (np.maximum(z - mid, 0) ** (1 / (alpha - 1))).sum(axis=-1, keepdims=True)
        lo, hi = np.where(s >= 1, mid, lo), np.where(s >= 1, hi, mid)
    y = np.maximum(z - (lo + hi) / 2, 0) ** (1 / (alpha - 1))
    y = y / y.sum(axis=-1, keepdims=True)
    w = np.where(y > 0, y ** (2 - alpha), 0)
    return t.Var(y, (x,), lambda g: (w * (g - (g * w).sum(axis=-1, keepdims=True) / w.sum(axis=-1, keepdims=True)),))


def time_learned(seconds: np.ndarray, p, name: str):
    """A linear term and sines of learned frequency and phase, for times scaled to days."""
    x = t.lift(seconds[:, None] / 86400.0)
    return t.concat([x * p[f"{name}.lin.w"] + p[f"{name}.lin.b"], sine(x * p[f"{name}.freq"] + p[f"{name}.phase"])], axis=1)


def sine(x):
    return t.Var(np.sin(x.v), (x,), lambda g: (g * np.cos(x.v),))


def pick_log_softmax(z, label: np.ndarray):
    """log softmax of (B, C) at the label of each row."""
    m = z.v.max(axis=1, keepdims=True)
    e = np.exp(z.v - m)
    y = e / e.sum(axis=1, keepdims=True)
    rows = np.arange(len(label))
    one = np.zeros_like(y)
    one[rows, label] = 1
    return t.Var(np.log(y[rows, label] + 1e-300), (z,), lambda g: (g[:, None] * (one - y),))
