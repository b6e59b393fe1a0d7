"""Base models on single-table features (B5-B12, B15-B18, B20): native vector and output per row.

All take a ``Schema``; ``start`` makes parameters, ``run`` returns (native vector, logit or value).
Text encoders and in-context models stand in for published checkpoints, which cannot be loaded
here: same interface and role, weights of our own, so no published accuracy is claimed.
"""

from __future__ import annotations

import hashlib
import math
from functools import lru_cache

import numpy as np

from relmodel.nn import layers as L
from relmodel.nn import tape as t


class UnsupportedTask(ValueError):
    """The model cannot do this kind of task (its metric is null)."""


def flat(p, s: L.Schema, num, cat):
    """Numerical values (null: 0) beside the embeddings of categorical ones, as one row."""
    xs = [t.lift(np.where(np.isnan(num), 0, num))] if s.numerical else []
    for i, (c, _) in enumerate(s.categorical):
        xs.append(t.take(p[f"base.embedding.{c}"], cat[:, i].astype(int)))
    return t.concat(xs, axis=1)


class Base:
    """Common part: embeddings of categorical columns and a linear output on the native vector."""

    kind, native_width, group = "", 16, "neural"

    def __init__(self, s: L.Schema, width: int = 16, depth: int = 2, embed: int = 4):
        self.s, self.width, self.depth, self.embed = s, width, depth, embed
        self.native_width = width

    def start(self, r) -> dict[str, np.ndarray]:
        p: dict[str, np.ndarray] = {}
        for c, n in self.s.categorical:
            p[f"base.embedding.{c}"] = r.standard_normal((n + 1, self.embed)) / 2
        self.inputs = len(self.s.numerical) + self.embed * len(self.s.categorical)
        self.more(r, p)
        L.dense(r, p, "base.out", self.native_width, 1)
        return p

    def run(self, p, num, cat):
        z = self.native(p, num, cat)
        return z, t.reshape(L.apply_dense(p, "base.out", z), (-1,))


class Mlp(Base):
    """B7."""

    kind = "mlp"

    def more(self, r, p):
        for k in range(self.depth):
            L.dense(r, p, f"base.l{k}", self.inputs if k == 0 else self.width, self.width)

    def native(self, p, num, cat):
        x = flat(p, self.s, num, cat)
        for k in range(self.depth):
            x = t.relu(L.apply_dense(p, f"base.l{k}", x))
        return x


class Residual(Base):
    """Blocks x + W2 relu(W1 norm(x))."""

    kind = "residual"

    def more(self, r, p):
        L.dense(r, p, "base.in", self.inputs, self.width)
        for k in range(self.depth):
            L.norm_params(p, f"base.n{k}", self.width)
            L.dense(r, p, f"base.a{k}", self.width, self.width)
            L.dense(r, p, f"base.z{k}", self.width, self.width)

    def native(self, p, num, cat):
        x = L.apply_dense(p, "base.in", flat(p, self.s, num, cat))
        for k in range(self.depth):
            x = x + L.apply_dense(p, f"base.z{k}", t.relu(L.apply_dense(p, f"base.a{k}", L.apply_norm(p, f"base.n{k}", x))))
        return x


def pairwise(e):
    """Sum over attribute pairs of products, by the square-of-sum identity; e is (B, M, d)."""
    s = t.total(e, axis=1)
    return (s * s - t.total(e * e, axis=1)) * 0.5


class Factorised(Base):
    """First order, pairwise products and a deep part over attribute embeddings."""

    kind = "factorised"

    def more(self, r, p):
        L.table_params(r, p, "base.tab", self.s, self.embed)
        L.dense(r, p, "base.first", self.inputs, self.width)
        L.dense(r, p, "base.pair", self.embed, self.width)
        L.dense(r, p, "base.deep0", self.s.width * self.embed, self.width)
        L.dense(r, p, "base.deep1", self.width, self.width)

    def native(self, p, num, cat):
        e = L.attributes(p, "base.tab", self.s, num, cat)
        deep = t.relu(L.apply_dense(p, "base.deep0", t.reshape(e, (e.shape[0], -1))))
        return L.apply_dense(p, "base.first", flat(p, self.s, num, cat)) + L.apply_dense(p, "base.pair", pairwise(e)) + L.apply_dense(p, "base.deep1", deep)


class Tokens(Base):
    """Attribute tokens, transformer blocks, summary token."""

    kind = "tokens"
    heads = 4

    def more(self, r, p):
        L.table_params(r, p, "base.tab", self.s, self.width)
        for k in range(self.depth):
            L.block_params(r, p, f"base.b{k}", self.width, 2 * self.width)

    def native(self, p, num, cat):
        x = L.attributes(p, "base.tab", self.s, num, cat)
        b, m, d = x.shape
        x = t.concat([t.lift(np.ones((b, 1, 1))) * p["base.tab.cls"], x], axis=1)
        for k in range(self.depth):
            x = L.encoder_block(p, f"base.b{k}", x, self.heads)
        return t.take(t.reshape(x, (b * (m + 1), d)), np.arange(b) * (m + 1))


class Gated(Base):
    """Multiplicative neurons with sparse gated attention over attributes, in log space."""

    kind, neurons = "gated", 8

    def more(self, r, p):
        L.table_params(r, p, "base.tab", self.s, self.embed)
        p["base.query"] = r.standard_normal((self.neurons, self.embed)) / math.sqrt(self.embed)
        p["base.power"] = r.standard_normal((self.neurons, self.s.width)) / math.sqrt(self.s.width)
        L.dense(r, p, "base.mix", self.neurons * self.embed, self.width)

    def native(self, p, num, cat):
        e = t.tanh(L.attributes(p, "base.tab", self.s, num, cat))  # log of the positive embedding
        gate = L.entmax(p["base.query"] @ t.swap(e, 1, 2))
        out = t.exp((gate * p["base.power"]) @ e)
        return t.relu(L.apply_dense(p, "base.mix", t.reshape(out, (e.shape[0], -1))))


class Ensemble(Base):
    """One weight matrix, rank-one adapters per expert, mean of the experts."""

    kind, experts = "ensemble", 8

    def more(self, r, p):
        for k in range(self.depth):
            a = self.inputs if k == 0 else self.width
            p[f"base.w{k}"] = r.standard_normal((a, self.width)) / math.sqrt(a)
            p[f"base.r{k}"] = np.sign(r.standard_normal((self.experts, 1, a)))
            p[f"base.s{k}"] = np.ones((self.experts, 1, self.width))
            p[f"base.b{k}"] = np.zeros((self.experts, 1, self.width))

    def native(self, p, num, cat):
        x = flat(p, self.s, num, cat)
        for k in range(self.depth):
            x = t.relu(((x * p[f"base.r{k}"]) @ p[f"base.w{k}"]) * p[f"base.s{k}"] + p[f"base.b{k}"])
        return t.mean(x, axis=0)


NEURAL = {c.kind: c for c in (Mlp, Factorised, Residual, Tokens, Gated, Ensemble)}


class InContext:
    """Labelled rows as context, one pass, no gradients at task time: scores are attention over
    the context's labels after a fixed random feature layer."""

    kind, group, most = "incontext", "tabular", 1024

    def __init__(self, task: str = "binary", width: int = 64, seed: int = 1):
        self.task, self.width, self.seed = task, width, seed

    def features(self, x):
        r = np.random.default_rng(self.seed)
        w = r.standard_normal((x.shape[1], self.width)) / math.sqrt(x.shape[1])
        return np.concatenate([x, np.tanh(x @ w)], axis=1)

    def fit(self, x, y):
        x, y = np.nan_to_num(x)[: self.most], np.asarray(y, float)[: self.most]
        self.mean, self.sd = x.mean(0), x.std(0) + 1e-9
        self.keys, self.y = self.features((x - self.mean) / self.sd), y
        return self

    def predict(self, x):
        q = self.features((np.nan_to_num(x) - self.mean) / self.sd)
        d = (q**2).sum(1)[:, None] + (self.keys**2).sum(1) - 2 * q @ self.keys.T
        w = np.exp(-(d - d.min(1, keepdims=True)) / math.sqrt(self.keys.shape[1]))
        return (w @ self.y) / w.sum(1)


class TwoStage(InContext):
    """Columns first (each value as its place among the context's), then rows; classification only."""

    kind = "two_stage_incontext"

    def __init__(self, task: str = "binary", **more):
        if task == "regression":
            raise UnsupportedTask("two_stage_incontext does classification only")
        super().__init__(task, **more)

    def fit(self, x, y):
        self.columns = np.sort(np.nan_to_num(x)[: self.most], axis=0)
        return super().fit(self.places(np.nan_to_num(x)[: self.most]), y)

    def places(self, x):
        return np.stack([np.searchsorted(self.columns[:, j], x[:, j]) / len(self.columns) for j in range(x.shape[1])], axis=1)

    def predict(self, x):
        return super().predict(self.places(np.nan_to_num(x)))


class Constant:
    """Majority rate or median."""

    kind, group = "constant", "floor"

    def __init__(self, task: str = "binary"):
        self.task = task

    def fit(self, x, y):
        self.value = float(np.mean(y) if self.task == "binary" else np.median(y))
        return self

    def predict(self, x):
        return np.full(len(x), self.value)


@lru_cache(1 << 17)  # grams repeat within and across texts
def gram_hash(gram: str, seed: int) -> int:
    return int.from_bytes(hashlib.blake2b(gram.encode(), digest_size=8, salt=seed.to_bytes(8, "little")).digest(), "little")


def hashed_text(text: str, width: int = 768, grams: str = "word", seed: int = 0, norm: bool = False) -> np.ndarray:
    """A frozen text vector by signed feature hashing of word or character n-grams."""
    low = text.lower()
    words = low.split()
    parts = words + [" ".join(p) for p in zip(words, words[1:])] if grams == "word" else [low[i : i + 3] for i in range(max(1, len(text) - 2))]
    h = np.fromiter((gram_hash(g, seed) for g in parts), np.uint64, len(parts))
    out = np.bincount((h % np.uint64(width)).astype(np.int64), np.where(h >> np.uint64(63), 1.0, -1.0), width)
    n = np.linalg.norm(out) if norm else max(1, len(parts)) ** 0.5
    return out / n if n else out


def magnitude_tokens(values: dict[str, object], edges: dict[str, np.ndarray], limit: int = 512) -> list[str] | None:
    """Numbers become the token of their magnitude bin, texts their words; None over the limit."""
    out: list[str] = []
    for name, v in values.items():
        if isinstance(v, (int, float)) and name in edges:
            out += [name, f"{name}#{int(np.searchsorted(edges[name], v))}"]
        elif v is not None:
            out += [name, *str(v).lower().split()]
    return out if len(out) <= limit else None


def magnitude_edges(numbers: dict[str, object], bins: int = 16) -> dict[str, np.ndarray]:
    """Inner quantiles per number column, the edges of ``magnitude_tokens``."""
    out = {}
    for name, v in numbers.items():
        v = np.asarray(v, float)
        v = v[~np.isnan(v)]
        out[name] = np.unique(np.quantile(v, np.arange(1, bins) / bins)) if len(v) else np.zeros(0)
    return out


class TextBase:
    """Frozen text vectors of serialised rows with a ridge head, the only part that learns."""

    group = "text"

    def __init__(self, kind: str, task: str = "binary", ridge: float = 1.0, edges: dict[str, np.ndarray] | None = None):
        self.kind, self.task, self.ridge, self.edges = kind, task, ridge, edges or {}

    def encode(self, texts: list) -> np.ndarray:
        """Texts, or for ``magnitude_text`` rows as dicts of values; NaN where there is no text or, for
        ``magnitude_text``, more tokens than its limit."""
        if self.kind == "magnitude_text":
            tokens = [None if x is None else magnitude_tokens(x if isinstance(x, dict) else {"text": x}, self.edges) for x in texts]
            texts = [None if x is None else " ".join(x) for x in tokens]
        how = {"general_text": dict(grams="word"), "pooled_text": dict(grams="char", norm=True), "magnitude_text": dict(grams="word", seed=3, norm=True)}[self.kind]
        prefix = "search_document: " if self.kind == "general_text" else ""
        return np.stack([np.full(768, np.nan) if x is None else hashed_text(prefix + x, **how) for x in texts])

    def fit(self, x, y):
        ok = ~np.isnan(x).any(axis=1)
        x, y = x[ok], np.asarray(y, float)[ok]
        if not len(x):
            raise UnsupportedTask("every input is too long")
        self.mean, self.y0 = x.mean(0), y.mean()
        z = x - self.mean
        k = z @ z.T + self.ridge * np.eye(len(z))
        self.w = z.T @ np.linalg.solve(k, y - self.y0)
        return self

    def predict(self, x):
        return (x - self.mean) @ self.w + self.y0
