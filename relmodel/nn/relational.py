"""The relational model over packed ego graphs: encoder, message passing, fusion, head (E, P, F).

Each seed brings its own small graph (one row, no shuffle at training or scoring time); a batch is
unrolled into one array per table and index arrays per relation, without padding.
"""

from __future__ import annotations

from dataclasses import dataclass, field

import numpy as np

from relmodel.nn import layers as L
from relmodel.nn import tape as t
from relmodel.nn.bases import NEURAL


@dataclass(frozen=True)
class Step:
    """A hop from ``source`` to ``table`` along ``relation``; ``down`` if the neighbours are children."""

    relation: str
    source: str
    table: str
    down: bool = True


@dataclass
class Config:
    target: str
    schemas: dict[str, L.Schema]
    steps: tuple[Step, ...]  # in hop order; a later step starts from a table reached before
    d: int = 8
    encoder_layers: int = 1
    heads: int = 2
    layers: int = 2
    agg: str = "sum"
    base: str = "residual"
    task: str = "binary"
    use_relations: bool = True  # False: F10, also no hops
    use_passing: bool = True  # False: F10
    use_fusion: bool = True  # False: F11
    combine: str = "concat_project"
    directed: bool = False
    classes: int = 2  # of multi-class tasks
    seed: int = 0
    extra: dict = field(default_factory=dict)


@dataclass
class Batch:
    num: dict[str, np.ndarray]
    cat: dict[str, np.ndarray]
    edges: list[tuple]  # (relation, child, parent, child index, parent index, first seed-side index or None)
    seeds: int
    y: np.ndarray | None
    owner: dict[str, tuple[str, np.ndarray]]  # signal name -> (table, rows, seed of each row)


def unroll(rows: list[dict], c: Config) -> Batch:
    """Rows {x, c, y, <relation>: [(at, num, cat)]} to arrays; ``at`` is the place of the neighbour
    this one hangs on among those of the step before (0 for first-hop steps)."""
    num = {n: [] for n in c.schemas}
    cat = {n: [] for n in c.schemas}
    size = {n: 0 for n in c.schemas}
    for row in rows:
        num[c.target].append(row["x"])
        cat[c.target].append(row.get("c", ()))
    size[c.target] = len(rows)
    edges, owner, place = [], {}, {c.target: [np.array([i]) for i in range(len(rows))]}
    for s in c.steps if c.use_relations else ():
        a, b, who, mine = [], [], [], []
        for i, row in enumerate(rows):
            got = row.get(s.relation) or ()
            ids = np.arange(size[s.table], size[s.table] + len(got))
            size[s.table] += len(got)
            mine.append(ids)
            for at, x, k in got:
                num[s.table].append(x)
                cat[s.table].append(k)
            if len(got):
                a.append(ids)
                b.append(place[s.source][i][[int(g[0]) for g in got]])
                who.append(np.full(len(got), i))
        place[s.table] = mine
        a, b, who = (np.concatenate(x).astype(int) if x else np.zeros(0, int) for x in (a, b, who))
        child, parent, ci, pi = (s.table, s.source, a, b) if s.down else (s.source, s.table, b, a)
        edges.append((s.relation, child, parent, ci, pi))
        if s.source == c.target:
            owner[s.relation] = (s.table, a, who)
    nums = {n: np.array(v, float).reshape(len(v), len(c.schemas[n].numerical)) for n, v in num.items()}
    cats = {n: np.array(v, int).reshape(len(v), len(c.schemas[n].categorical)) for n, v in cat.items()}
    y = np.array([r["y"] for r in rows], float) if rows and rows[0].get("y") is not None else None
    return Batch(nums, cats, edges, len(rows), y, owner)


def _lists(column, n: int) -> tuple[np.ndarray, object]:
    """(lengths, flattened values) of an Arrow list column; null lists are empty."""
    return column.value_lengths().fill_null(0).to_numpy(zero_copy_only=False).astype(int), column.flatten()


def unroll_arrow(b, c: Config) -> Batch:
    """``unroll`` of an Arrow batch of packed rows, read from its buffers: no Python object a row."""
    n = b.num_rows

    def matrix(values, rows: int, width: int, kind):
        return values.to_numpy(zero_copy_only=False).astype(kind).reshape(rows, width)

    def body(x, k, rows: int, table: str):
        s = c.schemas[table]
        return matrix(_lists(x, rows)[1], rows, len(s.numerical), float), matrix(_lists(k, rows)[1], rows, len(s.categorical), int)

    parts = {t_: [] for t_ in c.schemas}
    parts[c.target].append(body(b.column("x"), b.column("c"), n, c.target))
    size = {t_: 0 for t_ in c.schemas} | {c.target: n}
    first, edges, owner = {c.target: np.arange(n)}, [], {}
    for s in c.steps if c.use_relations else ():
        count, rows = _lists(b.column(s.relation), n)
        total = int(count.sum())
        at, x, k = (rows.field(f) if total else None for f in ("at", "x", "c"))
        ids, who = size[s.table] + np.arange(total), np.repeat(np.arange(n), count)
        if total:
            parts[s.table].append(body(x, k, total, s.table))
            up = first[s.source][who] + at.to_numpy(zero_copy_only=False).astype(int)
        else:
            up = np.zeros(0, int)
        first[s.table] = size[s.table] + np.cumsum(count) - count
        size[s.table] += total
        child, parent, ci, pi = (s.table, s.source, ids, up) if s.down else (s.source, s.table, up, ids)
        edges.append((s.relation, child, parent, ci, pi))
        if s.source == c.target:
            owner[s.relation] = (s.table, ids, who)
    empty = {t_: (np.zeros((0, len(s.numerical))), np.zeros((0, len(s.categorical)), int)) for t_, s in c.schemas.items()}
    made = {t_: tuple(map(np.concatenate, zip(*v))) if v else empty[t_] for t_, v in parts.items()}
    y = b.column("y").to_numpy(zero_copy_only=False).astype(float) if "y" in b.schema.names else None
    return Batch({k: v[0] for k, v in made.items()}, {k: v[1] for k, v in made.items()}, edges, n, y, owner)


class RelationalModel:
    """Base model augmented by its relational neighbourhood."""

    def __init__(self, c: Config):
        self.c = c
        self.base = NEURAL[c.base](c.schemas[c.target], width=2 * c.d)

    def start(self) -> dict[str, np.ndarray]:
        c, r = self.c, np.random.default_rng(self.c.seed)
        p = self.base.start(r)
        d2 = 2 * c.d
        for n, s in c.schemas.items():
            L.table_params(r, p, n, s, c.d)
        for k in range(c.encoder_layers):
            L.block_params(r, p, f"enc{k}", c.d, 2 * c.d)
        L.norm_params(p, "tuple", d2)
        L.dense(r, p, "combine", d2 + self.base.native_width, d2)
        for k in range(c.layers):
            for s in c.steps:
                p[f"pass{k}.{s.relation}.own"] = r.standard_normal((d2, d2)) / np.sqrt(d2)
                p[f"pass{k}.{s.relation}.nbr"] = r.standard_normal((d2, d2)) / np.sqrt(d2)
                if c.directed:
                    p |= {f"pass{k}.{s.relation}.down.{w}": r.standard_normal((d2, d2)) / np.sqrt(d2) for w in ("own", "nbr")}
            for n in c.schemas:
                L.norm_params(p, f"pass{k}.{n}", d2)
        L.attention_params(r, p, "fuse", d2)
        L.norm_params(p, "head", d2)
        L.dense(r, p, "head.out", d2, c.classes if c.task == "multiclass" else 1)
        return p

    def forward(self, params: dict[str, np.ndarray], b: Batch, embed=L.tuple_embedding):
        """(output Var, Var params, importance weights (B, S) or None, signal names)."""
        c = self.c
        p = {k: t.Var(v) for k, v in params.items()}
        h = {n: embed(p, n, s, b.num[n], b.cat[n], c.encoder_layers, c.heads) for n, s in c.schemas.items() if len(b.num[n])}
        native, own = self.base.run(p, b.num[c.target], b.cat[c.target])
        mixed = {"concat_project": lambda: L.apply_dense(p, "combine", t.concat([native, h[c.target]], axis=1)), "add": lambda: native + h[c.target], "native_only": lambda: native, "encoder_only": lambda: h[c.target]}
        h[c.target] = mixed[c.combine]()
        edges = [e for e in b.edges if e[1] in h and e[2] in h]
        if c.use_relations and c.use_passing:
            for k in range(c.layers):
                h = L.message_layer(p, k, h, edges, c.agg, c.directed)
        z, alpha, names = h[c.target], None, ["self"]
        if c.use_relations and c.use_fusion:
            around = {r: (t.take(h[n], rows), who) for r, (n, rows, who) in b.owner.items() if n in h and len(rows)}
            seq, mask, names = L.signal_stack(z, b.seeds, around)
            out, w = L.attention(p, "fuse", seq, c.heads, mask)
            s = len(names)
            z = t.take(t.reshape(out, (b.seeds * s, z.shape[1])), np.arange(b.seeds) * s) + z * c.extra.get("skip", 0.0)
            alpha = w.v[:, :, 0, :].mean(axis=1)
            alpha = np.where(mask, alpha, np.nan)
        y = L.apply_dense(p, "head.out", L.apply_norm(p, "head", t.relu(z)))
        return y if c.task == "multiclass" else t.reshape(y, (-1,)) + own, p, alpha, names

    def loss(self, params, b: Batch):
        y, p, _, _ = self.forward(params, b)
        return task_loss(y, b.y, self.c.task), p

    def predict(self, params, b: Batch):
        """(score, importance weights, names): probabilities for binary tasks."""
        y, _, alpha, names = self.forward(params, b, L.tuple_values)
        return {"binary": t.sigmoid, "multiclass": t.softmax}.get(self.c.task, lambda x: x)(y).v, alpha, names

    def reconstruct(self, params, b: Batch, masked: np.ndarray):
        """Squared error of masked numerical attributes of the target, read off its embedding."""
        c, p = self.c, {k: t.Var(v) for k, v in params.items()}
        num = b.num[c.target]
        h = L.tuple_embedding(p, c.target, c.schemas[c.target], np.where(masked, np.nan, num), b.cat[c.target], c.encoder_layers, c.heads)
        miss = (L.apply_dense(p, "pre.out", h) - np.nan_to_num(num)) * (masked & ~np.isnan(num)).astype(float)
        return t.total(miss * miss) * (1.0 / max(1, masked.sum())), p


class BaseModel:
    """A neural base alone, with the same interface."""

    def __init__(self, c: Config):
        self.c = c
        self.base = NEURAL[c.base](c.schemas[c.target], width=2 * c.d)

    def start(self):
        return self.base.start(np.random.default_rng(self.c.seed))

    def loss(self, params, b: Batch):
        p = {k: t.Var(v) for k, v in params.items()}
        return task_loss(self.base.run(p, b.num[self.c.target], b.cat[self.c.target])[1], b.y, self.c.task), p

    def predict(self, params, b: Batch):
        y = self.base.run({k: t.Var(v) for k, v in params.items()}, b.num[self.c.target], b.cat[self.c.target])[1]
        return (t.sigmoid(y).v if self.c.task == "binary" else y.v), None, ["self"]


def task_loss(y, label, task: str):
    """T1, T2; F9: cross-entropy over classes, and pairwise logistic loss for rankings."""
    if task == "multiclass":
        return t.mean(L.pick_log_softmax(y, label.astype(int))) * -1.0
    if task == "ranking":
        n = len(label)
        above = (label[:, None] > label[None, :]).astype(float)
        return t.total(t.softplus(t.reshape(y, (1, n)) - t.reshape(y, (n, 1))) * above) * (1.0 / max(1.0, above.sum()))
    return t.mean(t.softplus(y) - y * label) if task == "binary" else t.mean(t.absolute(y - label))


def importance(alpha: np.ndarray) -> np.ndarray:
    """F5 on rows of weights with NaN where a signal is absent."""
    n = (~np.isnan(alpha)).sum(axis=1, keepdims=True)
    with np.errstate(divide="ignore", invalid="ignore"):
        out = np.maximum((alpha - 1 / n) / (1 - 1 / n), 0)
    return np.where(n > 1, out, np.where(np.isnan(alpha), np.nan, 0))


def param_count(params: dict[str, np.ndarray], embeddings: bool = False) -> int:
    """A5: parameters without embedding tables."""
    return sum(v.size for k, v in params.items() if embeddings or ".embedding." not in k)


def passing_params(d: int, relations: int, layers: int) -> int:
    """2 D² per relation and layer, D = 2 d."""
    return layers * relations * 2 * (2 * d) ** 2
