"""Operator 10: quality classifier by attention-based multiple-instance learning.

A document is a bag of passages of ``PASSAGE`` words. Each passage is encoded (hashed words, word
shapes, repetition and character statistics, then a learned layer), gated attention weighs the
passages, and the weighted sum is scored. Encoder, attention and score are learned together from
document labels alone.

Training takes labelled documents outside the held-out fifth, in hash order: at most ``SAMPLE`` of them
and at most ``PASSAGES`` passages in all, each document with every passage it has or not at all; both
are parameters. It runs ``EPOCHS`` rounds, and more where they are fewer than ``STEPS`` steps. Scoring
takes every passage of every document. Labels, lang, source and doc_id are no inputs.

Null and empty texts are one empty passage and are scored. Without labels, or with one class of
labels, every score is the smoothed share of label 1. Repeated rows are scored alike; of texts that
share a labelled doc_id one, the first by hash, is learned from. Very long texts are read in full.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from relmodel.llm import _grams as G
from relmodel.llm._common import text_of, words_of, written

PASSAGE, SAMPLE, PASSAGES = 64, 4000, 200_000
WORDS, SHAPES, STATS = 64, 64, 9
WIDTH = WORDS + SHAPES + STATS
HIDDEN, GATE, EPOCHS, STEPS, RATE = 32, 16, 12, 400, 0.01

_kind = np.zeros((5, 256), np.int32)  # upper, lower, digit, mark, beyond ASCII
_kind[0, 65:91] = _kind[1, 97:123] = _kind[2, 48:58] = _kind[4, 128:] = 1
_kind[3, 33:128] = 1 - _kind[:3, 33:128].sum(axis=0)


def passages(raw: np.ndarray, offsets: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(features, first passage of each row and one more); a row without words is one empty passage."""
    s, e, first = G.word_spans(raw, offsets)
    n = np.diff(first)
    bags = np.maximum(1, -(-n // PASSAGE))
    base = np.append(0, np.cumsum(bags))
    out = np.zeros((base[-1], WIDTH), np.float32)
    if not len(s):
        return out, base
    row = np.repeat(np.arange(len(n)), n)
    at = base[row] + (np.arange(len(s)) - first[row]) // PASSAGE
    count = np.bincount(at, minlength=base[-1]).astype(np.float32)
    total = np.maximum(count, 1)
    values = G.word_values(raw, s, e)
    out[:, :WORDS] = np.sqrt(np.bincount(at * WORDS + (values & np.uint64(WORDS - 1)).astype(np.int64), minlength=base[-1] * WORDS).reshape(-1, WORDS) / total[:, None])
    have = np.zeros((5, len(s)), np.int64)
    for k in range(5):
        c = np.append(0, np.cumsum(_kind[k][raw]))
        have[k] = c[e] - c[s]
    size = e - s
    mark_end = _kind[3][raw[e - 1]]
    shape = (have[0] > 0) + 2 * (have[1] + have[4] > 0) + 4 * (have[2] > 0) + 8 * np.minimum(have[3], 3) + 32 * mark_end
    out[:, WORDS : WORDS + SHAPES] = np.bincount(at * SHAPES + shape, minlength=base[-1] * SHAPES).reshape(-1, SHAPES) / total[:, None]
    same1, same2 = np.zeros(len(s)), np.zeros(len(s))
    same1[1:] = (values[1:] == values[:-1]) & (at[1:] == at[:-1])
    same2[2:] = (values[2:] == values[:-2]) & (at[2:] == at[:-2])
    order = np.lexsort((values, at))
    new = np.ones(len(s))
    new[1:] = (values[order][1:] != values[order][:-1]) | (at[order][1:] != at[order][:-1])
    add = lambda x: np.bincount(at, x, base[-1]) / total
    chars = np.maximum(np.bincount(at, size, base[-1]), 1)
    stats = [np.bincount(at[order], new, base[-1]) / total, add(same1), add(same2), np.bincount(at, have[0], base[-1]) / chars, np.bincount(at, have[2], base[-1]) / chars, np.bincount(at, have[3], base[-1]) / chars, np.minimum(chars / total / 16, 2), count / PASSAGE, np.ones(base[-1])]
    out[:, WORDS + SHAPES :] = np.stack(stats, axis=1)
    return out, base


def start_weights(seed: int = 7) -> dict[str, np.ndarray]:
    r = np.random.default_rng(seed)
    scale = lambda a, b: (r.standard_normal((a, b)) / np.sqrt(a)).astype(np.float64)
    return {"W": scale(WIDTH, HIDDEN), "b": np.zeros(HIDDEN), "V": scale(HIDDEN, GATE), "U": scale(HIDDEN, GATE), "w": scale(GATE, 1)[:, 0], "c": scale(HIDDEN, 1)[:, 0], "c0": np.zeros(1)}


def forward(p: dict, x: np.ndarray, base: np.ndarray) -> dict:
    """Scores of bags x[base[i]:base[i+1]] and what the backward pass needs."""
    h = np.maximum(x @ p["W"] + p["b"], 0)
    t, g = np.tanh(h @ p["V"]), 1 / (1 + np.exp(-np.clip(h @ p["U"], -40, 40)))
    s = (t * g) @ p["w"]
    bag = np.repeat(np.arange(len(base) - 1), np.diff(base))
    ex = np.exp(s - np.maximum.reduceat(s, base[:-1])[bag])
    a = ex / np.add.reduceat(ex, base[:-1])[bag]
    z = np.add.reduceat(a[:, None] * h, base[:-1], axis=0)
    y = 1 / (1 + np.exp(-np.clip(z @ p["c"] + p["c0"][0], -40, 40)))
    return {"h": h, "t": t, "g": g, "a": a, "z": z, "y": y, "bag": bag}


def gradients(p: dict, x: np.ndarray, base: np.ndarray, label: np.ndarray) -> dict[str, np.ndarray]:
    f = forward(p, x, base)
    d = (f["y"] - label) / len(label)
    dz = d[:, None] * p["c"]
    da = (f["h"] * dz[f["bag"]]).sum(axis=1)
    ds = f["a"] * (da - np.add.reduceat(f["a"] * da, base[:-1])[f["bag"]])
    dt, dg = ds[:, None] * p["w"] * f["g"] * (1 - f["t"] ** 2), ds[:, None] * p["w"] * f["t"] * f["g"] * (1 - f["g"])
    dh = (f["a"][:, None] * dz[f["bag"]] + dt @ p["V"].T + dg @ p["U"].T) * (f["h"] > 0)
    return {"W": x.T @ dh, "b": dh.sum(axis=0), "V": f["h"].T @ dt, "U": f["h"].T @ dg, "w": (f["t"] * f["g"]).T @ ds, "c": f["z"].T @ d, "c0": np.array([d.sum()])}


def train(x: np.ndarray, base: np.ndarray, label: np.ndarray, epochs: int = EPOCHS, rate: float = RATE, seed: int = 7, steps: int = STEPS) -> dict[str, np.ndarray]:
    p, r = start_weights(seed), np.random.default_rng(seed)
    m, v, step = {k: 0.0 for k in p}, {k: 0.0 for k in p}, 0
    for _ in range(max(epochs, -(-64 * steps // max(1, len(label))))):
        order = r.permutation(len(label))
        for i in range(0, len(order), 64):
            bags = order[i : i + 64]
            n = np.diff(base)[bags]
            rows = np.repeat(base[bags] - np.append(0, np.cumsum(n)[:-1]), n) + np.arange(n.sum())
            g = gradients(p, x[rows].astype(np.float64), np.append(0, np.cumsum(n)), label[bags])
            step += 1
            for k in p:
                m[k], v[k] = 0.9 * m[k] + 0.1 * g[k], 0.999 * v[k] + 0.001 * g[k] ** 2
                p[k] = p[k] - rate * (m[k] / (1 - 0.9**step) / (np.sqrt(v[k] / (1 - 0.999**step)) + 1e-8) + 1e-4 * p[k])
    return p


def held_out():
    return F.crc32(F.coalesce(F.col("doc_id").cast("string"), F.lit("")).cast("binary")) % 5 == 0


def fit(docs: DataFrame, labels: DataFrame, sample: int = SAMPLE, most: int = PASSAGES):
    """Weights, or the share of label 1 where there is nothing to learn. Only the sample's features
    come to the driver: at most ``most`` × WIDTH numbers of two bytes."""
    known = labels.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("quality").cast("int").alias("quality")).where("quality IN (0, 1) AND doc_id IS NOT NULL").where(~held_out())
    known = known.groupBy("doc_id").agg(F.max("quality").alias("quality")).orderBy(F.xxhash64("doc_id"), "doc_id").limit(sample)
    known = written(known)
    own = docs.select(F.col("doc_id").cast("long").alias("doc_id"), text_of("text").alias("body")).withColumn("key", F.xxhash64("body"))
    size = F.greatest(F.lit(1), F.ceil(F.size(words_of("body")) / PASSAGE))
    sizes = own.join(F.broadcast(known), "doc_id").groupBy("doc_id").agg(F.min(F.struct("key", size.alias("n"))).alias("x"))
    sizes = sorted(((r.doc_id, r.x.key, r.x.n) for r in sizes.collect()), key=lambda x: mixed(x[0]))  # at most the sample
    taken, total = [], 0
    for doc, key, n in sizes:
        if total + n <= most:
            total += n
            taken.append((doc, key))
    few = docs.sparkSession.createDataFrame(taken, "doc_id long, key long").join(known, "doc_id")

    def run(batches):
        for b in batches:
            raw, off = G.text_buffer(b.column("body"))
            out = []
            for i, j in G.chunks(off):
                x, base = passages(raw[off[i] : off[j]], off[i : j + 1] - off[i])
                out += [x[base[r] : base[r + 1]].astype(np.float16).tobytes() for r in range(j - i)]
            yield pa.RecordBatch.from_arrays([b.column("doc_id"), b.column("quality"), pa.array(out, pa.binary())], names=["doc_id", "quality", "x"])

    rows = own.join(F.broadcast(few), ["doc_id", "key"]).select("doc_id", "quality", "body").mapInArrow(run, "doc_id long, quality int, x binary")
    rows = sorted(rows.dropDuplicates(["doc_id"]).collect(), key=lambda r: r.doc_id)
    label = np.array([r.quality for r in rows], np.float64)
    if len(set(label)) < 2:
        return float((label.sum() + 1) / (len(label) + 2))
    x = np.concatenate([np.frombuffer(r.x, np.float16).reshape(-1, WIDTH) for r in rows])
    base = np.append(0, np.cumsum([len(r.x) // (2 * WIDTH) for r in rows]))
    return train(x, base, label)


def mixed(doc: int) -> tuple[int, int]:
    """A fixed pseudo-random order of ids."""
    return int(G.mix(np.array([doc], np.int64).view(np.uint64))[0]), doc


def quality_classifier(docs: DataFrame, labels: DataFrame, sample: int = SAMPLE) -> DataFrame:
    """doc_id, held_out, score, predicted per row of (doc_id, text)."""
    model = docs.sparkSession.sparkContext.broadcast(fit(docs, labels, sample))

    def run(batches):
        p = model.value
        p = p if isinstance(p, float) else {k: v.astype(np.float32) for k, v in p.items()}
        for b in batches:
            raw, off = G.text_buffer(b.column("body"))
            out = []
            for i, j in G.chunks(off) if b.num_rows else ():
                if isinstance(p, float):
                    out.append(np.full(j - i, p))
                else:
                    out.append(forward(p, *passages(raw[off[i] : off[j]], off[i : j + 1] - off[i]))["y"].astype(np.float64))
            score = np.concatenate(out) if out else np.zeros(0)
            yield pa.RecordBatch.from_arrays([b.column("doc_id"), pa.array(score)], names=["doc_id", "score"])

    own = docs.select(F.col("doc_id").cast("long").alias("doc_id"), text_of("text").alias("body")).mapInArrow(run, "doc_id long, score double")
    return own.select("doc_id", held_out().alias("held_out"), "score", F.when(F.col("score") >= 0.3, 1).otherwise(0).alias("predicted"))
