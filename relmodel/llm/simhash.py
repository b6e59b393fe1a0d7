"""Operator 7: SimHash near-dedup by the generalised pigeonhole principle.

Fingerprints are split into m parts with thresholds t_i whose sum is radius - m + 1: two
fingerprints within ``radius`` bits must be within t_i in some part i. Correlated bits are put into
the same part, thresholds (-1: part unused) are chosen by dynamic programming over the number of
candidate pairs estimated from value counts of 16-bit pieces (at most 65,536 a piece, whatever the
corpus). Every fingerprint probes, in part i, all values within t_i; pairs that meet are verified.

Equal fingerprints are one representative. Parts are wide enough that a value is shared by few
fingerprints on average (``parts_for``). A part value that holds more than ``CROWD`` fingerprints, and
more than ``FULL`` times that average, is no place to pair everything with everything: the fingerprints
that come together there are
linked exactly in blocks (``BLOCK`` x ``BLOCK`` comparisons, spanning links only), or, from
``MANY`` of them on, by balls: two of them are within 4 bits iff some value is within 2 bits of both.

Null text is empty; an empty text has fingerprint zero and is linked like any other. A null doc_id
gets a fingerprint and no component. Rows that share a doc_id are one node. Other columns are ignored.
"""

from __future__ import annotations

import math
from itertools import combinations

import numpy as np
import pyarrow as pa
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from relmodel.llm import _grams as G
from relmodel.llm._common import components, text_of, written

CROWD, BLOCK, MANY, FULL = 32, 4096, 1 << 18, 8
STEP = np.uint64(0x9E3779B97F4A7C15)


def majority(h: np.ndarray) -> np.uint64:
    """The bits that are set in over half of the hashes (none: 0)."""
    ones = np.zeros(64, np.int64)
    for s in range(0, len(h), 1 << 15):
        ones += np.unpackbits(h[s : s + (1 << 15)].view(np.uint8).reshape(-1, 8), axis=1, bitorder="little").sum(axis=0, dtype=np.int64)
    return np.packbits(2 * ones > len(h), bitorder="little").view(np.uint64)[0]


def sketch(data: bytes, shingle: int, words64: int) -> np.ndarray:
    """Majority bits of the shingle hashes as ``words64`` 64-bit words; the first word's hash is
    XXH64 with seed 42, further words mix it anew."""
    words = data.lower().split()  # ASCII only, both
    out = np.zeros(words64, np.uint64)
    if not words:
        return out
    text = b" ".join(words)
    size = np.fromiter(map(len, words), np.int64, len(words))
    start = np.cumsum(size + 1) - size - 1
    end = start + size
    k = min(shingle, len(words))
    digest = xxhash.xxh64_intdigest
    h = np.fromiter((digest(text[s:e], 42) for s, e in zip(start[: len(words) - k + 1].tolist(), end[k - 1 :].tolist())), np.uint64, len(words) - k + 1)
    for j in range(words64):
        out[j] = majority(h if j == 0 else G.mix(h + np.uint64(int(STEP) * j % 2**64)))
    return out


def fingerprints(docs: DataFrame, shingle: int = 4, words64: int = 1) -> DataFrame:
    """(doc, fp array<long>); ``docs`` has doc and body."""

    def run(batches):
        for b in batches:
            raw, off = G.text_buffer(b.column("body"))
            data = raw.tobytes() if off[0] == 0 and off[-1] == len(raw) else raw[off[0] : off[-1]].tobytes()
            o = (off - off[0]).tolist()
            fp = np.concatenate([sketch(data[o[i] : o[i + 1]], shingle, words64) for i in range(b.num_rows)]) if b.num_rows else np.zeros(0, np.uint64)
            lists = pa.ListArray.from_arrays(pa.array(np.arange(b.num_rows + 1, dtype=np.int32) * words64), pa.array(fp.view(np.int64)))
            yield pa.RecordBatch.from_arrays([b.column("doc"), lists], names=["doc", "fp"])

    return docs.select("doc", "body").mapInArrow(run, "doc long, fp array<long>")


def correlations(codes: DataFrame, words64: int) -> np.ndarray:
    """Counts of bit pairs set together, over all codes; each task sends sums only."""
    n = 64 * words64

    def run(batches):
        total = np.zeros((n, n), np.int64)
        for b in batches:
            x = b.column("fp").flatten().to_numpy().reshape(-1, words64).view(np.uint8)
            for s in range(0, len(x), 4096):
                bits = np.unpackbits(x[s : s + 4096].reshape(-1, 8 * words64), axis=1, bitorder="little").astype(np.float32)
                total += (bits.T @ bits).astype(np.int64)
        i, j = np.triu_indices(n)
        yield pa.RecordBatch.from_arrays([pa.array((i * n + j).astype(np.int32)), pa.array(total[i, j])], names=["ij", "n"])

    out = np.zeros((n, n))
    for r in codes.select("fp").mapInArrow(run, "ij int, n long").groupBy("ij").agg(F.sum("n").alias("n")).toLocalIterator():
        out[r.ij // n, r.ij % n] = out[r.ij % n, r.ij // n] = r.n
    return out


def grouped_bits(both: np.ndarray, n: int, m: int) -> list[list[int]]:
    """m parts of bits, each filled with the bits most correlated to those it has."""
    p = np.diag(both) / max(n, 1)
    var = np.sqrt(np.maximum(p * (1 - p), 1e-12))
    corr = np.abs((both / max(n, 1) - np.outer(p, p)) / np.outer(var, var))
    left, parts = list(range(len(p))), []
    for i in range(m):
        size = math.ceil(len(left) / (m - i))
        part = [left.pop(0)]
        while len(part) < size:
            nxt = max(left, key=lambda b: (corr[b, part].sum(), -b))
            left.remove(nxt)
            part.append(nxt)
        parts.append(sorted(part))
    return parts


def piece(bits: list[int]):
    """The named bits of column fp as one number."""
    first, n = bits[0], len(bits)
    if n < 63 and bits == list(range(first, first + n)):  # a run of bits: one or two shifts
        own = F.shiftrightunsigned(F.col("fp")[first // 64], first % 64)
        if first % 64 + n > 64:
            own = own.bitwiseOR(F.shiftleft(F.col("fp")[first // 64 + 1], 64 - first % 64))
        return own.bitwiseAND((1 << n) - 1)
    out = F.lit(0).cast("long")
    for k, b in enumerate(bits):
        out = out.bitwiseOR(F.shiftleft(F.shiftrightunsigned(F.col("fp")[b // 64], b % 64).bitwiseAND(1), k))
    return out


def distances(codes: DataFrame, parts: list[list[int]]) -> list[np.ndarray]:
    """Per part: number of pairs of codes (each with each, itself too) at each distance.

    Exact for pieces of up to 16 bits, from their value counts by a Walsh-Hadamard transform; wider
    parts are taken as independent pieces."""
    pieces = [(i, bits[s : s + 16]) for i, bits in enumerate(parts) for s in range(0, len(bits), 16)]
    keys = F.array(*(F.struct(F.lit(k).alias("k"), piece(bits).cast("int").alias("v")) for k, (_, bits) in enumerate(pieces)))
    counts = [np.zeros(1 << len(bits)) for _, bits in pieces]
    for r in codes.select(F.explode(keys).alias("x")).groupBy("x.k", "x.v").count().toLocalIterator():  # at most 65,536 a piece
        counts[r.k][r.v] = r["count"]
    out: list[np.ndarray | None] = [None] * len(parts)
    for (i, bits), c in zip(pieces, counts):
        n = c.sum()
        x = c.copy()
        for inverse in (False, True):
            for b in range(len(bits)):
                x = x.reshape(-1, 2, 1 << b)
                x = np.stack([x[:, 0] + x[:, 1], x[:, 0] - x[:, 1]], axis=1).reshape(-1)
            x = x / len(c) if inverse else x * x
        ones = np.array([bin(v).count("1") for v in range(1 << len(bits))])
        pairs = np.bincount(ones, np.maximum(x, 0), len(bits) + 1)
        out[i] = pairs if out[i] is None else np.convolve(out[i], pairs) / max(n * n, 1)
    return out


def thresholds(pairs: list[np.ndarray], codes: int, total: int, probe: float = 4.0) -> list[int]:
    """t_i >= -1 with the given sum and the least estimated cost (candidates + probes), by dynamic
    programming over parts."""
    best: dict[int, tuple[float, list[int]]] = {0: (0.0, [])}
    for d in pairs:
        cum, ball, nxt = np.cumsum(d), np.cumsum([math.comb(len(d) - 1, e) for e in range(len(d))]), {}
        for s, (cost, chosen) in best.items():
            for t in range(-1, min(len(d) - 1, 4)):
                c = cost + (cum[t] + probe * codes * (ball[t] + 1) if t >= 0 else 0)
                if s + t not in nxt or c < nxt[s + t][0]:
                    nxt[s + t] = (c, chosen + [t])
        best = nxt
    return best[total][1]


def _near(fp_a, fp_b, words64: int):
    out = F.bit_count(fp_a[0].bitwiseXOR(fp_b[0]))
    for j in range(1, words64):
        out = out + F.bit_count(fp_a[j].bitwiseXOR(fp_b[j]))
    return out


def blocks(crowd: DataFrame, radius: int, words64: int, many: int) -> DataFrame:
    """Spanning links (a, b) among codes that meet in crowded places: all block pairs are compared."""
    count = max(1, math.ceil(many / BLOCK))
    own = crowd.withColumn("x", F.pmod(F.xxhash64("node"), F.lit(count)).cast("int"))
    own = own.withColumn("y", F.explode(F.sequence(F.lit(0), F.lit(count - 1)))).select("node", "fp", F.greatest("x", "y").alias("i"), F.least("x", "y").alias("j"), (F.col("x") >= F.col("y")).alias("left"), (F.col("x") <= F.col("y")).alias("right"))

    def link(t: pa.Table) -> pa.Table:
        node = t.column("node").to_numpy()
        fp = t.column("fp").combine_chunks().flatten().to_numpy().view(np.uint64).reshape(-1, words64)
        lo = {int(x): int(x) for x in node}

        def root(x):
            while lo[x] != x:
                lo[x] = x = lo[lo[x]]
            return x

        left, right = t.column("left").to_numpy(), t.column("right").to_numpy()
        a, b, out = np.flatnonzero(left), np.flatnonzero(right), []
        for x in a:
            d = np.bitwise_count(fp[b] ^ fp[x]).sum(axis=1, dtype=np.int32)
            for y in b[d <= radius]:
                u, v = root(int(node[x])), root(int(node[y]))
                if u != v:
                    lo[max(u, v)] = min(u, v)
                    out.append((int(node[x]), int(node[y])))
        return pa.table({"a": pa.array([x for x, _ in out], pa.int64()), "b": pa.array([y for _, y in out], pa.int64())})

    return own.groupBy("i", "j").applyInArrow(link, "a long, b long")


def balls(crowd: DataFrame) -> DataFrame:
    """Links (a, b) among 64-bit codes within 4 bits: everyone names all values within 2 bits of
    itself, and who names the same value is linked through its least namer. Linear in the codes."""
    one = np.uint64(1) << np.arange(64, dtype=np.uint64)
    masks = np.array([np.uint64(0), *one, *(a | b for a, b in combinations(one, 2))], np.uint64)

    def run(batches):
        for b in batches:
            node, fp = b.column("node").to_numpy(), b.column("fp").flatten().to_numpy().view(np.uint64)
            for s in range(0, len(node), 64):
                z = (fp[s : s + 64, None] ^ masks[None, :]).reshape(-1)
                yield pa.RecordBatch.from_arrays([pa.array(z.view(np.int64)), pa.array(np.repeat(node[s : s + 64], len(masks)))], names=["z", "node"])

    named = crowd.mapInArrow(run, "z long, node long")
    first = named.groupBy("z").agg(F.min("node").alias("a"), F.max("node").alias("m")).where("a < m").drop("m")
    return named.join(first.hint("merge"), "z").where("a < node").select("a", F.col("node").alias("b")).distinct()


def links(codes: DataFrame, radius: int, words64: int, parts: list[list[int]], t: list[int], accept: int | None = None, crowd: int | None = None) -> DataFrame:
    """Links (a, b) of codes (node, fp) that meet in some part and are within ``accept`` bits
    (default ``radius``, for which no pair is missed). ``crowd``: fingerprints that a place may hold."""
    accept, crowd = radius if accept is None else accept, CROWD if crowd is None else crowd
    used = [(i, bits, e) for i, (bits, e) in enumerate(zip(parts, t)) if e >= 0]
    keyed = codes.select("node", F.col("fp")[0].alias("w"), *(piece(bits).alias(f"k{i}") for i, bits, _ in used))

    def place_at(i, masks=None):
        if masks is None:
            return F.array(F.struct(F.lit(i).alias("part"), F.col(f"k{i}").alias("key")))
        near = F.array(*(F.lit(m).cast("long") for m in masks))
        return F.transform(near, lambda m: F.struct(F.lit(i).alias("part"), F.col(f"k{i}").bitwiseXOR(m).alias("key")))

    own = [place_at(i) for i, _, _ in used]
    ask = [place_at(i, [sum(1 << b for b in c) for r in range(e + 1) for c in combinations(range(len(bits)), r)]) for i, bits, e in used]
    data = keyed.select("node", "w", F.explode(F.flatten(F.array(*own))).alias("x")).select("node", "w", "x.part", "x.key")
    probe = data if all(e == 0 for _, _, e in used) else keyed.select("node", "w", F.explode(F.flatten(F.array(*ask))).alias("x")).select("node", "w", "x.part", "x.key")
    crowded = written(data.groupBy("part", "key").count().where(F.col("count") > crowd).select("part", "key"))
    place = ["part", "key"]
    a = data.join(crowded, place, "left_anti").alias("a")
    b = probe.join(crowded, place, "left_anti").hint("merge").alias("b")  # Spark sizes what is exploded as if it were not
    met = a.join(b, place).where(F.col("a.node") < F.col("b.node"))
    if words64 == 1:  # the whole fingerprint travels with the key
        met = met.where(F.bit_count(F.col("a.w").bitwiseXOR(F.col("b.w"))) <= accept)
    met = met.select(F.col("a.node").alias("a"), F.col("b.node").alias("b")).distinct()
    if words64 > 1:  # no sieve on a part of the bits: it could lose a pair within the bound
        x, y = codes.select(F.col("node").alias("a"), F.col("fp").alias("fa")), codes.select(F.col("node").alias("b"), F.col("fp").alias("fb"))
        met = met.join(x.hint("merge"), "a").join(y.hint("merge"), "b").where(_near(F.col("fa"), F.col("fb"), words64) <= accept).select("a", "b")
    out = met
    if not crowded.isEmpty():
        who = data.join(crowded, place, "left_semi").select("node").union(probe.join(crowded, place, "left_semi").select("node")).distinct()
        met_there = written(codes.join(who, "node"))
        many = met_there.count()
        dense = balls(met_there) if many > MANY and words64 == 1 and accept == 4 else blocks(met_there, accept, words64, many)
        out = out.union(dense)
    return out


def code_links(codes: DataFrame, radius: int = 4, m: int | None = None) -> DataFrame:
    """Links (a, b) of 64-bit codes (node, fp) by the generalised pigeonhole: m parts of correlated bits,
    thresholds by dynamic programming, so that every two codes within ``radius`` bits are connected."""
    n = codes.count()
    if n < 2:
        return codes.select(F.col("node").alias("a"), F.col("node").alias("b")).limit(0)
    m = m or parts_for(n)
    parts = grouped_bits(correlations(codes, 1), n, m)
    return links(codes, radius, 1, parts, thresholds(distances(codes, parts), n, radius - m + 1), crowd=max(CROWD, FULL * n >> 64 // m))


def parts_for(n: int) -> int:
    """4 parts, or 3 from where the values of 16 bits hold ``CROWD`` / ``FULL`` of ``n`` codes on average:
    wider parts cost more probes a code, but narrow ones would make every place a crowd."""
    return 4 if n * FULL < CROWD << 16 else 3


def near_components(docs: DataFrame, shingle: int = 4, radius: int = 4) -> DataFrame:
    """(doc, fp, component) per row of (doc, body): 64-bit fingerprints linked within ``radius`` bits."""
    rows = written(fingerprints(docs, shingle))
    codes = written(rows.where("doc IS NOT NULL").groupBy("fp").agg(F.min("doc").alias("node")))
    # One node is one doc_id: rows that share it are linked below through their codes.
    found = code_links(codes, radius)
    own = rows.join(codes, "fp", "left")
    shared = own.where("doc IS NOT NULL").groupBy("doc").agg(F.min("node").alias("a"), F.max("node").alias("b")).where("a <> b").select("a", "b")
    label = components(found.union(shared))
    return own.join(label, "node", "left").select("doc", "fp", F.when(F.col("doc").isNotNull(), F.coalesce("component", "node")).alias("component"))


def simhash_dedup(docs: DataFrame, shingle: int = 4, radius: int = 4) -> DataFrame:
    """doc_id, fingerprint (16 hex digits), component_id (smallest doc_id reachable) per row."""
    own = docs.select(F.col("doc_id").cast("long").alias("doc"), text_of("text").alias("body"))
    out = near_components(own, shingle, radius)
    return out.select(F.col("doc").alias("doc_id"), F.lower(F.lpad(F.hex(F.col("fp")[0]), 16, "0")).alias("fingerprint"), F.col("component").alias("component_id"))


def similar_components(docs: DataFrame, shingle: int = 5, similarity: float = 0.8) -> DataFrame:
    """(doc, component): documents whose sets of word shingles have a Jaccard similarity of at least
    ``similarity``, linked; component = smallest doc reachable. Exact, see ``relmodel.llm.similar``."""
    from relmodel.llm import similar  # which uses this module

    own = written(similar.similar_sets(docs.withColumn("key", F.xxhash64("body")), shingle, similarity).select("doc", "component").distinct())
    return own.join(own.groupBy("component").agg(F.min("doc").alias("first")), "component").select("doc", F.col("first").alias("component"))
