"""Operator 2: suffix-array dedup of repeated byte strings.

Suffixes are taken at content-defined anchors, so every string of ``length`` bytes that occurs twice
is met through equal anchors. Anchors that occur once are dropped. Contexts of the others meet by
anchor; a task sorts, inside each group, the suffixes to the right and the reversed prefixes to the
left with a merge sort whose comparisons find the common extension by binary search over prefix
polynomial hashes. Neighbours' extensions are verified on the bytes, and a group with a hash
collision is sorted again by its bytes. Longest common extensions of neighbours then tell, for each
offset of a string around the anchor, which occurrences are equal; all but the first are removed.

Skew: equal contexts inside a batch are combined before the shuffle. Anchors with more than ``HOT``
occurrences are taken apart into single strings, at most one row of each a 4 MB chunk, which a running
window reads in order without holding them; the other anchors are solved in units of ``UNIT`` bytes.

Null text is empty; a null doc_id takes no part. Rows that share a doc_id count as one document.
Texts shorter than ``length`` keep all bytes. Other columns are ignored.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from relmodel.llm import _grams as G
from relmodel.llm._common import drop_written, text_of, written
from relmodel.llm.substring import copies_of

LENGTH, GRAM, HOT, UNIT = 100, 40, 2000, 1 << 21
PRIME = np.uint64(2147483629)
_pow: dict[int, np.ndarray] = {}


def _powers_mod(base: int, n: int) -> np.ndarray:
    got = _pow.get(base)
    if got is None or len(got) < n:
        size, p = 1 << max(12, int(n).bit_length()), np.ones(1, np.uint64)
        step = base
        while len(p) < size:
            p = np.concatenate([p, p * np.uint64(step) % PRIME])
            step = step * step % int(PRIME)
        _pow[base] = got = p
    return got


class HashedText:
    """Bytes with prefix polynomial hashes modulo a prime; compares suffixes in log2(longest) steps."""

    def __init__(self, data: np.ndarray, base: int = 911382323):
        self.data, self.power = data, _powers_mod(base, len(data) + 1)
        pre = np.zeros(len(data) + 1, np.uint64)
        np.cumsum((data.astype(np.uint64) + np.uint64(1)) * self.power[: len(data)] % PRIME, out=pre[1:])
        self.pre = pre % PRIME

    def common(self, a: np.ndarray, b: np.ndarray, most: np.ndarray) -> np.ndarray:
        """Longest common extension of positions a and b, at most ``most``, by binary search."""
        lo, hi = np.zeros(len(a), np.int64), most.astype(np.int64).copy()
        x, y = np.minimum(a, b), np.maximum(a, b)
        shift = self.power[y - x]
        while (open_ := lo < hi).any():
            mid = (lo + hi + 1) >> 1
            u = (self.pre[x + mid] + PRIME - self.pre[x]) % PRIME * shift % PRIME
            v = (self.pre[y + mid] + PRIME - self.pre[y]) % PRIME
            same = u == v
            lo, hi = np.where(open_ & same, mid, lo), np.where(open_ & ~same, mid - 1, hi)
        return lo

    def after(self, a, b, la, lb) -> np.ndarray:
        """True where the suffix at a (length la) sorts after the one at b."""
        n = self.common(a, b, np.minimum(la, lb))
        end = n == np.minimum(la, lb)
        ca, cb = self.data[np.minimum(a + n, len(self.data) - 1)], self.data[np.minimum(b + n, len(self.data) - 1)]
        return np.where(end, la > lb, ca > cb)


def merge_sort(text: HashedText, start: np.ndarray, size: np.ndarray, group: np.ndarray) -> np.ndarray:
    """Order of the suffixes by (group, bytes); ``group`` must be sorted. Bottom-up and stable, all
    merges of a level at once: each suffix finds its place in the neighbour run by binary search."""
    order = np.arange(len(start))
    begins = np.flatnonzero(np.append(True, group[1:] != group[:-1]))
    sizes = np.diff(np.append(begins, len(group)))
    g0, gn = np.repeat(begins, sizes), np.repeat(sizes, sizes)
    local, width = np.arange(len(start)) - g0, 1
    while width < (sizes.max() if len(sizes) else 0):
        act = np.flatnonzero(gn > width)
        run, within = local[act] // width, local[act] % width
        right = run % 2 == 1
        other = np.where(right, run - 1, run + 1) * width
        olen = np.clip(gn[act] - other, 0, width)
        lo, hi, me = np.zeros(len(act), np.int64), olen.copy(), order[act]
        while (open_ := lo < hi).any():
            k = np.flatnonzero(open_)
            mid = (lo[k] + hi[k]) >> 1
            it = order[g0[act[k]] + other[k] + mid]
            mine = me[k]
            before = np.where(right[k], ~text.after(start[it], start[mine], size[it], size[mine]), text.after(start[mine], start[it], size[mine], size[it]))
            lo[k], hi[k] = np.where(before, mid + 1, lo[k]), np.where(before, hi[k], mid)
        place = g0[act] + (run // 2) * 2 * width + within + lo
        order[place] = me
        width *= 2
    return order


def sorted_extensions(data: np.ndarray, start: np.ndarray, size: np.ndarray, group: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(order, extension shared with the predecessor in that order; 0 at the start of a group)."""
    text = HashedText(data)
    order = merge_sort(text, start, size, group)
    a, b = order[:-1], order[1:]
    most = np.where(group[a] == group[b], np.minimum(size[a], size[b]), 0)
    ext = text.common(start[a], start[b], most)
    n = ext.sum()  # verification: the bytes of every claimed extension
    if n:
        at = np.repeat(np.append(0, np.cumsum(ext)[:-1]), ext)
        step = np.arange(n) - at
        differ = data[np.repeat(start[a], ext) + step] != data[np.repeat(start[b], ext) + step]
        bad = np.unique(group[np.repeat(a, ext)[differ]])
        for g in bad:
            own = np.flatnonzero(group == g)
            texts = {i: data[start[i] : start[i] + size[i]].tobytes() for i in own}
            put = sorted(own, key=lambda i: (texts[i], i))
            order[own] = put
            for q in range(1, len(own)):
                x, y = texts[put[q - 1]], texts[put[q]]
                ext[own[q] - 1] = next((i for i in range(min(len(x), len(y))) if x[i] != y[i]), min(len(x), len(y)))
    return order, np.append(0, ext)


def repeats_in_groups(g, doc, pos, off, wins, raw, offsets, length: int):
    """Of contexts that meet by anchor: (row, offset) pairs of strings that also occur earlier.

    Row r holds the bytes raw[offsets[r]:offsets[r+1]] around an anchor ``off[r]`` bytes in; its
    strings start wins[r] places, from the context's first byte on."""
    order0 = np.lexsort((pos, doc, g))
    twin = np.append(False, np.all([x[order0][1:] == x[order0][:-1] for x in (g, doc, pos, off, wins)], axis=0))[: len(order0)]
    for q in np.flatnonzero(twin):  # the same place of a repeated row is no repeat
        x, y = order0[q - 1], order0[q]
        twin[q] = raw[offsets[x] : offsets[x + 1]].tobytes() == raw[offsets[y] : offsets[y + 1]].tobytes()
    order0 = order0[~twin]
    n = len(order0)
    group = g[order0]
    group = np.cumsum(np.append(0, group[1:] != group[:-1]))  # rows in order0 from here on
    s, o, w = offsets[:-1][order0] + off[order0], off[order0], wins[order0]
    rlen = offsets[1:][order0] - s
    ro, rext = sorted_extensions(raw, s, rlen, group)
    back = raw[::-1]
    lo_, lext = sorted_extensions(back, len(raw) - s, o, group)
    rows, offs = [], []
    for d in range(int(o.max()) + 1 if n else 0):
        has = (d <= o) & (d > o - w)
        if has.sum() < 2:
            continue
        rc, lc = np.empty(n, np.int64), np.empty(n, np.int64)
        rc[ro] = np.cumsum(rext < length - d)
        lc[lo_] = np.cumsum((lext < d) | np.append(True, group[lo_][1:] != group[lo_][:-1]))
        k = np.flatnonzero(has)
        key = lc[k] * np.int64(n + 1) + rc[k]
        by = np.argsort(key, kind="stable")  # k ascends in (g, doc, pos), so the first of a key is the earliest
        later = np.append(False, key[by][1:] == key[by][:-1])
        hit = k[by][later]
        rows.append(order0[hit]), offs.append(np.full(len(hit), d))
    return (np.concatenate(rows), np.concatenate(offs)) if rows else (np.zeros(0, np.int64),) * 2


def _anchors(length: int, gram: int):
    def run(batches):
        for b in batches:
            raw, off = G.text_buffer(b.column("body"))
            doc, c = b.column("doc").to_numpy(zero_copy_only=False), b.column("c").to_numpy(zero_copy_only=False)
            for i, j in G.chunks(off):
                o = off[i : j + 1] - off[i]
                row, at, _, _, h = G.anchor_runs(G.BYTE_VALUES[raw[off[i] : off[j]]], o, gram, length)
                if len(row):
                    pos = at - o[row]
                    u = G.mix(c[row + i].view(np.uint64) + pos.astype(np.uint64) * G.BASE)
                    yield pa.RecordBatch.from_arrays([pa.array(h.view(np.int64)), pa.array(u.view(np.int64)), pa.array(doc[row + i]), pa.array(pos.astype(np.int32))], names=["g", "u", "doc", "pos"])

    return run


CONTEXT = "g long, doc long, pos int, off int, wins int, ctx binary"


def _contexts(length: int, gram: int):
    """Contexts of repeated anchors, equal ones of a chunk combined. ``wins`` = 0: a single string of a hot
    anchor; ``wins`` < 0: not a context but -wins strings from ``pos`` on that are known to occur earlier."""

    def emit(g, doc, pos, off, wins, ctx):
        return pa.RecordBatch.from_arrays([pa.array(x, t) for x, t in zip((g, doc, pos, off, wins, ctx), (pa.int64(), pa.int64(), pa.int32(), pa.int32(), pa.int32(), pa.binary()))], names=["g", "doc", "pos", "off", "wins", "ctx"])

    def run(batches):
        for b in batches:
            raw, off = G.text_buffer(b.column("body"))
            doc, lists = b.column("doc").to_numpy(zero_copy_only=False), b.column("at")
            flat, lo = lists.flatten().to_numpy(), np.append(0, np.cumsum(lists.value_lengths().to_numpy()))
            for i, j in G.chunks(off, 1 << 22):
                part, o = raw[off[i] : off[j]], off[i : j + 1] - off[i]
                row, at, p0, p1, h = G.anchor_runs(G.BYTE_VALUES[part], o, gram, length)
                keep = np.zeros(len(part) + 1, np.int8)
                for r in range(i, j):
                    x = flat[lo[r] : lo[r + 1]]
                    keep[np.where(x < 0, -x - 1, x) + o[r - i]] = np.where(x < 0, 2, 1)
                take = np.flatnonzero(keep[at] > 0)
                if not len(take):
                    continue
                hot = keep[at[take]] == 2
                row, at, p0, p1, h = (x[take] for x in (row, at, p0, p1, h))
                if hot.any():  # single strings, dealt out by their own hash
                    n = np.where(hot, p1 - p0 + 1, 1)
                    first = np.where(hot, p0, 0)
                    k = np.repeat(np.arange(len(row)), n)
                    step = np.arange(n.sum()) - np.repeat(np.append(0, np.cumsum(n)[:-1]), n)
                    hot = hot[k]
                    p0 = np.where(hot, first[k] + step, p0[k])
                    p1 = np.where(hot, p0, p1[k])
                    own = G.span_hash(G.prefix(G.BYTE_VALUES[part], G.BASE), p0, p0 + length, G.BASE)
                    row, at, h = row[k], np.where(hot, p0, at[k]), np.where(hot, own, h[k])
                wins = np.where(hot, 0, p1 - p0 + 1)
                d, pos, body = doc[row + i], at - o[row], part.tobytes()
                order = np.lexsort((pos, d, h))
                seen: dict[tuple, int] = {}
                out, dup = [], []
                last = None
                for q, (hq, x, y, z, n) in enumerate(zip(h[order].tolist(), p0[order].tolist(), (p1[order] + length).tolist(), at[order].tolist(), wins[order].tolist())):
                    if hq != last:
                        seen, last = {}, hq
                    key = (z - x, body[x:y], n)
                    place = (d[order[q]], pos[order[q]])
                    if key not in seen:
                        seen[key] = place
                        out.append((q, key))
                    elif seen[key] != place:  # else a repeated row
                        dup.append(q)
                if dup:
                    q = order[dup]
                    yield emit(np.zeros(len(q), np.int64), d[q], (p0[q] - o[row[q]]).astype(np.int32), np.zeros(len(q), np.int32), (p0[q] - p1[q] - 1).astype(np.int32), [None] * len(q))
                q = order[[x for x, _ in out]]
                yield emit(h[q].view(np.int64), d[q], pos[q].astype(np.int32), np.array([x[0] for _, x in out], np.int32), wins[q].astype(np.int32), [x[1] for _, x in out])

    return run


def _spans(length: int, unit: int = UNIT):
    """Sorted contexts of whole anchors in, removed byte spans (doc, a, z) out; solved in units of about
    ``unit`` bytes of contexts and one anchor more (at most HOT contexts)."""

    def solve(t: pa.Table):
        g, doc, pos, off, wins = (t.column(c).to_numpy() for c in ("g", "doc", "pos", "off", "wins"))
        ctx = t.column("ctx").combine_chunks()
        if isinstance(ctx, pa.ChunkedArray):
            ctx = pa.concat_arrays(ctx.chunks) if ctx.num_chunks else pa.array([], pa.binary())
        _, o, data = ctx.buffers()
        offsets = np.frombuffer(o, np.int32)[ctx.offset : ctx.offset + len(ctx) + 1].astype(np.int64)
        raw = np.frombuffer(data, np.uint8)[offsets[0] : offsets[-1]]
        row, d = repeats_in_groups(g, doc, pos.astype(np.int64), off.astype(np.int64), wins.astype(np.int64), raw, offsets - offsets[0], length)
        if not len(row):
            return None
        p = pos[row].astype(np.int64) - d
        by = np.lexsort((p, row))
        row, p = row[by], p[by]
        new = np.append(True, (row[1:] != row[:-1]) | (p[1:] != p[:-1] + 1))
        k = np.flatnonzero(new)
        end = p[np.append(k[1:], len(p)) - 1] + length
        return pa.RecordBatch.from_arrays([pa.array(doc[row[k]]), pa.array(p[k].astype(np.int32)), pa.array(end.astype(np.int32))], names=["doc", "a", "z"])

    def run(batches):
        held: list[pa.RecordBatch] = []
        size = 0
        for b in batches:
            for i in range(0, b.num_rows, 2048):
                held.append(b.slice(i, 2048))
                size += pc.sum(pc.binary_length(held[-1].column("ctx"))).as_py()
                if size < unit:
                    continue
                t = pa.Table.from_batches(held)
                g = t.column("g").to_numpy()
                cut = int(np.searchsorted(g, g[-1], "left"))  # the last anchor may go on in the next batch
                if cut:
                    if (out := solve(t.slice(0, cut))) is not None:
                        yield out
                    held = t.slice(cut).combine_chunks().to_batches()
                    size = sum(pc.sum(pc.binary_length(x.column("ctx"))).as_py() for x in held)
        if held and (out := solve(pa.Table.from_batches(held))) is not None:
            yield out

    return run


def removed_spans(docs: DataFrame, length: int = LENGTH, gram: int = GRAM, hot: int = HOT) -> tuple[DataFrame, DataFrame]:
    """((doc, spans array<struct<a,z>>), (doc): whole copies)."""
    own = docs.where("doc IS NOT NULL")
    copies = written(copies_of(own))
    anchors = own.withColumn("c", F.xxhash64("body")).mapInArrow(_anchors(length, gram), "g long, u long, doc long, pos int")
    again = anchors.groupBy("g").agg(F.min("u").alias("a"), F.max("u").alias("z"), F.count("*").alias("n")).where("a <> z").select("g", (F.col("n") > hot).alias("hot"))
    at = anchors.select("g", "doc", "pos").join(again, "g").join(copies, "doc", "left_anti")
    at = written(at.groupBy("doc").agg(F.collect_list(F.when(F.col("hot"), -F.col("pos") - 1).otherwise(F.col("pos"))).alias("at")))
    ctx = written(own.join(at, "doc").mapInArrow(_contexts(length, gram), CONTEXT))
    met = ctx.where("wins > 0").repartition("g").sortWithinPartitions("g").mapInArrow(_spans(length), "doc long, a int, z int")
    sure = ctx.where("wins < 0").select("doc", F.col("pos").alias("a"), (F.col("pos") - F.col("wins") - 1 + length).cast("int").alias("z"))
    single = ctx.where("wins = 0").select("g", "ctx", F.struct("doc", "pos").alias("place"))
    first = F.first("place").over(Window.partitionBy("g", "ctx").orderBy("place").rowsBetween(Window.unboundedPreceding, 0))
    single = single.withColumn("first", first).where("place > first")  # read in order, nothing is held
    single = single.select("place.doc", F.col("place.pos").alias("a"), (F.col("place.pos") + length).cast("int").alias("z"))
    spans = written(met.union(sure).union(single).groupBy("doc").agg(F.collect_list(F.struct("a", "z")).alias("spans")))
    drop_written(at, ctx)
    return spans, copies


def _cut(length: int):
    def run(batches):
        for b in batches:
            out = []
            for doc, body, spans, copy in zip(b.column("doc").to_pylist(), b.column("body"), b.column("spans"), b.column("copy").to_pylist()):
                data = np.frombuffer(body.as_buffer(), np.uint8)
                gone = np.zeros(len(data) + 1, np.int32)
                if copy and len(data) >= length:
                    gone[0] = 1
                elif spans.is_valid:
                    a, z = (spans.values.field(x).to_numpy() for x in ("a", "z"))
                    a, z = a[z <= len(data)], z[z <= len(data)]
                    np.add.at(gone, a, 1)
                    np.add.at(gone, z, -1)
                gone = np.cumsum(gone[:-1]) > 0
                edge = np.flatnonzero(np.diff(np.concatenate([[0], gone, [0]]).astype(np.int8)))
                out.append((doc, len(data), int(gone.sum()), [{"a": int(x), "z": int(y)} for x, y in zip(edge[::2], edge[1::2])], data[~gone].tobytes()))
            cols = list(zip(*out)) or [[]] * 5
            kinds = (pa.int64(), pa.int64(), pa.int64(), pa.list_(pa.struct([("a", pa.int64()), ("z", pa.int64())])), pa.binary())
            yield pa.RecordBatch.from_arrays([pa.array(x, t) for x, t in zip(cols, kinds)], names=["doc_id", "n_bytes", "n_removed", "spans", "kept"])

    return run


def suffix_dedup(docs: DataFrame, length: int = LENGTH, gram: int = GRAM) -> DataFrame:
    """doc_id, n_bytes, n_removed, spans (removed, maximal), kept (remaining bytes) per row: a byte
    goes if a string of ``length`` bytes covers it that also starts earlier (smaller doc_id, or same
    document and earlier start), judged on the input."""
    own = docs.select(F.col("doc_id").cast("long").alias("doc"), text_of("text").alias("body"))
    spans, copies = removed_spans(own, length, gram)
    return (
        own.join(spans, "doc", "left").join(copies.withColumn("copy", F.lit(True)), "doc", "left")
        .mapInArrow(_cut(length), "doc_id long, n_bytes long, n_removed long, spans array<struct<a:long,z:long>>, kept binary")
    )
