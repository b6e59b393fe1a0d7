"""Operator 3: substring dedup over word windows by level-wise doubling.

The levels look at windows of about a quarter (``LEAST`` words or a little less), a half and then all of
the wanted length. Only what stands in two different texts at one length goes on to twice that length,
and the search ends at a level that nothing survives. Below the full length a document shows, for each
full window that is still a candidate, only the shorter window with the least hash inside it
(content-defined, so equal full windows show equal parts): all repeats are found while a fraction of
the positions is shuffled.

Null text is an empty text; a null doc_id takes no part (the row comes back unchanged). Rows that
share a doc_id count as one document and each gets the same cuts. Texts shorter than the window
keep all words; very long texts are searched in full. Other columns are ignored.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from relmodel.llm import _grams as G
from relmodel.llm._common import drop_written, text_of, written

WINDOW, LEAST = 50, 13
ODD = np.uint64(0xA24BAED4963EE407)


def copies_of(docs: DataFrame) -> DataFrame:
    """(doc, ) of documents whose whole text also stands under a smaller doc_id."""
    own = docs.select("doc", F.md5(F.col("body").cast("binary")).alias("m"))
    return own.join(own.groupBy("m").agg(F.min("doc").alias("first")), "m").where("doc > first").select("doc").distinct()


def _docs(docs: DataFrame) -> DataFrame:
    return docs.select(F.col("doc_id").cast("long").alias("doc"), text_of("text").alias("body"))


def levels(window: int, least: int = LEAST) -> list[int]:
    """Lengths before the full one, each half of the next, down to ``least`` or one halving."""
    out: list[int] = []
    n = window
    while n > 1 and (not out or n > least):
        n = (n + 1) // 2
        out.insert(0, n)
    return out


def _kept(b: pa.RecordBatch):
    """Reads column ``at``: a function of (row, first word of the row) that gives its places in the buffer."""
    flat, lo = b.column("at").flatten().to_numpy(), np.append(0, np.cumsum(b.column("at").value_lengths().to_numpy()))
    return lambda r, first: flat[lo[r] : lo[r + 1]] + first


def _level(window: int, length: int, before: int | None):
    """Parts of ``length`` words of the windows whose part at the level ``before`` repeats (None: all)."""

    def run(batches):
        for b in batches:
            raw, off = G.text_buffer(b.column("body"))
            doc, c = b.column("doc").to_numpy(zero_copy_only=False), b.column("c").to_numpy(zero_copy_only=False)
            kept = None if before is None else _kept(b)
            for i, j in G.chunks(off):
                part, o = raw[off[i] : off[j]], off[i : j + 1] - off[i]
                s, e, first = G.word_spans(part, o)
                values = G.word_values(part, s, e)
                row, at, p0, p1, h = G.anchor_runs(values, first, length, window)
                if before is not None and len(row):
                    keep = np.zeros(len(values) + 1, bool)
                    for r in range(i, j):
                        keep[kept(r, first[r - i])] = True
                    _, old, q0, q1, _ = G.anchor_runs(values, first, before, window)
                    open_ = np.zeros(len(values) + 2, np.int64)  # candidates among the windows, as starts
                    np.add.at(open_, q0[keep[old]], 1)
                    np.add.at(open_, q1[keep[old]] + 1, -1)
                    count = np.append(0, np.cumsum(np.cumsum(open_) > 0))
                    take = count[p1 + 1] > count[p0]
                    row, at, h = row[take], at[take], h[take]
                if len(row):
                    yield pa.RecordBatch.from_arrays([pa.array(h.view(np.int64)), pa.array(c[row + i]), pa.array(doc[row + i]), pa.array((at - first[row]).astype(np.int32))], names=["h", "c", "doc", "pos"])

    return run


def _full_windows(window: int):
    """Windows of full length around parts of the last level that repeat; two hashes, 96 bits."""
    half = levels(window)[-1]

    def run(batches):
        for b in batches:
            raw, off = G.text_buffer(b.column("body"))
            doc, kept = b.column("doc").to_numpy(zero_copy_only=False), _kept(b)
            for i, j in G.chunks(off):
                part, o = raw[off[i] : off[j]], off[i : j + 1] - off[i]
                s, e, first = G.word_spans(part, o)
                values = G.word_values(part, s, e)
                row, at, p0, p1, h = G.anchor_runs(values, first, half, window)
                keep = np.zeros(len(values) + 1, bool)
                for r in range(i, j):
                    keep[kept(r, first[r - i])] = True
                take = keep[at]
                row, p0, p1 = row[take], p0[take], p1[take]
                if not len(row):
                    continue
                n = p1 - p0 + 1
                p = np.repeat(p0 - np.append(0, np.cumsum(n)[:-1]), n) + np.arange(n.sum())
                row = np.repeat(row, n)
                k = G.span_hash(G.prefix(values, G.BASE), p, p + window, G.BASE)
                k2 = (G.span_hash(G.prefix(values * ODD ^ (values >> np.uint64(29)), G.BASE2), p, p + window, G.BASE2) >> np.uint64(32)).astype(np.uint32)
                yield pa.RecordBatch.from_arrays([pa.array(k.view(np.int64)), pa.array(k2.view(np.int32)), pa.array(doc[row + i]), pa.array((p - first[row]).astype(np.int32))], names=["k", "k2", "doc", "pos"])

    return run


def _cut(window: int, carried: bool = False):
    """Cuts the windows that start at ``at``; column ``row`` is handed on if ``carried``."""

    def run(batches):
        for b in batches:
            out: list[tuple] = []
            for doc, body, at, copy in zip(b.column("doc").to_pylist(), b.column("body"), b.column("at"), b.column("copy").to_pylist()):
                data = np.frombuffer(body.as_buffer(), np.uint8)
                s, e, _ = G.word_spans(data, np.array([0, len(data)]))
                gone = np.zeros(len(s) + 1, np.int32)
                if copy and len(s) >= window:
                    gone[0] = 1
                elif at.is_valid:
                    p = at.values.to_numpy()
                    p = p[p + window <= len(s)]
                    np.add.at(gone, p, 1)
                    np.add.at(gone, p + window, -1)
                gone = np.cumsum(gone[:-1]) > 0
                if not gone.any():
                    out.append((doc, len(s), 0, body.as_py()))
                    continue
                nxt = np.append(s[1:], len(data))  # a word goes with the space up to the next one
                text = data.copy()
                drop = np.zeros(len(data) + 1, np.int32)
                np.add.at(drop, s[gone], 1)
                np.add.at(drop, nxt[gone], -1)
                out.append((doc, len(s), int(gone.sum()), text[np.cumsum(drop[:-1]) == 0].tobytes().decode()))
            cols = list(zip(*out)) or [[], [], [], []]
            made = [pa.array(x, t) for x, t in zip(cols, (pa.int64(), pa.int64(), pa.int64(), pa.string()))]
            names = ["doc_id", "n_words", "n_removed", "kept_text"]
            yield pa.RecordBatch.from_arrays([*made, b.column("row")], names=[*names, "row"]) if carried else pa.RecordBatch.from_arrays(made, names=names)

    return run


def repeated_windows(docs: DataFrame, window: int = WINDOW) -> tuple[DataFrame, DataFrame]:
    """((doc, at): starts of windows to remove per document, (doc): whole copies)."""
    own = _docs(docs).where("doc IS NOT NULL")
    copies = written(copies_of(own))
    at, before = None, None
    for length in levels(window):
        left = own if at is None else own.join(at, "doc")
        parts = left.withColumn("c", F.xxhash64("body")).mapInArrow(_level(window, length, before), "h long, c long, doc long, pos int")
        again = parts.groupBy("h").agg(F.min("c").alias("a"), F.max("c").alias("z")).where("a <> z").select("h")
        found = parts.select("h", "doc", "pos").join(again, "h").join(copies, "doc", "left_anti")
        found = written(found.groupBy("doc").agg(F.collect_list("pos").alias("at")))
        if at is not None:
            drop_written(at)
        at, before = found, length
        if at.isEmpty():
            return at, copies
    full = written(own.join(at, "doc").mapInArrow(_full_windows(window), "k long, k2 int, doc long, pos int"))
    first = full.groupBy("k", "k2").agg(F.min("doc").alias("first"), F.max("doc").alias("last")).where("first < last").drop("last")
    out = written(full.join(first, ["k", "k2"]).where("doc > first").groupBy("doc").agg(F.collect_list("pos").alias("at")))
    drop_written(at, full)
    return out, copies


def substring_dedup(docs: DataFrame, window: int = WINDOW) -> DataFrame:
    """doc_id, n_words, n_removed, kept_text per row: words covered by a window of ``window`` words
    that also starts in a document with a smaller doc_id are cut, judged on the input."""
    at, copies = repeated_windows(docs, window)
    return (
        _docs(docs).join(at, "doc", "left").join(copies.withColumn("copy", F.lit(True)), "doc", "left")
        .mapInArrow(_cut(window), "doc_id long, n_words long, n_removed long, kept_text string")
    )
