"""Operators 2 and 3 against brute force."""

import hashlib
import random
import re

import pytest
from pyspark.sql import functions as F

from relmodel.llm.substring import substring_dedup
from relmodel.llm.suffix import merge_sort, HashedText, suffix_dedup

WORD = re.compile(r"[^\x20\x09-\x0D]+")


def brute_words(docs, window):
    first, words = {}, {}
    for d, t in docs:
        words[d] = WORD.findall(t or "")
        for i in range(len(words[d]) - window + 1):
            k = tuple(words[d][i : i + window])
            first[k] = min(first.get(k, d), d)
    out = {}
    for d, w in words.items():
        gone = set()
        for i in range(len(w) - window + 1):
            if first[tuple(w[i : i + window])] < d:
                gone.update(range(i, i + window))
        out[d] = (len(w), len(gone), " ".join(x for i, x in enumerate(w) if i not in gone))
    return out


def brute_bytes(docs, length):
    first, out = {}, {}
    for d, t in sorted(docs):
        b = (t or "").encode()
        gone = bytearray(len(b))
        for i in range(len(b) - length + 1):
            if (k := b[i : i + length]) in first:
                gone[i : i + length] = b"\1" * length
            else:
                first[k] = 1
        spans = len(re.findall(rb"\x01+", bytes(gone)))
        out[d] = (len(b), sum(gone), spans, bytes(x for x, y in zip(b, gone) if not y))
    return out


def made_docs():
    r = random.Random(3)
    words = ["aé", "b", "cc", "dog", "e,", "fox x", "g", "hill"]
    text = lambda n: r.choice([" ", "\n", "  "]).join(r.choice(words) + str(r.randrange(9)) for _ in range(n))
    shared = [text(r.randrange(8, 40)) for _ in range(6)]
    docs = []
    for d in range(60):
        parts = [text(r.randrange(0, 30)), r.choice(shared), text(r.randrange(0, 12)), r.choice(shared)]
        docs.append((d * 3, " ".join(parts)))
    docs += [(500, docs[3][1]), (501, docs[3][1]), (502, docs[7][1] + " tail"), (503, None), (504, ""), (505, "x " * 300), (506, "x " * 280), (507, " \n\t "), (508, "ab" * 400)]
    return docs


@pytest.fixture(scope="module")
def docs(spark):
    rows = made_docs()
    return rows, spark.createDataFrame(rows, "doc_id long, text string").repartition(5)


@pytest.mark.parametrize("window", [10, 7])
def test_substring_dedup(docs, window):
    rows, df = docs
    got = {r.doc_id: (r.n_words, r.n_removed, " ".join(WORD.findall(r.kept_text))) for r in substring_dedup(df, window).collect()}
    assert got == brute_words(rows, window)


@pytest.mark.parametrize("hot", [2000, 3])
def test_suffix_dedup(docs, hot, monkeypatch):
    import relmodel.llm.suffix as S

    rows, df = docs
    monkeypatch.setattr(S.removed_spans, "__defaults__", (60, 20, hot))
    own = S.removed_spans.__defaults__
    from relmodel.llm._common import text_of

    base = df.select(F.col("doc_id").alias("doc"), text_of("text").alias("body"))
    spans, copies = S.removed_spans(base, 60, 20, hot)
    out = base.join(spans, "doc", "left").join(copies.withColumn("copy", F.lit(True)), "doc", "left").mapInArrow(S._cut(60), "doc_id long, n_bytes long, n_removed long, spans array<struct<a:long,z:long>>, kept binary")
    got = {r.doc_id: (r.n_bytes, r.n_removed, len(r.spans), bytes(r.kept)) for r in out.collect()}
    assert got == brute_bytes(rows, 60)
    assert own


def test_merge_sort_equals_plain_sort():
    import numpy as np

    r = random.Random(5)
    data = np.frombuffer(bytes(r.choice(b"ab") for _ in range(3000)), np.uint8)
    n = 400
    start = np.array([r.randrange(0, 2900) for _ in range(n)])
    size = np.array([r.randrange(0, 90) for _ in range(n)])
    group = np.sort(np.array([r.randrange(0, 7) for _ in range(n)]))
    order = merge_sort(HashedText(data), start, size, group)
    key = lambda i: (group[i], data[start[i] : start[i] + size[i]].tobytes())
    assert [key(i) for i in order] == sorted(map(key, range(n)))


def test_odd_tables(spark):
    empty = spark.createDataFrame([], "doc_id long, text string, h string")
    assert substring_dedup(empty).count() == 0 and suffix_dedup(empty).count() == 0
    rows = [(1, "w " * 80, "a"), (1, "w " * 80, "b"), (2, "w " * 80, None), (None, "w " * 80, "z"), (3, None, "q")]
    df = spark.createDataFrame(rows, "doc_id long, text string, pos string")
    got = sorted((r.doc_id or -1, r.n_removed) for r in substring_dedup(df).collect())
    assert got == [(-1, 0), (1, 0), (1, 0), (2, 80), (3, 0)]
    cut = {r.doc_id: r.n_removed for r in suffix_dedup(df).collect()}
    assert cut[2] == 160 and cut[None] == 0 and cut[1] == 158
