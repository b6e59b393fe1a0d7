"""Near copies of the pipeline against the exact Jaccard of their five-word shingles."""

import random
from itertools import combinations

import corpus_pipeline as P
from relmodel.llm import similar, simhash


def shingles(text):
    w = text.lower().split()
    return {tuple(w[i : i + 5]) for i in range(len(w) - 4)}


def jaccard(a, b):
    return len(a & b) / len(a | b)


def planted(r):
    """Pairs (doc, doc + 1000) whose similarity falls between 0.75 and 0.85."""
    rows, boiler = {}, " ".join(f"boiler{i}" for i in range(30))
    while len(rows) < 240:
        n, d = r.choice([55, 100, 300]), len(rows)
        words = [f"d{d}w{r.randrange(10**6)}" for _ in range(n)]
        other = list(words)
        for _ in range(r.randrange(1, 9) * n // 100 + 1):
            other[r.randrange(n)] = f"x{r.randrange(10**6)}"
        j = jaccard(shingles(" ".join(words)), shingles(" ".join(other)))
        if 0.75 <= j <= 0.85:
            rows[d], rows[d + 1000] = " ".join(words), " ".join(other)
    for i in range(50):  # a shared passage alone is no near copy
        rows[5000 + i] = boiler + " " + " ".join(f"own{i}_{j}" for j in range(40))
    base = [f"crowd{i}" for i in range(200)]
    for i in range(60):  # more near copies than a place may hold, of different similarity
        c = list(base)
        for _ in range(r.randrange(1, 7)):
            c[r.randrange(200)] = f"c{r.randrange(10**6)}"
        rows[7000 + i] = " ".join(c)
    return rows


def brute(rows):
    sets = {d: shingles(t) for d, t in rows.items()}
    lo = {d: d for d in rows}

    def root(x):
        while lo[x] != x:
            x = lo[x]
        return x

    for a, b in combinations(sorted(rows), 2):
        if sets[a] & sets[b] and len(sets[a] & sets[b]) * 5 >= 4 * len(sets[a] | sets[b]):
            u, v = root(a), root(b)
            lo[max(u, v)] = min(u, v)
    return {d: root(d) for d in rows}


def test_pairs_around_the_bound(spark):
    rows = planted(random.Random(5))
    own = spark.createDataFrame(list(rows.items()), "doc long, body string")
    assert {x.doc: x.component for x in simhash.similar_components(own).collect()} == brute(rows)


def test_blocks_of_crowds(spark, monkeypatch):
    monkeypatch.setattr(similar, "CROWD", 1)
    monkeypatch.setattr(similar, "BLOCK", 50)
    rows = planted(random.Random(6))
    own = spark.createDataFrame(list(rows.items()), "doc long, body string")
    assert {x.doc: x.component for x in simhash.similar_components(own).collect()} == brute(rows)


def test_shared_ids_are_told_apart(spark):
    text = {x: " ".join(f"{x}{i}" for i in range(60)) for x in "abc"}
    rows = [(1, text["a"]), (1, text["b"]), (1, text["b"]), (2, text["a"]), (3, text["c"]), (None, text["a"])]
    docs = spark.createDataFrame(rows, "doc_id long, text string")
    got = sorted(((r.doc_id, r.text) for r in P.near_dedup_stage(spark, docs, "").collect()), key=str)
    assert got == sorted([(1, text["a"]), (1, text["b"]), (3, text["c"]), (None, text["a"])], key=str)


def test_links_of_wide_fingerprints_lose_no_pair_within_the_bound(spark):
    """All differing bits in the first word: a sieve on that word alone would drop the pair."""
    rows = [(1, [0] * 10), (2, [(1 << 60) - 1 - (1 << 16) + 1] + [0] * 9)]
    codes = spark.createDataFrame(rows, "node long, fp array<long>")
    parts = [list(range(i * 16, i * 16 + 16)) for i in range(40)]
    assert simhash.links(codes, 39, 10, parts, [0] * 40, accept=96).collect() == [(1, 2)]


def test_a_shared_passage_makes_no_place(spark, monkeypatch):
    """Texts that meet only at a crowded passage cannot be similar and are not compared as whole sets."""
    import numpy as np

    r, seen, own = random.Random(9), [], similar._blocks
    monkeypatch.setattr(similar, "frequent", lambda docs, shingle: (np.zeros(0, np.uint64), np.zeros(0, np.uint64)))
    monkeypatch.setattr(similar, "_blocks", lambda crowd, share: (seen.append(crowd.count()), own(crowd, share))[1])
    rows = {i: " ".join([f"line{j}" for j in range(30)] + [f"own{i}_{j}" for j in range(200)]) for i in range(60)}
    base = [f"crowd{i}" for i in range(200)]
    for i in range(40):
        c = list(base)
        for _ in range(r.randrange(1, 7)):
            c[r.randrange(200)] = f"c{r.randrange(10**6)}"
        rows[100 + i] = " ".join(c)
    got = simhash.similar_components(spark.createDataFrame(list(rows.items()), "doc long, body string"))
    assert {x.doc: x.component for x in got.collect()} == brute(rows)
    assert seen and seen[0] <= 40
