"""Operators 1 and 4 to 10 on small fixtures and by brute force."""

import hashlib
import os
import random
import re

import duckdb
import numpy as np
import pytest
import xxhash
from pyspark.sql import functions as F

from relmodel.llm import chat, classifier, decontaminate, mixing, quality, queries, simhash, tokencount, urls

WORD = re.compile(r"[^\x20\x09-\x0D]+")


def plain(df):
    cols = sorted(df.columns)
    show = lambda v: "null" if v is None or v != v else repr(float(v)) if isinstance(v, (int, float)) else str(v)
    return cols, sorted(tuple(map(show, r)) for r in df[cols].astype(object).itertuples(index=False))


@pytest.mark.parametrize("name", sorted(queries.oracle_sql()))
def test_sql_twins(spark, sf, name):
    c = duckdb.connect()
    c.execute(f"CREATE VIEW documents AS SELECT * FROM read_parquet('{sf}/documents.parquet')")
    assert plain(queries.queries()[name](spark, sf).toPandas()) == plain(c.sql(queries.oracle_sql()[name]).df())


ODD = [(1, "a b c", "s"), (1, "a b c", "s"), (2, None, None), (3, "", "s"), (None, "x y z", None), (4, "w " * 5000, "t"), (5, " \n\t ", "s")]


@pytest.fixture(scope="module")
def odd(spark):
    return spark.createDataFrame(ODD, "doc_id long, text string, source string").withColumn("size", F.lit("clash")).withColumn("fp", F.lit(1)).withColumn("h", F.lit("x"))


@pytest.fixture(scope="module")
def empty(spark, odd):
    return spark.createDataFrame([], odd.schema)


# ---- 1 ------------------------------------------------------------------------------------------


def test_mixing_targets_by_brute_force(spark):
    r = random.Random(1)
    rows = [(i, " ".join("w" for _ in range(r.randrange(0, 60))), r.choice([None, "a", "b", "c", "é", "d"] + ["hot"] * 8)) for i in range(600)]
    got = mixing.mix(spark.createDataFrame(rows, "doc_id long, text string, source string")).collect()
    size = {}
    for _, t, s in rows:
        size[s] = size.get(s, 0) + len(t.split())
    order = sorted((s for s in size if s is not None), key=lambda s: s.encode()) + [None]
    weight = {s: (5, 2, 1)[i % 3] for i, s in enumerate(order)}
    total, capped = 1.5 * sum(size.values()), set()
    while True:
        rest, load = total - sum(2 * size[s] for s in capped), sum(weight[s] for s in order if s not in capped)
        target = {s: 2.0 * size[s] if s in capped else weight[s] * rest / load for s in order}
        over = {s for s in order if target[s] > 2 * size[s]} - capped
        if not over:
            break
        capped |= over
    taken = {}
    for x in got:
        assert x.size == len(rows[x.doc_id][1].split()) and abs(x.target - target[x.source]) < 1e-6 and x.taken in (0, x.size, 2 * x.size)
        taken[x.source] = taken.get(x.source, 0) + x.taken
    assert all(abs(taken[s] - target[s]) <= 60 for s in order) and len(got) == 600
    again = {(x.doc_id, x.taken) for x in got}
    assert again == {(x.doc_id, x.taken) for x in mixing.mix(spark.createDataFrame(rows[::-1], "doc_id long, text string, source string").repartition(7)).collect()}


def test_mixing_odd(odd, empty):
    got = mixing.mix(odd).collect()
    assert len(got) == len(ODD) and all(x.taken <= 2 * x.size for x in got) and mixing.mix(empty).count() == 0


# ---- 4 ------------------------------------------------------------------------------------------


def best_count(text, scores):
    best = [(0.0, 0)]
    for i in range(1, len(text) + 1):
        options = [(best[j][0] + scores[text[j:i]], -(best[j][1] + 1)) for j in range(i) if text[j:i] in scores]
        if text[i - 1] not in scores:
            n = len(text[i - 1].encode())
            options.append((best[i - 1][0] + tokencount.BYTE_SCORE * n, -(best[i - 1][1] + n)))
        s, c = max(options)
        best.append((s, -c))
    return best[-1][1]


def test_token_counts(spark, odd, empty):
    scores = {"▁": -3.0, "a": -2.5, "b": -2.7, "ab": -3.1, "ba": -4.0, "▁a": -2.2, "aba": -3.9, "c": -5.0}
    r = random.Random(2)
    rows = [(i, " ".join("".join(r.choice("abcé") for _ in range(r.randrange(1, 9))) for _ in range(r.randrange(0, 30)))) for i in range(80)]
    got = {x.doc_id: (x.n_pretokens, x.n_tokens) for x in tokencount.token_counts(spark.createDataFrame(rows, "doc_id long, text string"), scores).collect()}
    assert got == {i: (len(t.split()), sum(best_count("▁" + w, scores) for w in t.split())) for i, t in rows}
    assert sorted(x.n_pretokens for x in tokencount.token_counts(odd, scores).collect()) == [0, 0, 0, 3, 3, 3, 5000]
    assert tokencount.token_counts(empty, scores).count() == 0


def test_trie_scores_prefixes_once():
    t = tokencount.TrieCounter({"a": -1.0, "b": -1.0})
    for w in sorted(["abab", "abba", "abb", "abab"]):
        t.tokens(w)
    assert t.steps == 4 + 1 + 1  # abab, then b after ab, then a after abb


def test_vocabulary_file():
    if os.path.exists(tokencount.VOCABULARY):
        s = tokencount.piece_scores()
        assert len(s) > 30_000 and all(v < 0 for v in list(s.values())[:100])


# ---- 5 ------------------------------------------------------------------------------------------


def test_escape_round_trip():
    r = random.Random(3)
    bits = list(chat.CONTROLS) + ["\\", "<", "[", "s>", "/s>", "a", "\n", "<\\/s>", "é", "|>"]
    for _ in range(3000):
        t = "".join(r.choice(bits) for _ in range(r.randrange(0, 8)))
        e = chat.escape(t)
        assert chat.unescape(e) == t and not any(c in e for c in chat.CONTROLS)
        text, spans = chat.render([(t, "x"), ("assistant", t), ("user", t)])
        assert chat.parse(text) == [(t, "x"), ("assistant", t), ("user", t)]
        assert "".join(chat.unescape(text[a:z]) for a, z in spans) == t * (2 if t == "assistant" else 1) or t == "assistant"


def test_conversations(spark):
    rows = [(1, 2, "assistant", "two"), (1, 1, "user", None), (1, 3, "user", "</s>"), (2, 1, "assistant", "é"), (2, 1, "assistant", "é"), (None, 1, "user", "n"), (3, 5, None, "r")]
    got = {x.conv_id: x for x in chat.format_conversations(spark.createDataFrame(rows, "conv_id long, turn long, role string, text string").withColumn("node", F.lit(1))).collect()}
    assert chat.parse(got[1].formatted) == [("user", ""), ("assistant", "two"), ("user", "</s>")]
    assert chat.parse(got[2].formatted) == [("assistant", "é")] * 2 and len(got[2].loss_spans) == 2
    assert chat.parse(got[None].formatted) == [("user", "n")] and chat.parse(got[3].formatted) == [("", "r")]
    assert chat.format_conversations(spark.createDataFrame([], "conv_id long, turn long, role string, text string")).count() == 0


def test_reply_trees(spark):
    nodes = [(1, 10, None, "user", "q", 0.0), (1, 11, 10, "assistant", "bad", 0.1), (1, 12, 10, "assistant", "good", 0.9), (1, 13, 12, "user", "more", 0.2), (1, 14, 12, "user", "less", 0.1), (2, 20, None, "user", "alone", None)]
    df = spark.createDataFrame(nodes, "tree long, node long, parent long, role string, text string, score double")
    best = {x.tree: chat.parse(x.formatted) for x in chat.format_trees(df).collect()}
    assert [t for _, t in best[1]] == ["q", "good", "more"] and best[2] == [("user", "alone")]
    every = chat.format_trees(df, None).collect()
    assert sorted(x.leaf for x in every) == [11, 13, 14, 20]
    chain = spark.createDataFrame([(1, i, i - 1 if i else None) for i in range(70)], "tree long, node long, parent long")
    assert chat.paths(chain.select("node", "parent")).count() == 70
    with pytest.raises(ValueError):
        ring = spark.createDataFrame([(1, 2), (2, 3), (3, 1), (4, 3)], "node long, parent long")
        chat.paths(ring)


def test_op5_digests(spark, sf):
    out = {x.conv_id: x for x in queries.op5_chat_format(spark, sf).collect()}
    said = "</s>[INST] ok [/INST]"
    assert out[-1].turns_sha256 == hashlib.sha256(f"user\n{said}\nassistant\n{said}\n".encode()).hexdigest() and out[-1].loss_chars == len(said)
    want = {}
    for x in spark.read.parquet(f"{sf}/conversations.parquet").orderBy("conv_id", "turn").collect():
        want.setdefault(x.conv_id, []).append((x.role, x.text or ""))
    for k, turns in want.items():
        loss = "".join(t for r, t in turns if r == "assistant")
        assert out[k].n_turns == len(turns) and out[k].turns_sha256 == hashlib.sha256("".join(f"{r}\n{t}\n" for r, t in turns).encode()).hexdigest()
        assert out[k].loss_chars == len(loss) and out[k].loss_sha256 == hashlib.sha256(loss.encode()).hexdigest()


# ---- 6 ------------------------------------------------------------------------------------------


def test_quality_features(spark, odd, empty):
    r = random.Random(4)
    rows = [(i, "\n".join(" ".join(r.choice(["a", "b", "c", "dé#", "&&x", "THE!!"]) for _ in range(r.randrange(0, 9))) for _ in range(r.randrange(0, 6)))) for i in range(120)]
    got = {x.doc_id: x for x in quality.quality_rules(spark.createDataFrame(rows, "doc_id long, text string")).collect()}
    for i, t in rows:
        w = WORD.findall(t)
        grams = [tuple(w[k : k + 3]) for k in range(len(w) - 2)]
        covered = {k + j for k, g in enumerate(grams) if grams.count(g) > 1 for j in range(3)}
        lines = [x for x in t.split("\n") if WORD.search(x)]
        assert (got[i].n_words, got[i].word_chars, got[i].n_symbols, got[i].n_dup_lines, got[i].n_repeat_words) == (len(w), sum(map(len, w)), sum(t.count(c) for c in quality.SYMBOLS), len(lines) - len(set(lines)), len(covered))
        assert got[i].base_failed == (len(w) < 50 or 100 * len(covered) > 50 * len(w))
    assert quality.quality_rules(odd).count() == len(ODD) and quality.quality_rules(empty).count() == 0


def test_quality_separates(spark):
    sf = "/root/testdata/sf0.01"
    marks = spark.read.parquet(f"{sf}/labels.parquet").select("doc_id", F.col("quality").alias("label"))
    got = quality.quality_rules(spark.read.parquet(f"{sf}/documents.parquet")).join(marks, "doc_id").where("NOT base_failed")
    n = {(x.label, x.kept): x.n for x in got.groupBy("label", "kept").agg(F.count("*").alias("n")).collect()}
    assert n.get((1, False), 0) == 0 and n.get((0, True), 0) <= 0.1 * n[0, False]


# ---- 7 ------------------------------------------------------------------------------------------


def brute_components(rows, shingle, radius):
    fp = {}
    for d, t in rows:
        w = bytes((t or "").encode()).lower().split()
        h = [xxhash.xxh64_intdigest(b" ".join(w[i : i + shingle]), 42) for i in range(max(1, len(w) - shingle + 1))] if w else []
        fp[d] = sum(1 << b for b in range(64) if 2 * sum(x >> b & 1 for x in h) > len(h))
    root = {d: d for d in fp}

    def find(x):
        while root[x] != x:
            x = root[x]
        return x

    ids = sorted(fp)
    for i, a in enumerate(ids):
        for b in ids[:i]:
            if bin(fp[a] ^ fp[b]).count("1") <= radius:
                x, y = find(a), find(b)
                root[max(x, y)] = min(x, y)
    return {d: (format(fp[d], "016x"), find(d)) for d in ids}


def near_docs(n, seed):
    r = random.Random(seed)
    base = [[f"w{r.randrange(10**6)}" for _ in range(120)] for _ in range(4)]
    rows = []
    for i in range(n):
        w = list(r.choice(base)) if r.random() < 0.8 else [f"v{r.randrange(10**6)}" for _ in range(60)]
        for _ in range(r.randrange(0, 3)):
            w[r.randrange(len(w))] = f"x{r.randrange(10**6)}"
        rows.append((i + 7, " ".join(w)))
    return rows + [(3, ""), (4, None), (5, "one"), (6, "ONE")]


@pytest.mark.parametrize("crowd,many", [(32, 1 << 18), (3, 1 << 18), (3, 2)])
def test_simhash_components(spark, monkeypatch, crowd, many):
    monkeypatch.setattr(simhash, "CROWD", crowd)
    monkeypatch.setattr(simhash, "MANY", many)
    monkeypatch.setattr(simhash, "BLOCK", 16)
    rows = near_docs(90, crowd)
    got = {x.doc_id: (x.fingerprint, x.component_id) for x in simhash.simhash_dedup(spark.createDataFrame(rows, "doc_id long, text string").repartition(3)).collect()}
    assert got == brute_components(rows, 4, 4)


def test_simhash_thresholds():
    d = [np.array([10, 5, 85.0]), np.array([1.0, 9, 90]), np.array([50.0, 30, 20])]
    t = simhash.thresholds(d, 10, 0, probe=0.0)
    assert sum(t) == 0 and t[2] == -1  # the least selective part is not used
    assert sum(simhash.thresholds(d, 10, 1)) == 1


@pytest.mark.parametrize("n", [200, 235_000, 600_000, 3_034_159, 15_000_000, 200_000_000])
def test_simhash_average_places_are_no_crowds(n, monkeypatch):
    """Codes that are spread evenly are paired place by place at any size, not as one crowd."""
    seen = {}
    monkeypatch.setattr(simhash, "correlations", lambda codes, words64: np.eye(64))
    monkeypatch.setattr(simhash, "distances", lambda codes, parts: [np.array([1.0, 1, 1]) for _ in parts])
    monkeypatch.setattr(simhash, "links", lambda codes, radius, words64, parts, t, accept=None, crowd=simhash.CROWD: seen.update(parts=parts, t=t, crowd=crowd))
    simhash.code_links(type("Codes", (), {"count": lambda self: n})(), 4)
    least = min(len(p) for p in seen["parts"])
    assert sum(map(len, seen["parts"])) == 64 and sum(seen["t"]) == 4 - len(seen["parts"]) + 1
    assert n / 2**least * 4 <= seen["crowd"]


def test_simhash_odd(odd, empty):
    got = simhash.simhash_dedup(odd).collect()
    assert len(got) == len(ODD) and {x.component_id for x in got if x.doc_id is None} == {None}
    assert {x.component_id for x in got if x.doc_id in (2, 3, 5)} == {2} and simhash.simhash_dedup(empty).count() == 0


def test_wide_fingerprints_find_similar(spark):
    r = random.Random(8)
    w = [f"w{r.randrange(10**6)}" for _ in range(300)]
    close = list(w)
    close[10] = "other"
    rows = [(1, " ".join(w)), (2, " ".join(close)), (3, " ".join(f"z{r.randrange(10**6)}" for _ in range(300)))]
    own = spark.createDataFrame(rows, "doc long, body string")
    assert {x.doc: x.component for x in simhash.similar_components(own).collect()} == {1: 1, 2: 1, 3: 3}


# ---- 8 ------------------------------------------------------------------------------------------


def test_url_rules(spark):
    rows = [(1, "http://a.org/x"), (2, "https://EXAMPLE.org/es/1"), (3, "http://www.example.org/en/12?q"), (4, "http://b.com/de/"), (5, "http://b.com"), (6, None), (7, "nothing"), (8, "http://notorg/x"), (9, "http://org/#f"), (1, "http://a.org/x"), (10, "x://h.com/fr/a?b#c")]
    got = urls.url_filter(spark.createDataFrame(rows, "page_id long, url string").withColumn("host", F.lit("z"))).collect()
    m = {x.page_id: (x.host, x.path, x.rule, x.verdict) for x in got}
    assert len(got) == len(rows)
    assert m[1] == ("a.org", "/x", "org/", "allow") and m[2] == ("example.org", "/es/1", "example.org/es/", "block") and m[3] == ("www.example.org", "/en/12", "example.org/en/1", "block")
    assert m[4] == ("b.com", "/de/", "com/de/", "block") and m[5][:3] == ("b.com", "", None) and m[6] == ("", "", None, "allow") and m[7] == ("", "", None, "allow")
    assert m[8][2] is None and m[9][:3] == ("org", "/", "org/") and m[10][:3] == ("h.com", "/fr/a", "com/fr/")
    assert urls.url_filter(spark.createDataFrame([], "page_id long, url string")).count() == 0


def test_mined_rules_equal_counts(spark):
    r = random.Random(5)
    rows = []
    for i in range(300):
        tags = [t for t in ("a", "b", "c") if r.random() < 0.5]
        rows.append((tags or ["d"], "block" if {"a", "b"} <= set(tags) else r.choice(["allow", "allow", "block"])))
    got = urls.mine(spark.createDataFrame(rows, "items array<string>, verdict string"), 0.05, 0.6).collect()
    assert got
    for x in got:
        have = [v for items, v in rows if set(x.antecedent) <= set(items)]
        assert abs(have.count(x.verdict) / len(have) - x.confidence) < 1e-9 and x.key in x.antecedent


# ---- 9 ------------------------------------------------------------------------------------------


def test_decontamination(spark, odd):
    r = random.Random(6)
    word = lambda: "".join(r.choice("abcdefgh") for _ in range(6))
    items = [(i, " ".join(word() for _ in range(30))) for i in range(20)] + [(20, "tiny item here"), (21, None), (22, "")]
    filler = lambda n: " ".join(word() for _ in range(n))
    docs = [(i, filler(200)) for i in range(40)]
    docs += [(100, f"{filler(50)} {items[3][1].upper()}, {filler(9)}"), (102, f"x TINY, item; here y {filler(30)}"), (103, None)]
    sub = items[5][1].split()
    sub[8] = sub[19] = "changed"
    docs.append((101, filler(20) + " " + " ".join(sub)))
    got = {(x.doc_id, x.item_id) for x in decontaminate.matches(spark.createDataFrame(docs, "doc_id long, text string"), spark.createDataFrame(items, "item_id long, text string")).collect()}
    assert got == {(100, 3), (101, 5), (102, 20)}
    assert decontaminate.matches(odd, spark.createDataFrame([], "item_id long, text string")).count() == 0


# ---- 10 -----------------------------------------------------------------------------------------


def test_attention_gradients():
    r = np.random.default_rng(0)
    p = classifier.start_weights(1)
    x, base, y = r.random((9, classifier.WIDTH)), np.array([0, 2, 3, 9]), np.array([1.0, 0, 1])
    g = classifier.gradients(p, x, base, y)

    def loss(q):
        z = classifier.forward(q, x, base)["y"]
        return -np.mean(y * np.log(z) + (1 - y) * np.log(1 - z))

    for k in p:
        i = tuple(0 for _ in p[k].shape)
        a, b = {**p, k: p[k].copy()}, {**p, k: p[k].copy()}
        a[k][i] += 1e-5
        b[k][i] -= 1e-5
        assert abs((loss(a) - loss(b)) / 2e-5 - g[k][i]) < 1e-6


def test_classifier_held_out(spark, odd, empty):
    sf = "/root/testdata/sf0.01"
    docs, labels = spark.read.parquet(f"{sf}/documents.parquet"), spark.read.parquet(f"{sf}/labels.parquet")
    out = classifier.quality_classifier(docs, labels)
    import zlib

    rows = out.join(labels.select("doc_id", "quality"), "doc_id").where("held_out").collect()
    assert all(zlib.crc32(str(x.doc_id).encode()) % 5 == 0 for x in rows)
    good, bad = [x.score for x in rows if x.quality == 1], [x.score for x in rows if x.quality == 0]
    assert np.mean([g > b for g in good for b in bad]) > 0.95 and np.mean([x.predicted == x.quality for x in rows]) > 0.93
    assert classifier.quality_classifier(odd, labels.limit(0)).count() == len(ODD) and classifier.quality_classifier(empty, labels).count() == 0
