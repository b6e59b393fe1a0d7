"""The corpus pipeline against a brute-force version on planted documents."""

import random

import corpus_pipeline as P
from relmodel.llm import mixing
from tests.llm.test_substrings import WORD, brute_words

R = random.Random(11)


def prose(n, tag):
    words = [f"{tag}{R.randrange(10**6)}x" for _ in range(n)]
    return "\n".join(" ".join(words[i : i + 12]) + "." for i in range(0, n, 12))


def planted():
    clean = {i: prose(R.randrange(90, 200), f"c{i}") for i in range(60)}
    rows = dict(clean)
    rows[100], rows[101] = clean[3], clean[3]  # exact copies
    near = clean[7].split(" ")
    near[20] = "changed"
    rows[102] = " ".join(near)
    passage = " ".join(f"p{i}q" for i in range(60))
    for i in (103, 104, 105):  # passages over 50 words that repeat
        rows[i] = prose(90, f"d{i}") + "\n" + passage + "\n" + prose(60, f"e{i}")
    item = " ".join(f"bench{i}mark" for i in range(30))
    rows[106] = prose(80, "f") + " " + item
    rows[107] = "spam " * 300
    rows[108] = " ".join(f"w{i}$$$" for i in range(120))
    rows[109] = "too short"
    return rows, clean, passage, item


def test_pipeline(spark, tmp_path):
    rows, clean, passage, item = planted()
    rows |= {200 + i: " ".join(f"bad{i}_{j}%%%" for j in range(100)) for i in range(6)}
    frame = [(d, t, "en", f"s{d % 3}", len(t)) for d, t in rows.items()]
    schema = "doc_id long, text string, lang string, source string, n_chars long"
    spark.createDataFrame(frame, schema).repartition(3).write.parquet(f"{tmp_path}/documents.parquet")
    spark.createDataFrame([(0, item)], "item_id long, text string").write.parquet(f"{tmp_path}/benchmark.parquet")
    docs, seen = spark.read.parquet(f"{tmp_path}/documents.parquet"), []
    for name, stage in P.STAGES:
        path = f"{tmp_path}/{len(seen)}"
        stage(spark, docs, str(tmp_path)).write.parquet(path)
        docs = spark.read.parquet(path)
        if len(seen) < 4:
            assert docs.columns == schema.replace(" long", "").replace(" string", "").split(", ")
        seen.append({r.doc_id: r.text for r in docs.collect()})
    good, near, cut, fair, mixed = seen
    assert set(good) == set(clean) | set(range(100, 107))
    assert set(near) == set(good) - {100, 101, 102}
    want = brute_words(sorted(near.items()), 50)
    assert {d: " ".join(WORD.findall(t)) for d, t in cut.items()} == {d: k for d, (_, _, k) in want.items() if k}
    assert passage in cut[103] and passage not in cut[104] and passage not in cut[105] and all(cut[d] == t for d, t in clean.items())
    assert set(fair) == set(cut) - {106}
    taken = {r.doc_id for r in mixing.mix(spark.createDataFrame([(d, t, f"s{d % 3}") for d, t in fair.items()], "doc_id long, text string, source string")).where("taken > 0").collect()}
    assert set(mixed) == taken
    again = {r.doc_id: r.text for r in P.run(spark, str(tmp_path)).collect()}
    assert again == mixed


def test_empty_pipeline(spark, tmp_path):
    schema = "doc_id long, text string, lang string, source string, n_chars long"
    spark.createDataFrame([], schema).write.parquet(f"{tmp_path}/documents.parquet")
    spark.createDataFrame([], "item_id long, text string").write.parquet(f"{tmp_path}/benchmark.parquet")
    assert P.run(spark, str(tmp_path)).count() == 0
