"""Pipeline stages on rows that share a doc_id or have none."""

import corpus_pipeline as P

SCHEMA = "doc_id long, text string, source string, n_chars long"


def words(tag, n=60):
    return " ".join(f"{tag}{i}" for i in range(n))


def frame(spark, rows):
    return spark.createDataFrame([(d, t, s, len(t)) for d, t, s in rows], SCHEMA)


def test_substring_stage_cuts_the_copy_only(spark):
    copy, other, late = words("a"), words("b", 70), words("b", 70) + " " + words("z")
    docs = frame(spark, [(1, copy, "s"), (2, copy, "s"), (2, other, "s"), (3, late, "s"), (None, copy, "s")])
    got = sorted(((r.doc_id, r.text) for r in P.substring_stage(spark, docs, "").collect()), key=str)
    assert got == sorted([(1, copy), (2, other), (3, words("z")), (None, copy)], key=str)


def test_decontamination_stage_judges_texts(spark, tmp_path):
    item = words("bench", 30)
    spark.createDataFrame([(0, item)], "item_id long, text string").write.parquet(f"{tmp_path}/benchmark.parquet")
    docs = frame(spark, [(1, words("a") + " " + item, "s"), (1, words("b"), "s"), (None, words("c") + " " + item, "s"), (None, words("d"), "s")])
    got = sorted(((r.doc_id, r.text) for r in P.decontamination_stage(spark, docs, str(tmp_path)).collect()), key=str)
    assert got == sorted([(1, words("b")), (None, words("d"))], key=str)


def test_mixing_stage_gives_each_row_its_own_verdict(spark):
    from relmodel.llm import mixing

    rows = [(None, words(f"n{i}", 20 + i), "s0") for i in range(12)] + [(None, "", "s0")] * 2 + [(None, words("e"), "s1")] * 4
    rows += [(7, words("x"), "s2"), (7, words("y", 90), "s2"), (8, words("z"), "s1")]
    docs = frame(spark, rows)
    want = sorted((r.source, r.size, r.times, r.v) for r in mixing.mix(docs).where("times > 0").collect())
    got = P.mixing_stage(spark, docs, "")
    assert got.columns == docs.columns + ["mix_times", "mix_time"]
    assert sorted((r.source, len(r.text.split()), r.mix_times, r.mix_time) for r in got.collect()) == want


def test_columns_of_any_name_come_back(spark, tmp_path):
    """Names that the stages use inside are handed through with their values, at every stage."""
    from pyspark.sql import functions as F

    spark.createDataFrame([(0, words("bench", 30))], "item_id long, text string").write.parquet(f"{tmp_path}/benchmark.parquet")
    texts = {d: " ".join(f"w{d}x{i}" for i in range(80)) for d in range(12)}
    names = ["_body", "doc", "key", "body", "_doc", "_source", "_nr", "h", "v", "row", "rank", "k", "times"]
    base = frame(spark, [(d, t, "s") for d, t in texts.items()] + [(0, texts[0], "s")])
    docs = base.select("*", *(F.concat(F.lit(n), F.col("doc_id").cast("string")).alias(n) for n in names))
    for name, stage in P.STAGES:
        out = stage(spark, docs, str(tmp_path))
        assert out.columns[: len(docs.columns)] == docs.columns, name
        rows = out.collect()
        assert rows and all(r[n] == f"{n}{r.doc_id}" for r in rows for n in names), name


def test_fewer_parts_give_the_same_links(spark):
    import random

    from relmodel.llm import simhash
    from relmodel.llm._common import components

    r = random.Random(12)
    base = [r.getrandbits(63) for _ in range(6)]
    codes = {x ^ sum(1 << b for b in r.sample(range(63), r.randrange(0, 5))) for x in base for _ in range(20)}
    df = spark.createDataFrame([(i, [c]) for i, c in enumerate(sorted(codes))], "node long, fp array<long>")
    got = [sorted(map(tuple, components(simhash.code_links(df, 4, m)).collect())) for m in (3, 4)]
    assert got[0] == got[1] and got[0]
