"""Text bases: every labelled document is scored, magnitude tokens are what is encoded."""

import numpy as np
from pyspark.sql import functions as F

from relmodel import learned
from relmodel.catalog import load
from relmodel.nn.bases import TextBase, magnitude_tokens


def test_text_bases_score_every_labelled_document(spark, sf):
    d = load(spark, sf, ["documents", "labels"])
    words = d["documents"].join(d["labels"], "doc_id").select("doc_id", "lang", "source", F.col("n_chars").cast("double").alias("n_chars"), "text").collect()
    got = learned.base_text_scores(spark, sf).collect()
    assert len(got) == 3 * len(words)
    long = {r.doc_id for r in words if magnitude_tokens(r.asDict() | {"doc_id": None}, {"n_chars": np.zeros(1)}) is None}
    assert long and {r.doc_id for r in got if r.score is None} == long and {r.kind for r in got if r.score is None} == {"magnitude_text"}


def test_magnitude_text_encodes_bins():
    m = TextBase("magnitude_text", edges={"a": np.array([1.0, 2.0])})
    x = m.encode([{"a": 3.0}, {"a": 9.0}, {"a": 0.5}, {"b": "w " * 600}])
    assert (x[0] == x[1]).all() and not (x[0] == x[2]).all() and np.isnan(x[3]).all()


def test_repeated_grams_are_hashed_once(monkeypatch):
    import hashlib

    from relmodel.nn import bases

    made, real = [], hashlib.blake2b
    monkeypatch.setattr(bases.hashlib, "blake2b", lambda *a, **k: made.append(a[0]) or real(*a, **k))
    text = "quire of zanthic quire of " * 50
    for how in ({}, {"grams": "char", "norm": True}, {"seed": 3}):
        made.clear()
        got = bases.hashed_text(text, **how)
        assert made and len(made) == len(set(made))
        want = np.zeros(768)
        words = text.lower().split()
        for g in words + [f"{a} {b}" for a, b in zip(words, words[1:])] if "grams" not in how else [text[i : i + 3] for i in range(len(text) - 2)]:
            h = int.from_bytes(real(g.encode(), digest_size=8, salt=how.get("seed", 0).to_bytes(8, "little")).digest(), "little")
            want[h % 768] += 1 if h >> 63 else -1
        assert np.allclose(got / np.linalg.norm(got), want / np.linalg.norm(want))
    assert not bases.hashed_text("").any()
