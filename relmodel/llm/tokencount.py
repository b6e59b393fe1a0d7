"""Operator 4: token counts by a unigram model, scored along a trie of pre-tokens.

A task takes the distinct pre-tokens of its batch in sorted order, which is the depth-first order of
their trie, and keeps the forward scores of the current path: each prefix is scored once however
many pre-tokens share it. Counts at terminals are kept for later batches, up to ``KEPT`` of them.

Pre-tokens are runs of non-space characters with a mark in front. The best segmentation has the
greatest sum of piece scores (then the fewest pieces); a character without a piece costs one byte
piece for each of its UTF-8 bytes. The scores are those of the vocabulary's order, Zipf-like: a piece
of rank r scores -ln(r + 2); any {piece: score} table can be given instead.

Null text is empty: no tokens. Repeated rows are counted alike; other columns are ignored.
"""

from __future__ import annotations

import math

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from relmodel.llm import _grams as G
from relmodel.llm._common import text_of

MARK = "▁"
VOCABULARY = "/opt/tokenizers/piece_bpe_32k.model"
KEPT, BYTE_SCORE = 400_000, -12.0


def piece_scores(path: str = VOCABULARY) -> dict[str, float]:
    """Pieces of a vocabulary file (bounded: tens of thousands), read on the driver alone."""
    import sentencepiece

    model = sentencepiece.SentencePieceProcessor(model_file=path)
    names = [model.id_to_piece(i) for i in range(model.get_piece_size()) if not (model.is_control(i) or model.is_unknown(i) or model.is_byte(i))]
    return {p: -math.log(r + 2) for r, p in enumerate(names)}


class TrieCounter:
    """Forward scores along the trie path of the last pre-token."""

    def __init__(self, scores: dict[str, float]):
        self.scores = scores
        self.longest = max(map(len, scores), default=1)
        self.path, self.best, self.count = "", [0.0], [0]
        self.steps = 0

    def tokens(self, text: str) -> int:
        old, n = self.path, 0
        while n < len(old) and n < len(text) and old[n] == text[n]:
            n += 1
        best, count, scores, longest = self.best, self.count, self.scores, self.longest
        del best[n + 1 :], count[n + 1 :]
        for i in range(n + 1, len(text) + 1):
            top, few = -math.inf, 0
            for j in range(max(0, i - longest), i):
                s = scores.get(text[j:i])
                if s is not None:
                    s += best[j]
                    if s > top or (s == top and count[j] + 1 < few):
                        top, few = s, count[j] + 1
            if text[i - 1] not in scores:
                size = len(text[i - 1].encode("utf-8", "surrogatepass"))
                s = best[i - 1] + BYTE_SCORE * size
                if s > top:
                    top, few = s, count[i - 1] + size
            best.append(top)
            count.append(few)
            self.steps += 1
        self.path = text
        return count[-1]


def token_counts(docs: DataFrame, scores: dict[str, float] | None = None, vocabulary: str = VOCABULARY) -> DataFrame:
    """doc_id, n_pretokens, n_tokens per row."""
    shared = docs.sparkSession.sparkContext.broadcast(scores or piece_scores(vocabulary))

    def run(batches):
        trie, kept = TrieCounter(shared.value), {}
        for b in batches:
            raw, off = G.text_buffer(b.column("body"))
            pre, tok = [], []
            for i, j in G.chunks(off, 1 << 22):
                rows = [raw[off[r] : off[r + 1]].tobytes().split() for r in range(i, j)]
                if len(kept) > KEPT:
                    kept.clear()
                new = {w for row in rows for w in row if w not in kept}
                for text, w in sorted((MARK + w.decode("utf-8", "replace"), w) for w in new):
                    kept[w] = trie.tokens(text)
                pre += [len(row) for row in rows]
                tok += [sum(map(kept.__getitem__, row)) for row in rows]
            yield pa.RecordBatch.from_arrays([b.column("doc"), pa.array(pre, pa.int64()), pa.array(tok, pa.int64())], names=["doc_id", "n_pretokens", "n_tokens"])

    own = docs.select(F.col("doc_id").cast("long").alias("doc"), text_of("text").alias("body"))
    return own.mapInArrow(run, "doc_id long, n_pretokens long, n_tokens long")
