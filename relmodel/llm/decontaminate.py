"""Operator 9: benchmark decontamination by spaced seeds (DataFrame and SQL operations only).

Tokens are lower-cased runs of letters and digits. Each fixed mask selects some of the tokens of a
short span and ignores the rest, so a substituted token under a 0 does not hide a match. Seeds of
all documents meet the seeds of the test items by hash. A hit fixes an alignment; the tokens along
it are compared, a match scoring 1 and a mismatch -2, and the best run's score decides.

Items shorter than a mask get a solid mask of their own length. The seeds of the benchmark are
broadcast while they number at most ``MOST_BROADCAST``, else both sides are shuffled by hash.
Texts are followed by their hash, so documents that share a doc_id, or have none, are searched each on
its own. Null texts and items have no tokens and never match; repeated rows give one finding per
(doc_id, item_id), the best of them; very long texts are searched in full. Items that share an
item_id, or have none, count as one item. Other columns are ignored.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from relmodel.llm._common import text_of, written

#: 1 = the token counts, 0 = it is ignored.
MASKS = ("110110101", "11101011")
SCORE, SHARE = 10, 0.6
MOST_BROADCAST = 2_000_000


def tokens(col):
    return F.array_remove(F.split(F.lower(col), r"[^\p{L}\p{N}]+"), "")


def seeds(df: DataFrame, keep: list[str], masks) -> DataFrame:
    """One row (h, pos) per place and mask; ``df`` has tokens t."""
    out = None
    for k, mask in enumerate(masks):
        n = F.greatest(F.size("t") - (len(mask) - 1), F.lit(0))
        picks = [F.slice("t", i + 1, n) for i, x in enumerate(mask) if x == "1"]
        rows = df.where(F.size("t") >= len(mask)).select(*keep, F.posexplode(F.arrays_zip(*(p.alias(f"c{i}") for i, p in enumerate(picks)))).alias("pos", "z"))
        rows = rows.select(*keep, "pos", F.xxhash64(F.lit(mask), *(F.col("z")[f"c{i}"] for i in range(len(picks)))).alias("h"))
        out = rows if out is None else out.union(rows)
    return out


def matches(docs: DataFrame, items: DataFrame, masks=MASKS, score: int = SCORE, share: float = SHARE) -> DataFrame:
    """(doc_id, item_id, score, matched, doc_pos): the best alignment of each overlapping pair.

    An overlap counts when its best run scores ``score``, or ``share`` of the item's tokens if that
    is less."""
    item = written(items.select(F.col("item_id").cast("long").alias("item_id"), tokens(text_of("text")).alias("t")).where(F.size("t") > 0))
    shortest = min(map(len, masks))
    short = [r[0] for r in item.where(F.size("t") < max(map(len, masks))).select(F.size("t")).distinct().collect()]  # fewer than a mask's length
    masks = tuple(masks) + tuple("1" * n for n in short if n < shortest)
    test = written(seeds(item, ["item_id"], masks).withColumnRenamed("pos", "at"))
    small = test.count() <= MOST_BROADCAST
    own = docs.select(F.xxhash64(text_of("text")).alias("key"), tokens(text_of("text")).alias("t"))
    hits = seeds(own, ["key"], masks).join(F.broadcast(test) if small else test, "h")
    lines = written(hits.select("key", "item_id", (F.col("pos") - F.col("at")).alias("diagonal")).distinct())
    found = lines.select("key").distinct()
    few = found.limit(MOST_BROADCAST + 1).count() <= MOST_BROADCAST
    own = own.join(F.broadcast(found) if few else found, "key", "left_semi").dropDuplicates(["key"])
    full = item.select(F.col("item_id").alias("item"), F.col("t").alias("q"))
    some = own.join(lines, "key").join(F.broadcast(full) if small else full, F.col("item_id").eqNullSafe(F.col("item")))
    begin = F.greatest(F.col("diagonal"), F.lit(0))
    some = some.select("key", "item_id", F.size("q").alias("n"), begin.alias("doc_pos"), F.slice("t", begin + 1, F.size("q")).alias("x"), F.slice("q", F.greatest(-F.col("diagonal"), F.lit(0)) + 1, F.size("q")).alias("y"))
    some = some.withColumn("same", F.zip_with("x", "y", lambda a, b: F.coalesce(a == b, F.lit(False))))
    best = F.aggregate("same", F.struct(F.lit(0).alias("run"), F.lit(0).alias("best")), lambda s, m: F.struct(
        F.greatest(F.lit(0), s["run"] + F.when(m, 1).otherwise(-2)).alias("run"), F.greatest(s["best"], s["run"] + F.when(m, 1).otherwise(-2)).alias("best")))["best"]
    some = some.select("key", "item_id", "n", "doc_pos", best.alias("score"), F.size(F.filter("same", lambda m: m)).alias("matched"))
    some = some.where(F.col("score") >= F.least(F.lit(score), F.ceil(F.col("n") * share)))
    top = F.max(F.struct("score", "matched", (-F.col("doc_pos")).alias("before")))
    some = written(some.groupBy("key", "item_id").agg(top.alias("b")))
    ids = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.xxhash64(text_of("text")).alias("key"))
    few = some.limit(MOST_BROADCAST + 1).count() <= MOST_BROADCAST
    out = ids.join(F.broadcast(some) if few else some, "key").groupBy("doc_id", "item_id").agg(F.max("b").alias("b"))
    return out.select("doc_id", "item_id", F.col("b.score").alias("score"), F.col("b.matched").alias("matched"), (-F.col("b.before")).cast("long").alias("doc_pos"))
