"""Attribute embeddings as column expressions (E1-E5, B18) for plans and score functions."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from relmodel.functions.vec import fixed_weight


def fit_vocab(df: DataFrame, column: str, cap: int = 1000) -> DataFrame:
    """(value, idx) of the ``cap`` most frequent values from 1 on; 0 stands for all others."""
    from pyspark.sql import Window

    counts = df.where(F.col(column).isNotNull()).groupBy(F.col(column).alias("value")).count().orderBy(F.desc("count"), "value").limit(cap)
    return counts.select("value", F.row_number().over(Window.orderBy(F.desc("count"), "value")).alias("idx"), "count")  # at most cap rows


def embed_categorical(df: DataFrame, column: str, vocab: DataFrame, d: int = 4) -> DataFrame:
    """Lookup of a d-vector by vocabulary index (unknown: index 0)."""
    own = df.join(F.broadcast(vocab.select(F.col("value").alias(column), "idx")), column, "left").withColumn("idx", F.coalesce("idx", F.lit(0)))
    return own.select("*", *(F.round(F.sin(1 + 7 * F.col("idx") + j) / 4, 9).alias(f"e{j}") for j in range(d)))


def hashed_index(column: str, size: int) -> Column:
    """E2 for vocabularies too large to broadcast."""
    return F.pmod(F.xxhash64(column), F.lit(size))


def embed_numerical(x: Column, mean: float, spread: float, d: int = 4) -> list[Column]:
    """Z-score times a direction plus a bias."""
    z = (x - F.lit(mean)) / F.lit(spread)
    return [F.round(z * F.lit(fixed_weight(0, 0, j)) + F.lit(fixed_weight(1, 0, j)), 9).alias(f"e{j}") for j in range(d)]


def time_features(ts: Column, base_year: int) -> list[Column]:
    """E5: year offset and sine/cosine of month, day and hour."""
    two_pi = 6.283185307179586
    out = [(F.year(ts) - base_year).alias("year_offset")]
    for name, part, period in (("month", F.month(ts), 12), ("day", F.dayofmonth(ts), 31), ("hour", F.hour(ts), 24)):
        angle = part * F.lit(two_pi) / F.lit(float(period))
        out += [(F.round(F.sin(angle), 9) + 0.0).alias(f"{name}_sin"), (F.round(F.cos(angle), 9) + 0.0).alias(f"{name}_cos")]
    return out


def text_vector(text: Column, column: str, width: int = 16) -> Column:
    """Frozen vector of (column name, text): each word adds or takes one at a place, both told by its
    hash; scaled to length one. Null or without words: zeros."""
    words = F.array_remove(F.split(F.lower(F.coalesce(text.cast("string"), F.lit(""))), r"[^\p{L}\p{N}]+"), "")
    codes = F.transform(words, lambda w: F.pmod(F.conv(F.substring(F.md5(F.concat(F.lit(f"{column}:"), w).cast("binary")), 1, 6), 16, 10).cast("int"), F.lit(2 * width)))
    held = lambda own, h: -F.size(F.array_remove(own, F.lit(h)))  # noqa: E731  places of h, less a constant
    sums = _once(codes, lambda own: F.array(*(held(own, 2 * i + 1) - held(own, 2 * i) for i in range(width))))
    norm = lambda s: F.greatest(F.sqrt(F.aggregate(s, F.lit(0), lambda a, v: a + v * v).cast("double")), F.lit(1.0))
    return _once(sums, lambda s: _once(norm(s), lambda n: F.transform(s, lambda v: v / n)))


def _once(value: Column, then) -> Column:
    """``then`` of a value that is worked out once, however often ``then`` names it."""
    return F.transform(F.array(value), then)[0]


def serialise(columns: dict[str, str]) -> Column:
    """A row as 'attribute value' pairs; nulls are left out."""
    return F.concat_ws(", ", *(F.when(F.col(c).isNotNull(), F.concat_ws(" ", F.lit(label), F.col(c).cast("string"))) for label, c in columns.items()))
