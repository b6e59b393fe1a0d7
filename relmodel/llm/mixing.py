"""Operator 1: mixing sources to target weights by weighted fair queueing (DataFrame operations only).

Each source's documents stand in a shuffled order (by hash of the id, of the text where there is none). A document's virtual time is
the source's running word count divided by its target, taken at the document's middle word so that
a cut rounds to the nearer side; a second pass over the source follows the first. Ranges of virtual
time hold about equal numbers of words by construction, so the global sort is a sort by these
ranges: running totals over ranges find the range that crosses the budget, and only that range is
put in order row by row. A source's own running count is taken in ``SLOTS`` hash slots, so one
source with most of the rows is spread over as many tasks.

Null text has size 0 and is never taken; a null source is a source of its own, sorted last; repeated
rows are separate documents. Other columns are ignored.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from relmodel.llm._common import text_of, words_of, written

WEIGHTS = (5, 2, 1)
BUDGET = 1.5
MOST = 2
RANGES = 1 << 15
SEED = "mix"


def ranked(df: DataFrame, *by) -> DataFrame:
    """Adds ``rank`` (from 0) in a total order: range sort, then offsets per sorted partition."""
    mark = F.monotonically_increasing_id()
    own = written(df.orderBy(*by).withColumn("mark", mark)).withColumn("part", F.shiftright("mark", 33))
    off = own.groupBy("part").agg(F.count("*").alias("n"))  # one row per partition
    off = off.select("part", (F.sum("n").over(Window.orderBy("part").rowsBetween(Window.unboundedPreceding, -1))).alias("before"))
    return own.join(F.broadcast(off), "part").withColumn("rank", F.coalesce("before", F.lit(0)) + F.col("mark").bitwiseAND((1 << 33) - 1)).drop("part", "before", "mark")


def source_targets(sizes: DataFrame, weights=WEIGHTS, budget: float = BUDGET, most: int = MOST) -> DataFrame:
    """(source, source_size, target): shares of budget × all words by weight, none above ``most``
    times the source; the excess is shared again by weight until none is above."""
    w = F.element_at(F.array(*map(F.lit, weights)), (F.col("rank") % len(weights) + 1).cast("int"))
    src = written(ranked(sizes, F.col("source").asc_nulls_last()).withColumn("w", w.cast("double")).withColumn("cap", F.col("source_size") * float(most)))
    total = budget * (src.agg(F.sum("source_size")).first()[0] or 0)
    full, load, seen = 0.0, src.agg(F.sum("w")).first()[0] or 0.0, None
    while load and seen != (full, load):
        seen = (full, load)
        over = F.col("w") * F.lit(total - full) / F.lit(load) >= F.col("cap")
        a, b = src.agg(F.sum(F.when(over, F.col("cap")).otherwise(0.0)), F.sum(F.when(over, 0.0).otherwise(F.col("w")))).first()
        full, load = (a, b) if b else (full, load)
        if not b:
            return src.select("source", "source_size", F.col("cap").alias("target"))
    share = F.col("w") * F.lit(total - full) / F.lit(load or 1.0)
    return src.select("source", "source_size", F.least("cap", share).alias("target"))


def timed(docs: DataFrame, targets: DataFrame, seed: str = SEED) -> DataFrame:
    """Adds source_size, target, and v: the virtual time of the first pass. ``docs`` has doc_id,
    source, size and salt (for rows without doc_id)."""
    own = docs.join(targets, docs.source.eqNullSafe(targets.source)).drop(targets.source)
    own = own.withColumn("h", F.md5(F.concat(F.lit(f"{seed}:"), F.coalesce(F.col("doc_id").cast("string"), F.concat(F.lit("null"), "salt"))).cast("binary")))
    own = own.withColumn("slot", F.substring("h", 1, 3))
    key = [F.col("source").isNull().alias("none"), F.coalesce("source", F.lit("")).alias("key"), "slot"]
    own = own.select("*", *key[:2])
    slots = own.groupBy("none", "key", "slot").agg(F.sum("size").alias("n"))
    before = Window.partitionBy("none", "key").orderBy("slot").rowsBetween(Window.unboundedPreceding, -1)
    slots = slots.select("none", "key", "slot", F.coalesce(F.sum("n").over(before), F.lit(0)).alias("base"))
    run = Window.partitionBy("none", "key", "slot").orderBy("h", "doc_id", "size").rowsBetween(Window.unboundedPreceding, 0)
    own = own.withColumn("cum", F.sum("size").over(run)).join(slots, ["none", "key", "slot"])
    v = (2 * (F.col("base") + F.col("cum")) - F.col("size")) / (2 * F.col("target"))
    return own.withColumn("v", F.when(F.col("target") > 0, v)).drop("none", "key", "slot", "base", "cum")


ORDER = ["v", "h", "doc_id", "size"]


def passes(times: DataFrame) -> DataFrame:
    """One row per pass of a document with words."""
    second = F.col("v") + F.col("source_size") / F.col("target")
    return times.where("size > 0 AND target > 0").withColumn("v", F.explode(F.array("v", second)))


def cut_of(times: DataFrame, budget: float) -> tuple:
    """The last place, in ORDER, that the budget takes (None: nothing is taken)."""
    at = F.least(F.floor(F.col("v") * (RANGES // 2)), F.lit(4 * RANGES)).cast("int")
    items = passes(times).withColumn("range", at)
    ranges = items.groupBy("range").agg(F.sum("size").alias("n"))  # at most 4 * RANGES + 1 rows
    ranges = ranges.withColumn("total", F.sum("n").over(Window.orderBy("range")))
    crossing = ranges.where(F.col("total") >= budget).orderBy("range").first() or ranges.orderBy(F.desc("range")).first()
    if crossing is None:
        return None
    inside = items.where(F.col("range") == crossing["range"])
    run = F.lit(crossing["total"] - crossing["n"]) + F.sum("size").over(Window.partitionBy("range").orderBy(*ORDER).rowsBetween(Window.unboundedPreceding, 0))
    last = inside.withColumn("run", run).where(2 * F.col("run") - F.col("size") <= 2 * budget).orderBy(*(F.desc(c) for c in ORDER)).first()
    if last is None:  # all earlier ranges, nothing of this one
        return (crossing["range"] / (RANGES // 2), "", None, 0)
    return tuple(last[c] for c in ORDER)


def within(v, cut: tuple):
    """Whether a pass at virtual time v comes no later than the cut."""
    if cut is None:
        return F.lit(False)
    rest = F.struct(F.col("h"), F.col("doc_id"), F.col("size")) <= F.struct(F.lit(cut[1]), F.lit(cut[2]).cast("long"), F.lit(cut[3]).cast("long"))
    return F.coalesce((v < F.lit(cut[0])) | ((v == F.lit(cut[0])) & rest), F.lit(False))


def mix(docs: DataFrame, weights=WEIGHTS, budget: float = BUDGET, most: int = MOST, seed: str = SEED) -> DataFrame:
    """doc_id, source, size, source_size, target, times (0 to 2), taken, v (virtual time of the first pass);
    ``row_key`` is handed on if ``docs`` has it."""
    more = [c for c in ("row_key",) if c in docs.columns]
    salt = F.when(F.col("doc_id").isNull(), F.md5(text_of("text").cast("binary"))).otherwise("")  # rows without id are spread too
    own = written(docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.col("source").cast("string").alias("source"), F.size(words_of("text")).cast("long").alias("size"), salt.alias("salt"), *more))
    targets = source_targets(own.groupBy("source").agg(F.sum("size").alias("source_size")), weights, budget, most)
    total = budget * (own.agg(F.sum("size")).first()[0] or 0)
    times = written(timed(own, targets, seed))
    cut = cut_of(times, total)
    some = (F.col("size") > 0) & (F.col("target") > 0)
    n = F.when(some & within(F.col("v"), cut), 1).otherwise(0) + F.when(some & within(F.col("v") + F.col("source_size") / F.col("target"), cut), 1).otherwise(0)
    return times.withColumn("times", n).select("doc_id", "source", "size", "source_size", "target", "times", (F.col("times") * F.col("size")).cast("long").alias("taken"), "v", "h", *more)
