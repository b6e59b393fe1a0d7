"""Operator 6: quality rules as weak supervision (DataFrame and SQL operations only).

Rules over counted features vote for (1) or against (-1) a document or abstain (0).
Expectation-maximisation over the table of vote patterns (at most 3 ** rules rows, whatever the
corpus) estimates how often each rule is right on good and on bad documents; the posterior
probability of good quality then decides, instead of all rules having to pass.

Null text is an empty text. Repeated rows are judged alike. Other columns are ignored.
"""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from relmodel.llm._common import SPACE_CHARS, SPACE_PATTERN, text_of, written

#: Characters counted as symbols.
SYMBOLS = "#*$%&|<>"

#: Votes as SQL over the features, in integers so that every engine agrees.
RULES = {
    "length": "CASE WHEN n_words < 50 THEN -1 WHEN n_words >= 80 THEN 1 ELSE 0 END",
    "symbols": "CASE WHEN 10 * n_symbols > 3 * n_words THEN -1 WHEN 20 * n_symbols < n_words THEN 1 ELSE 0 END",
    "symbol_share": "CASE WHEN 100 * n_symbols > 5 * word_chars THEN -1 WHEN 100 * n_symbols < word_chars THEN 1 ELSE 0 END",
    "marked": "CASE WHEN 10 * n_symbol_runs > 2 * n_words THEN -1 WHEN 50 * n_symbol_runs < n_words THEN 1 ELSE 0 END",
    "repeats": "CASE WHEN 100 * n_repeat_words > 30 * n_words THEN -1 WHEN 100 * n_repeat_words < 15 * n_words THEN 1 ELSE 0 END",
    "lines": "CASE WHEN 100 * n_dup_lines > 30 * n_lines THEN -1 WHEN 10 * n_dup_lines <= n_lines THEN 1 ELSE 0 END",
    "capitals": "CASE WHEN 10 * n_capitals > 4 * word_chars THEN -1 WHEN 10 * n_capitals < word_chars THEN 1 ELSE 0 END",
    "shouts": "CASE WHEN 10 * n_shouts > 2 * n_words THEN -1 WHEN 50 * n_shouts < n_words THEN 1 ELSE 0 END",
    "word_size": "CASE WHEN word_chars > 12 * n_words OR word_chars < 2 * n_words THEN -1 WHEN word_chars BETWEEN 3 * n_words AND 10 * n_words THEN 1 ELSE 0 END",
}
BASE_FAILED = "n_words < 50 OR 100 * n_repeat_words > 50 * n_words"
#: A rule is a precise one: of good documents it votes against 1 in 100 at most (``LEAST_ON_GOOD``),
#: while it may miss most kinds of bad ones; without that bound the largest kind of bad document
#: would be the only one that the estimates tell apart.
ROUNDS, PRIOR, RIGHT_ON_GOOD, RIGHT_ON_BAD, LEAST_ON_GOOD, SMOOTH = 15, 0.85, 0.99, 0.3, 0.99, 5.0
FEATURES = ["n_words", "word_chars", "n_symbols", "n_symbol_runs", "n_dup_lines", "n_repeat_words", "n_lines", "n_capitals", "n_shouts"]


def features(docs: DataFrame, keep: list[str]) -> DataFrame:
    """The columns of ``keep`` and the features of column ``body``."""
    trimmed = F.btrim("body", F.lit(SPACE_CHARS))
    d = docs.select(*keep, "body", F.when(trimmed == "", F.array().cast("array<string>")).otherwise(F.split(trimmed, SPACE_PATTERN)).alias("w"))
    lines = F.filter(F.split("body", "\n"), lambda x: F.btrim(x, F.lit(SPACE_CHARS)) != "")
    n3 = F.greatest(F.size("w") - 2, F.lit(0))
    zipped = F.arrays_zip(F.slice("w", 1, n3).alias("a"), F.slice("w", 2, n3).alias("b"), F.slice("w", 3, n3).alias("c"))
    d = d.select(
        *keep, F.size("w").cast("long").alias("n_words"), F.length(F.array_join("w", "")).cast("long").alias("word_chars"),
        F.btrim(F.regexp_replace("body", f"[^{SYMBOLS}]+", " ")).alias("marks"), lines.alias("lines"),
        F.length(F.regexp_replace("body", "[^A-Z]+", "")).cast("long").alias("n_capitals"),
        ((F.length("body") - F.length(F.replace(F.col("body"), F.lit("!!"), F.lit("")))) / 2).cast("long").alias("n_shouts"),
        F.transform(zipped, lambda z: F.xxhash64(z["a"], z["b"], z["c"])).alias("grams"),
    )
    marks = F.length(F.replace(F.col("marks"), F.lit(" "), F.lit("")))
    runs = F.when(F.col("marks") == "", 0).otherwise(F.length("marks") - marks + 1)
    d = d.withColumn("n_symbols", marks.cast("long")).withColumn("n_symbol_runs", runs.cast("long")).drop("marks")
    d = d.withColumn("twice", F.size(F.array_distinct("grams")) < F.size("grams"))
    # Positions of windows that occur twice: neighbours in (hash, position) order.
    d = d.withColumn("s", F.when(F.col("twice"), F.sort_array(F.transform("grams", lambda h, i: F.struct(h.alias("h"), i.alias("i"))))))
    same = lambda x, k: (F.get("s", k - 1)["h"] == x["h"]) | (F.get("s", k + 1)["h"] == x["h"])
    marked = F.transform("s", lambda x, k: F.when(F.coalesce(same(x, k), F.get("s", k - 1)["h"] == x["h"], F.get("s", k + 1)["h"] == x["h"]), x["i"]))
    d = d.withColumn("p", F.sort_array(F.array_compact(marked)))
    covered = F.aggregate(F.transform("p", lambda p, k: F.least(F.lit(3), F.coalesce(F.get("p", k + 1) - p, F.lit(3)))), F.lit(0), lambda a, x: a + x)
    return d.select(
        *keep, "n_words", "word_chars", "n_symbols", "n_symbol_runs", (F.size("lines") - F.size(F.array_distinct("lines"))).cast("long").alias("n_dup_lines"),
        F.coalesce(covered, F.lit(0)).cast("long").alias("n_repeat_words"), F.size("lines").cast("long").alias("n_lines"), "n_capitals", "n_shouts",
    )


def posterior_sql(p: dict[str, object]) -> str:
    """Probability of good quality as SQL; p gives numbers or column names for prior, g_i and b_i."""
    terms = [f"CASE v{i} WHEN 1 THEN ln({p[f'g{i}']} / (1 - {p[f'b{i}']})) WHEN -1 THEN ln((1 - {p[f'g{i}']}) / {p[f'b{i}']}) ELSE 0 END" for i in range(len(RULES))]
    return f"1 / (1 + exp(-(ln({p['prior']} / (1 - {p['prior']})) + {' + '.join(terms)})))"


def update_sql() -> list[str]:
    """The next estimates as SQL aggregates over patterns (v_i, n) with posterior q."""
    out = [f"round((sum(n * q) + {SMOOTH * PRIOR}) / (sum(n) + {SMOOTH}), 9) AS prior"]
    for i in range(len(RULES)):
        out.append(f"round(greatest({LEAST_ON_GOOD}, (sum(CASE WHEN v{i} = 1 THEN n * q ELSE 0 END) + {SMOOTH * RIGHT_ON_GOOD}) / (sum(CASE WHEN v{i} <> 0 THEN n * q ELSE 0 END) + {SMOOTH})), 9) AS g{i}")
        out.append(f"round((sum(CASE WHEN v{i} = -1 THEN n * (1 - q) ELSE 0 END) + {SMOOTH * RIGHT_ON_BAD}) / (sum(CASE WHEN v{i} <> 0 THEN n * (1 - q) ELSE 0 END) + {SMOOTH}), 9) AS b{i}")
    return out


def first_estimates() -> dict[str, float]:
    return {"prior": PRIOR} | {f"g{i}": RIGHT_ON_GOOD for i in range(len(RULES))} | {f"b{i}": RIGHT_ON_BAD for i in range(len(RULES))}


def fit(votes: DataFrame) -> dict[str, float]:
    """Estimates from all documents' votes. Only the pattern counts and 1 + 2 * rules numbers a
    round leave the executors."""
    names = [f"v{i}" for i in range(len(RULES))]
    patterns = written(votes.groupBy(*names).agg(F.count("*").cast("double").alias("n")).coalesce(1))
    p: dict[str, object] = first_estimates()
    if patterns.isEmpty():
        return p
    for _ in range(ROUNDS):
        exact = {k: f"{v!r}D" for k, v in p.items()}
        p = patterns.selectExpr("*", f"{posterior_sql(exact)} AS q").selectExpr(*update_sql()).first().asDict()
    return p


def voted(feats: DataFrame) -> DataFrame:
    return feats.selectExpr("*", *(f"{sql} AS v{i}" for i, sql in enumerate(RULES.values())))


def verdict(feats: DataFrame, estimates: dict[str, float]) -> DataFrame:
    """Adds the votes, ``quality`` (posterior), base_failed and kept."""
    exact = {k: f"{v!r}D" for k, v in estimates.items()}
    out = voted(feats).selectExpr("*", f"{posterior_sql(exact)} AS quality", f"{BASE_FAILED} AS base_failed")
    return out.withColumn("kept", ~F.col("base_failed") & (F.col("quality") >= 0.5))


def judged(feats: DataFrame) -> DataFrame:
    """Estimates from all of ``feats`` and its verdicts; it is read twice."""
    return verdict(feats, fit(voted(feats)))


def quality_rules(docs: DataFrame) -> DataFrame:
    """doc_id, the features, votes, quality, base_failed and kept per row."""
    own = docs.select(F.col("doc_id").cast("long").alias("doc_id"), text_of("text").alias("body"))
    return judged(written(features(own, ["doc_id"])))
