"""Operator 8: URL filter by mined association rules.

Given rules (host, path prefix) judge the urls they fit. Their verdicts label the tokens of those
urls, FP-growth finds token sets that go with a verdict, and rules above a support and a confidence
judge the other urls. Mined rules are matched through an inverted index: each rule is filed under
its rarest token, a url looks up its tokens and checks the whole set.

A null url, or one without "://", has an empty host and path and gets the default verdict.
Repeated rows are judged alike; other columns are ignored. Each distinct url is judged once.
"""

from __future__ import annotations

from pyspark.ml.fpm import FPGrowth
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from relmodel.llm._common import written

#: Fixed values: (verdict, host, path).
RULES = (("allow", "org", "/"), ("block", "example.org", "/es/"), ("block", "example.org", "/en/1"), ("allow", "com", "/fr/"), ("block", "com", "/de/"))
SUPPORT, CONFIDENCE, DEFAULT = 0.01, 0.8, "allow"
MOST_BROADCAST = 200_000


def parts(df: DataFrame) -> DataFrame:
    """Adds host, path and rest (from ? or # on) of column url."""
    tail = F.when(F.instr("url", "://") > 0, F.expr("substr(url, instr(url, '://') + 3)")).otherwise(F.lit(""))
    df = df.withColumn("tail", F.coalesce(tail, F.lit("")))
    host = F.regexp_extract("tail", r"^([^/?#]*)", 1)
    df = df.withColumn("raw", host).withColumn("after", F.expr("substr(tail, length(raw) + 1)"))
    df = df.withColumn("path", F.regexp_extract("after", r"^([^?#]*)", 1)).withColumn("rest", F.expr("substr(after, length(path) + 1)"))
    upper, lower = "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"
    return df.withColumn("host", F.translate("raw", upper, lower)).drop("tail", "raw", "after")


def ruled(df: DataFrame, rules=RULES) -> DataFrame:
    """url, rule, verdict of the longest rule that fits; urls that none fits are absent."""
    spark = df.sparkSession
    table = spark.createDataFrame([(v, h, p, h + p) for v, h, p in rules], "verdict string, at string, prefix string, rule string")
    label = F.split("host", r"\.")
    ends = F.transform(F.sequence(F.lit(1), F.size(label)), lambda i: F.array_join(F.slice(label, i, F.size(label)), "."))
    own = df.select("url", "path", F.explode(ends).alias("at")).join(F.broadcast(table) if len(rules) <= MOST_BROADCAST else table, "at").where(F.col("path").startswith(F.col("prefix")))
    best = own.groupBy("url").agg(F.max(F.struct(F.length("rule").alias("n"), "rule", "verdict")).alias("b"))
    return best.select("url", F.col("b.rule").alias("rule"), F.col("b.verdict").alias("verdict"))


def tokens():
    """Tokens of a url: its host and the host's ends, words of the path, names in the query, marks."""
    label = F.split("host", r"\.")
    ends = F.transform(F.sequence(F.lit(1), F.size(label)), lambda i: F.concat(F.lit("host:"), F.array_join(F.slice(label, i, F.size(label)), ".")))
    first = F.array(F.concat(F.lit("sub:"), label[0]))
    steps = F.transform(F.filter(F.split("path", "/"), lambda s: (s != "") & ~s.rlike(r"^\d+$")), lambda s: F.concat(F.lit("path:"), s))
    asked = F.transform(F.regexp_extract_all("rest", F.lit(r"[?&]([^=&#]+)"), F.lit(1)), lambda s: F.concat(F.lit("ask:"), s))
    marks = F.when(F.instr("rest", "#") > 0, F.array(F.lit("mark:#"))).otherwise(F.array().cast("array<string>"))
    size = F.array(F.concat(F.lit("deep:"), F.size(F.split("path", "/")).cast("string")))
    return F.array_distinct(F.concat(ends, first, steps, asked, marks, size))


def mine(labelled: DataFrame, support: float = SUPPORT, confidence: float = CONFIDENCE) -> DataFrame:
    """(antecedent, verdict, confidence, support, key): pruned rules from (items, verdict) rows; key
    is the antecedent's rarest token."""
    spark = labelled.sparkSession
    basket = written(labelled.select(F.array_append("items", F.concat(F.lit("verdict:"), "verdict")).alias("items")))
    if basket.isEmpty():
        return spark.createDataFrame([], "antecedent array<string>, verdict string, confidence double, support double, key string")
    model = FPGrowth(itemsCol="items", minSupport=support, minConfidence=confidence).fit(basket)
    rules = model.associationRules.where(F.size("consequent") == 1).where(F.col("consequent")[0].startswith("verdict:"))
    rules = rules.select(F.array_sort("antecedent").alias("antecedent"), F.substring_index(F.col("consequent")[0], ":", -1).alias("verdict"), "confidence", "support")
    rules = rules.where(~F.exists("antecedent", lambda x: x.startswith("verdict:")))
    single = model.freqItemsets.where(F.size("items") == 1).select(F.col("items")[0].alias("key"), "freq")
    filed = rules.select("*", F.explode("antecedent").alias("key")).join(single, "key")
    filed = filed.groupBy("antecedent", "verdict", "confidence", "support").agg(F.min(F.struct("freq", "key")).alias("k"))
    return written(filed.select("antecedent", "verdict", "confidence", "support", F.col("k.key").alias("key")))


def judge(df: DataFrame, rules: DataFrame) -> DataFrame:
    """url, verdict by the most confident mined rule (then support, then name); others are absent."""
    small = rules.count() <= MOST_BROADCAST  # bounded by 1/support and the tokens of a url, checked here
    own = df.select("url", "items", F.explode("items").alias("key")).join(F.broadcast(rules) if small else rules, "key")
    own = own.where(F.size(F.array_except("antecedent", "items")) == 0)
    best = own.groupBy("url").agg(F.max(F.struct("confidence", "support", F.array_join("antecedent", " ").alias("name"), "verdict")).alias("b"))
    return best.select("url", F.col("b.verdict").alias("verdict"))


def url_filter(pages: DataFrame, rules=RULES, support: float = SUPPORT, confidence: float = CONFIDENCE, default: str = DEFAULT) -> DataFrame:
    """page_id, host, path, rule, verdict per row of (page_id, url)."""
    rows = pages.select(F.col("page_id").cast("long").alias("page_id"), F.col("url").cast("string").alias("url"))
    urls = written(parts(rows.select("url").where("url IS NOT NULL").distinct()).withColumn("items", tokens()))
    fixed = written(ruled(urls, rules))
    mined = mine(urls.join(fixed, "url").select("items", "verdict"), support, confidence)
    rest = judge(urls.join(fixed, "url", "left_anti"), mined)
    verdicts = fixed.union(rest.select("url", F.lit(None).cast("string").alias("rule"), "verdict"))
    out = urls.select("url", "host", "path").join(verdicts, "url", "left")
    out = rows.join(out, "url", "left")
    none = F.lit("")
    return out.select("page_id", F.coalesce("host", none).alias("host"), F.coalesce("path", none).alias("path"), "rule", F.coalesce("verdict", F.lit(default)).alias("verdict"))
