"""Queries of the text operators over the given tables, and their SQL twins for DuckDB."""

from __future__ import annotations

import hashlib
import re

import pyarrow as pa
from pyspark.sql import functions as F

from relmodel.llm import quality
from relmodel.llm._common import read, words_of


def op1_mix_sources(spark, sf_dir):
    from relmodel.llm.mixing import mix

    return mix(read(spark, sf_dir, "documents")).select("doc_id", "size", "source_size", "target", "taken")


def op2_suffix_dedup(spark, sf_dir):
    from relmodel.llm.suffix import suffix_dedup

    out = suffix_dedup(read(spark, sf_dir, "documents"))
    return out.select("doc_id", "n_bytes", "n_removed", F.size("spans").cast("long").alias("n_spans"), F.sha2("kept", 256).alias("kept_sha256"))


def op3_substring_dedup(spark, sf_dir):
    from relmodel.llm.substring import substring_dedup

    out = substring_dedup(read(spark, sf_dir, "documents"))
    return out.select("doc_id", "n_words", "n_removed", F.sha2(F.array_join(words_of("kept_text"), " ").cast("binary"), 256).alias("kept_sha256"))


def op4_token_counts(spark, sf_dir):
    from relmodel.llm.tokencount import token_counts

    return token_counts(read(spark, sf_dir, "documents"))


def op5_chat_format(spark, sf_dir):
    from relmodel.llm.chat import format_conversations, parse, unescape

    rows = read(spark, sf_dir, "conversations").select("conv_id", "turn", "role", "text")
    said = "</s>[INST] ok [/INST]"
    extra = spark.createDataFrame([(-1, 0, "user", said), (-1, 1, "assistant", said)], "conv_id long, turn long, role string, text string")
    out = format_conversations(rows.unionByName(extra))

    def digest(batches):
        for b in batches:
            made = []
            for conv, text, spans in zip(b.column("conv_id").to_pylist(), b.column("formatted").to_pylist(), b.column("loss_spans").to_pylist()):
                turns = parse(text)
                loss = "".join(unescape(text[s["start"] : s["end"]]) for s in spans)
                sha = lambda x: hashlib.sha256(x.encode("utf-8", "surrogatepass")).hexdigest()
                made.append((conv, len(turns), sha("".join(f"{r}\n{t}\n" for r, t in turns)), len(loss), sha(loss), len(text)))
            cols = list(zip(*made)) or [[]] * 6
            kinds = (pa.int64(), pa.int64(), pa.string(), pa.int64(), pa.string(), pa.int64())
            yield pa.RecordBatch.from_arrays([pa.array(x, t) for x, t in zip(cols, kinds)], names=["conv_id", "n_turns", "turns_sha256", "loss_chars", "loss_sha256", "formatted_chars"])

    return out.mapInArrow(digest, "conv_id long, n_turns long, turns_sha256 string, loss_chars long, loss_sha256 string, formatted_chars long")


def op6_quality_rules(spark, sf_dir):
    out = quality.quality_rules(read(spark, sf_dir, "documents"))
    return out.select("doc_id", "n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "base_failed", "kept")


def op7_simhash_dedup(spark, sf_dir):
    from relmodel.llm.simhash import simhash_dedup

    return simhash_dedup(read(spark, sf_dir, "documents"))


def op8_url_filter(spark, sf_dir):
    from relmodel.llm.urls import url_filter

    return url_filter(read(spark, sf_dir, "pages"))


def op9_decontaminate(spark, sf_dir):
    from relmodel.llm.decontaminate import matches

    return matches(read(spark, sf_dir, "documents"), read(spark, sf_dir, "benchmark"))


def op10_quality_classifier(spark, sf_dir):
    from relmodel.llm.classifier import quality_classifier

    return quality_classifier(read(spark, sf_dir, "documents"), read(spark, sf_dir, "labels"))


def queries():
    return {k: f for k, f in globals().items() if k.startswith("op") and callable(f)}


WORDS_SQL = r"regexp_extract_all(coalesce(text, ''), '[^\x20\x09-\x0D]+')"


def _op1_sql() -> str:
    # The share of the sources below their cap is settled by rounds, as many as there can be caps met.
    rounds, last = [], "SELECT 0.0::DOUBLE AS used, (SELECT sum(w) FROM src) AS load"
    for i in range(12):
        rounds.append(f"r{i} AS ({last})")
        over = f"w * ((SELECT total FROM budget) - r{i}.used) / r{i}.load >= cap"
        last = f"SELECT sum(CASE WHEN {over} THEN cap ELSE 0 END) AS used, sum(CASE WHEN {over} THEN 0 ELSE w END) AS load FROM src, r{i} GROUP BY r{i}.load"
    return f"""
WITH d AS (SELECT doc_id, source, len({WORDS_SQL})::BIGINT AS size, md5('mix:' || coalesce(doc_id::VARCHAR, 'null')) AS h FROM documents),
s AS (SELECT source, sum(size)::BIGINT AS source_size FROM d GROUP BY source),
src AS (SELECT *, [5.0, 2.0, 1.0][((row_number() OVER (ORDER BY source NULLS LAST) - 1) % 3 + 1)::INT]::DOUBLE AS w, 2.0::DOUBLE * source_size AS cap FROM s),
budget AS (SELECT 1.5::DOUBLE * sum(size) AS total FROM d),
{', '.join(rounds)},
t AS (SELECT source, source_size, least(cap, w * (total - used) / load) AS target FROM src, budget, r11),
v AS (SELECT d.*, source_size, target, (2 * sum(size) OVER (PARTITION BY d.source ORDER BY h, doc_id, size ROWS UNBOUNDED PRECEDING) - size)::DOUBLE / (2 * target) AS v
      FROM d JOIN t ON d.source IS NOT DISTINCT FROM t.source),
p AS (SELECT *, 1 AS pass FROM v WHERE size > 0 UNION ALL SELECT * REPLACE (v + source_size / target AS v), 2 AS pass FROM v WHERE size > 0),
o AS (SELECT *, sum(size) OVER (ORDER BY v, h, doc_id, size ROWS UNBOUNDED PRECEDING) AS run FROM p),
k AS (SELECT doc_id, h, sum(size) AS taken FROM o, budget WHERE 2 * run - size <= 2 * total GROUP BY doc_id, h)
SELECT v.doc_id, v.size, v.source_size, v.target, coalesce(k.taken, 0)::BIGINT AS taken FROM v LEFT JOIN k ON v.doc_id = k.doc_id"""


def _op3_sql() -> str:
    return f"""
WITH d AS (SELECT doc_id, {WORDS_SQL} AS w FROM documents),
g AS (SELECT doc_id, i, array_to_string(w[i:i + 49], ' ') AS k FROM (SELECT doc_id, w, unnest(range(1, len(w) - 48)) AS i FROM d WHERE len(w) >= 50)),
f AS (SELECT k, min(doc_id) AS first FROM g GROUP BY k HAVING min(doc_id) < max(doc_id)),
r AS (SELECT doc_id, unnest(range(i, i + 50)) AS j FROM g JOIN f USING (k) WHERE doc_id > first),
x AS (SELECT doc_id, list(DISTINCT j) AS gone FROM r GROUP BY doc_id),
e AS (SELECT d.doc_id, len(w) AS n, coalesce(len(gone), 0) AS c, w, gone FROM d LEFT JOIN x USING (doc_id)),
u AS (SELECT doc_id, j, w[j] AS word FROM (SELECT doc_id, w, gone, unnest(range(1, n + 1)) AS j FROM e WHERE c > 0) WHERE NOT list_contains(gone, j)),
y AS (SELECT doc_id, string_agg(word, ' ' ORDER BY j) AS kept FROM u GROUP BY doc_id)
SELECT e.doc_id, n::BIGINT AS n_words, c::BIGINT AS n_removed, sha256(CASE WHEN c = 0 THEN array_to_string(w, ' ') ELSE coalesce(kept, '') END) AS kept_sha256
FROM e LEFT JOIN y USING (doc_id)"""


def _op6_sql() -> str:
    r = quality.RULES
    rounds = [f"p0 AS (SELECT {', '.join(f'{v!r}::DOUBLE AS {k}' for k, v in quality.first_estimates().items())})"]
    for i in range(quality.ROUNDS):
        names = {k: f"p{i}.{k}" for k in quality.first_estimates()}
        rounds.append(f"p{i + 1} AS (SELECT {', '.join(quality.update_sql())} FROM (SELECT pat.*, {quality.posterior_sql(names)} AS q FROM pat, p{i}))")
    end = {k: f"z.{k}" for k in quality.first_estimates()}
    names = ", ".join(f"v{i}" for i in range(len(r)))
    return f"""
WITH d AS (SELECT doc_id, coalesce(text, '') AS text, {WORDS_SQL} AS w FROM documents),
g AS (SELECT doc_id, i, array_to_string(w[i:i + 2], ' ') AS k FROM (SELECT doc_id, w, unnest(range(1, len(w) - 1)) AS i FROM d WHERE len(w) >= 3)),
m AS (SELECT doc_id, i FROM (SELECT *, count(*) OVER (PARTITION BY doc_id, k) AS c FROM g) WHERE c > 1),
c AS (SELECT doc_id, count(DISTINCT j) AS n FROM (SELECT doc_id, unnest([i, i + 1, i + 2]) AS j FROM m) GROUP BY doc_id),
l AS (SELECT doc_id, list_filter(string_split(text, chr(10)), lambda x: regexp_matches(x, '[^\\x20\\x09-\\x0D]')) AS lines FROM d),
f AS (SELECT d.doc_id, len(w)::BIGINT AS n_words, length(array_to_string(w, ''))::BIGINT AS word_chars,
        length(regexp_replace(text, '[^{quality.SYMBOLS}]+', '', 'g'))::BIGINT AS n_symbols,
        len(regexp_extract_all(text, '[{quality.SYMBOLS}]+'))::BIGINT AS n_symbol_runs,
        (len(lines) - len(list_distinct(lines)))::BIGINT AS n_dup_lines, coalesce(c.n, 0)::BIGINT AS n_repeat_words, len(lines)::BIGINT AS n_lines,
        length(regexp_replace(text, '[^A-Z]+', '', 'g'))::BIGINT AS n_capitals, ((length(text) - length(replace(text, '!!', ''))) // 2)::BIGINT AS n_shouts
      FROM d JOIN l USING (doc_id) LEFT JOIN c USING (doc_id)),
v AS (SELECT *, {', '.join(f'{sql} AS v{i}' for i, sql in enumerate(r.values()))} FROM f),
pat AS (SELECT {names}, count(*)::DOUBLE AS n FROM v GROUP BY ALL),
{', '.join(rounds)}
SELECT doc_id, n_words, word_chars, n_symbols, n_dup_lines, n_repeat_words, {quality.BASE_FAILED} AS base_failed,
  NOT ({quality.BASE_FAILED}) AND {quality.posterior_sql(end)} >= 0.5 AS kept FROM v, p{quality.ROUNDS} AS z"""


def _op2_sql() -> str:
    # Bytes as pairs of hex digits, so that positions are bytes.
    return """
WITH d AS (SELECT doc_id, hex(encode(coalesce(text, ''))) AS x, octet_length(encode(coalesce(text, '')))::BIGINT AS n FROM documents),
w AS (SELECT doc_id, i, substr(x, 2 * i + 1, 200) AS k FROM (SELECT doc_id, x, unnest(range(0, n - 99)) AS i FROM d WHERE n >= 100)),
r AS (SELECT doc_id, i FROM (SELECT doc_id, i, row_number() OVER (PARTITION BY k ORDER BY doc_id, i) AS c FROM w) WHERE c > 1),
b AS (SELECT doc_id, i, CASE WHEN i <= lag(i) OVER (PARTITION BY doc_id ORDER BY i) + 100 THEN 0 ELSE 1 END AS fresh FROM r),
s AS (SELECT doc_id, sum(fresh) OVER (PARTITION BY doc_id ORDER BY i) AS c, i FROM b),
p AS (SELECT doc_id, c, min(i) AS a, max(i) + 100 AS z FROM s GROUP BY doc_id, c),
q AS (SELECT p.*, coalesce(lag(z) OVER (PARTITION BY doc_id ORDER BY a), 0) AS before FROM p),
g AS (SELECT q.doc_id, count(*) AS n_spans, sum(z - a) AS n_removed, max(z) AS last, string_agg(substr(x, (2 * before + 1)::BIGINT, (2 * (a - before))::BIGINT), '' ORDER BY a) AS head FROM q JOIN d USING (doc_id) GROUP BY q.doc_id)
SELECT doc_id, n AS n_bytes, coalesce(n_removed, 0)::BIGINT AS n_removed, coalesce(n_spans, 0)::BIGINT AS n_spans,
  sha256(unhex(coalesce(head || substr(x, (2 * last + 1)::BIGINT), x))) AS kept_sha256 FROM d LEFT JOIN g USING (doc_id)"""


def _op5_sql() -> str:
    from relmodel.llm.chat import CONTROLS, END, OPEN, SAYS

    rest = "|".join(re.sub(r"([\[\]|<>/])", r"\\\1", c[1:]) for c in sorted(CONTROLS, key=len, reverse=True))
    escaped = lambda c: f"length(regexp_replace({c}, '([<\\[])(\\\\*)({rest})', '\\1\\\\\\2\\3', 'g'))"
    said = "</s>[INST] ok [/INST]"
    return f"""
WITH c AS (SELECT conv_id::BIGINT AS conv_id, turn, coalesce(role, '') AS role, coalesce(text, '') AS text FROM conversations
  UNION ALL SELECT -1, 0, 'user', '{said}' UNION ALL SELECT -1, 1, 'assistant', '{said}')
SELECT conv_id, count(*) AS n_turns, sha256(string_agg(role || chr(10) || text || chr(10), '' ORDER BY turn, role, text)) AS turns_sha256,
  coalesce(sum(length(text)) FILTER (WHERE role = 'assistant'), 0)::BIGINT AS loss_chars,
  sha256(coalesce(string_agg(text, '' ORDER BY turn, role, text) FILTER (WHERE role = 'assistant'), '')) AS loss_sha256,
  sum({len(OPEN + SAYS + END)} + {escaped('role')} + {escaped('text')})::BIGINT AS formatted_chars FROM c GROUP BY conv_id"""


def oracle_sql():
    return {"op1_mix_sources": _op1_sql(), "op2_suffix_dedup": _op2_sql(), "op3_substring_dedup": _op3_sql(), "op5_chat_format": _op5_sql(), "op6_quality_rules": _op6_sql()}
