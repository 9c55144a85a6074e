"""The registered query of each operator, with production parameters, and its SQL where there is one."""

from __future__ import annotations

import os

import public_tokenizers
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from boxprune.llm.shared import table


def _vocabulary(name: str) -> str:
    """Folder of the vocabulary files: a parameter of the environment, by default the public package's."""
    root = os.environ.get("BOXPRUNE_TOKENIZERS")
    return os.path.join(root, name) if root else public_tokenizers.path(name)


def op1_chat_tokens(spark: SparkSession, sf_dir: str) -> DataFrame:
    from boxprune.llm.chat import conversation_digests, format_turns, read_turns

    path, pattern = _vocabulary("byte_bpe_50k.tiktoken"), public_tokenizers.PATTERN
    turns = table(spark, sf_dir, "conversations").select("conv_id", "turn", "role", "text")
    probe = spark.range(2).select(F.lit(-1).cast("long").alias("conv_id"), F.col("id").alias("turn"), F.when(F.col("id") == 0, "user").otherwise("assistant").alias("role"), F.lit("</s>[INST] ok [/INST]").alias("text"))
    return conversation_digests(read_turns(format_turns(turns.unionByName(probe), path, pattern), path, pattern))


def op2_crf_language(spark: SparkSession, sf_dir: str) -> DataFrame:
    from boxprune.llm.langid import predict_languages, train_field

    docs = table(spark, sf_dir, "documents")
    held_out = F.coalesce(F.crc32(F.col("doc_id").cast("string").cast("binary")) % 3 == 1, F.lit(False))
    field = train_field(docs, ~held_out)
    return predict_languages(docs, field).select("doc_id", held_out.alias("held_out"), "lang_pred", "score")


def op3_combination_jaccard(spark: SparkSession, sf_dir: str) -> DataFrame:
    from boxprune.llm.jaccard import jaccard_components

    return jaccard_components(table(spark, sf_dir, "documents"))


def op4_pack_patterns(spark: SparkSession, sf_dir: str) -> DataFrame:
    from boxprune.llm.packing import pack_documents

    return pack_documents(table(spark, sf_dir, "documents"), _vocabulary("byte_bpe_50k.json"), public_tokenizers.PATTERN)


def op5_segment_tree_bpe(spark: SparkSession, sf_dir: str) -> DataFrame:
    from boxprune.llm.bpe import round_trip_digests

    return round_trip_digests(table(spark, sf_dir, "documents"), _vocabulary("byte_bpe_50k.tiktoken"), public_tokenizers.PATTERN)


def op6_host_quality(spark: SparkSession, sf_dir: str) -> DataFrame:
    from boxprune.llm.quality import quality_verdicts

    out = quality_verdicts(table(spark, sf_dir, "documents"))
    return out.select("doc_id", "n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "base_failed", "kept")


def op7_fm_passages(spark: SparkSession, sf_dir: str) -> DataFrame:
    from boxprune.llm.substring import repeated_passages

    return repeated_passages(table(spark, sf_dir, "documents"))


def op9_boosted_pii(spark: SparkSession, sf_dir: str) -> DataFrame:
    from boxprune.llm.pii import KINDS, find_spans, span_digest

    found = find_spans(table(spark, sf_dir, "documents"))
    base = F.filter("spans", lambda s: s["kind"] != "secret")
    of_kind = F.transform("spans", lambda s: s["kind"])
    counts = [(F.size(of_kind) - F.size(F.array_remove(of_kind, k))).cast("long").alias(f"n_{k}") for k in KINDS]
    return found.select("doc_id", *counts, F.sha2(span_digest(base), 256).alias("base_sha256"), span_digest(F.col("spans")).alias("spans"), F.size("spans").cast("long").alias("n_spans"))


def op10_hnsw_shards(spark: SparkSession, sf_dir: str) -> DataFrame:
    from boxprune.llm.hnsw import nearest_neighbours

    return nearest_neighbours(table(spark, sf_dir, "embeddings"), F.col("id") % 100 == 0)


def op8_site_lines(spark: SparkSession, sf_dir: str) -> DataFrame:
    from boxprune.llm.lines import drop_boilerplate

    return drop_boilerplate(table(spark, sf_dir, "documents"), counts=True).select("doc_id", "n_lines", "n_dropped", "text")


QUERIES = {f.__name__: f for f in (op1_chat_tokens, op2_crf_language, op3_combination_jaccard, op4_pack_patterns, op5_segment_tree_bpe, op6_host_quality, op7_fm_passages, op8_site_lines, op9_boosted_pii, op10_hnsw_shards)}

_WORD = r"[^\x20\x09-\x0D]+"

#: Control strings of the chat template, as in chat.CONTROLS.
_CONTROL = r"<\|turn\|>|<\|text\|>|<\|end\|>|<s>|</s>|\[INST\]|\[/INST\]|<<SYS>>|<</SYS>>|<\|im_start\|>|<\|im_end\|>|<\|endoftext\|>|<\|system\|>|<\|user\|>|<\|assistant\|>"

ORACLES = {
    "op1_chat_tokens": rf"""
WITH t AS (SELECT conv_id, turn, coalesce(role, '') AS role, coalesce(text, '') AS text FROM conversations
  UNION ALL SELECT -1, i, CASE i WHEN 0 THEN 'user' ELSE 'assistant' END, '</s>[INST] ok [/INST]' FROM range(2) r(i))
SELECT conv_id, count(*)::BIGINT AS n_turns,
  sha256(string_agg(role || chr(10) || text || chr(10), '' ORDER BY turn, role, text)) AS turns_sha256,
  coalesce(sum(length(text)) FILTER (WHERE role = 'assistant'), 0)::BIGINT AS loss_chars,
  sha256(coalesce(string_agg(text, '' ORDER BY turn, role, text) FILTER (WHERE role = 'assistant'), '')) AS loss_sha256,
  sum(length(role) + length(text) + 25 + len(regexp_extract_all(role, '{_CONTROL}')) + len(regexp_extract_all(text, '{_CONTROL}')))::BIGINT AS formatted_chars
FROM t GROUP BY conv_id""",
    "op3_combination_jaccard": rf"""
WITH RECURSIVE t AS (SELECT doc_id, translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz') AS x FROM documents),
w AS (SELECT doc_id, regexp_extract_all(x, '{_WORD}') AS ws FROM t),
s AS (SELECT doc_id, CASE WHEN len(ws) = 0 THEN []::VARCHAR[] WHEN len(ws) < 3 THEN [array_to_string(ws, ' ')]
  ELSE list_distinct(list_transform(generate_series(1, len(ws) - 2), lambda i: array_to_string(ws[i:i+2], ' '))) END AS g FROM w),
n AS MATERIALIZED (SELECT doc_id, len(g) AS n FROM s),
e AS MATERIALIZED (SELECT doc_id, unnest(g) AS g FROM s),
i AS (SELECT a.doc_id AS a, b.doc_id AS b, count(*) AS c FROM e a JOIN e b ON a.g = b.g AND a.doc_id < b.doc_id GROUP BY 1, 2),
l AS MATERIALIZED (SELECT a, b FROM i JOIN n na ON na.doc_id = a JOIN n nb ON nb.doc_id = b WHERE 100 * c >= 90 * (na.n + nb.n - c)),
d AS (SELECT a, b FROM l UNION ALL SELECT b, a FROM l),
r AS (SELECT doc_id AS x, doc_id AS y FROM n UNION SELECT d.b, r.y FROM r JOIN d ON d.a = r.x),
c AS (SELECT x, min(y) AS y FROM r GROUP BY x)
SELECT n.doc_id, n.n::BIGINT AS n_shingles, c.y AS component_id FROM n JOIN c ON c.x = n.doc_id""",
    "op6_host_quality": rf"""
WITH t AS (SELECT doc_id, coalesce(text, '') AS text, source, row_number() OVER () AS rid FROM documents),
w AS (SELECT rid, regexp_extract_all(text, '{_WORD}') AS ws FROM t),
win AS (SELECT rid, i, array_to_string(ws[i:i+4], ' ') AS g FROM (SELECT rid, ws, unnest(generate_series(1, len(ws) - 4)) AS i FROM w WHERE len(ws) >= 5)),
hot AS (SELECT rid, i FROM (SELECT rid, i, count(*) OVER (PARTITION BY rid, g) AS c FROM win) WHERE c > 1),
rep AS (SELECT rid, count(DISTINCT p) AS n FROM (SELECT rid, i + unnest([0, 1, 2, 3, 4]) AS p FROM hot) GROUP BY rid),
ln AS (SELECT rid, sum(c - 1) AS n FROM (SELECT rid, l, count(*) AS c FROM (SELECT rid, unnest(string_split(text, chr(10))) AS l FROM t) WHERE regexp_matches(l, '[^\x20\x09-\x0D]') GROUP BY rid, l) GROUP BY rid),
c AS (SELECT t.rid, t.doc_id, t.source, len(w.ws) AS n_words,
  length(regexp_replace(t.text, '[\x20\x09-\x0D]', '', 'g')) AS word_chars,
  length(regexp_replace(t.text, '[^#*$%&|<>]', '', 'g')) AS n_symbols,
  coalesce(ln.n, 0) AS n_dup_lines, coalesce(rep.n, 0) AS n_repeat_words
  FROM t JOIN w USING (rid) LEFT JOIN ln USING (rid) LEFT JOIN rep USING (rid)),
b AS (SELECT *, (n_words < 10 OR 100 * n_repeat_words > 20 * n_words) AS base_failed FROM c),
h AS (SELECT source, count(*)::DOUBLE AS n, sum(base_failed::INT)::DOUBLE AS f FROM b GROUP BY source),
m AS (SELECT avg(f / n) AS m, var_pop(f / n) AS v FROM h),
p AS (SELECT m, CASE WHEN v > 0 THEN least(greatest(m * (1 - m) / v - 1, 1.0), 1e6) ELSE 1e6 END AS s FROM m),
r AS (SELECT source, (f + m * s) / (n + s) > 0.5 AS bad FROM h, p)
SELECT doc_id, n_words::BIGINT AS n_words, word_chars::BIGINT AS word_chars, n_symbols::BIGINT AS n_symbols,
  n_dup_lines::BIGINT AS n_dup_lines, n_repeat_words::BIGINT AS n_repeat_words, base_failed, (NOT base_failed AND NOT r.bad) AS kept
FROM b JOIN r ON b.source IS NOT DISTINCT FROM r.source""",
    "op7_fm_passages": rf"""
WITH w AS (SELECT doc_id, regexp_extract_all(coalesce(text, ''), '{_WORD}') AS ws FROM documents),
g AS (SELECT doc_id, i, hash(array_to_string(ws[i:i+49], ' ')) AS g FROM (SELECT doc_id, ws, unnest(generate_series(1, len(ws) - 49)) AS i FROM w WHERE len(ws) >= 50)),
m AS (SELECT doc_id, i, min(doc_id) OVER (PARTITION BY g) < doc_id AS again FROM g),
r AS (SELECT DISTINCT doc_id, i + unnest(range(50)) AS p FROM m WHERE again),
x AS (SELECT doc_id, unnest(ws) AS word, generate_subscripts(ws, 1) AS p FROM w),
k AS (SELECT x.doc_id, count(r.p) AS n, string_agg(x.word, ' ' ORDER BY x.p) FILTER (WHERE r.p IS NULL) AS kept FROM x LEFT JOIN r USING (doc_id, p) GROUP BY x.doc_id)
SELECT w.doc_id, len(w.ws)::BIGINT AS n_words, coalesce(k.n, 0)::BIGINT AS n_removed, sha256(coalesce(k.kept, '')) AS kept_sha256 FROM w LEFT JOIN k USING (doc_id)""",
    "op8_site_lines": r"""
WITH t AS (SELECT doc_id, text, source, row_number() OVER () AS rid FROM documents),
l AS (SELECT rid, source, unnest(string_split(text, chr(10))) AS line, generate_subscripts(string_split(text, chr(10)), 1) AS i FROM t WHERE text IS NOT NULL),
p AS (SELECT source, count(*) AS pages FROM t GROUP BY source),
c AS (SELECT source, line, count(DISTINCT rid) AS n FROM l WHERE regexp_matches(line, '[^\x20\x09-\x0D]') GROUP BY source, line),
bad AS (SELECT c.source, c.line FROM c JOIN p ON c.source IS NOT DISTINCT FROM p.source WHERE n >= 3 AND n > 0.3 * pages),
k AS (SELECT l.rid, count(*) AS n_lines, count(bad.line) AS n_dropped, coalesce(string_agg(l.line, chr(10) ORDER BY l.i) FILTER (WHERE bad.line IS NULL), '') AS kept
  FROM l LEFT JOIN bad ON l.line = bad.line AND l.source IS NOT DISTINCT FROM bad.source GROUP BY l.rid)
SELECT t.doc_id, coalesce(n_lines, 0)::BIGINT AS n_lines, coalesce(n_dropped, 0)::BIGINT AS n_dropped, CASE WHEN t.text IS NULL THEN NULL ELSE kept END AS text
FROM t LEFT JOIN k USING (rid)""",
}
