"""Registered queries of this folder, and DuckDB SQL where it can say the same."""

from __future__ import annotations

import public_tokenizers
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from erblock.llm import byte_bpe, chat_format, lm_scoring, mixing, ngram_join, quality_rules, suffix_dedup, token_counts, topk_search, url_filter

WS = r"[^\x20\x09-\x0D]+"


def _table(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def op1_url_filter(spark: SparkSession, sf_dir: str) -> DataFrame:
    return url_filter.judge(_table(spark, sf_dir, "pages"))


def op2_ngram_jaccard_join(spark: SparkSession, sf_dir: str) -> DataFrame:
    return ngram_join.near_duplicates(_table(spark, sf_dir, "documents")).select("doc_id", "class_id", "n_links")


def op3_suffix_array_dedup(spark: SparkSession, sf_dir: str) -> DataFrame:
    out = suffix_dedup.remove_repeats(_table(spark, sf_dir, "documents"))
    return out.select("doc_id", "n_bytes", "n_removed", "n_spans", "kept_sha256")


def op4_quality_rules(spark: SparkSession, sf_dir: str) -> DataFrame:
    led = quality_rules.ledger(_table(spark, sf_dir, "documents").select("doc_id", "text"))
    judged = quality_rules.apply_policy(led, quality_rules.PRODUCTION)
    return judged.select("doc_id", "n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", (~quality_rules.passes(quality_rules.BASE)).alias("base_failed"), "kept")


def op5_chat_format(spark: SparkSession, sf_dir: str) -> DataFrame:
    convs = _table(spark, sf_dir, "conversations").select("conv_id", "turn", "role", "text")
    tag = "</s>[INST] ok [/INST]"
    roles = F.explode(F.array(*[F.struct(F.lit(i).cast("long").alias("turn"), F.lit(r).alias("role")) for i, r in enumerate(("user", "assistant"))]))
    extra = spark.range(1).select(roles.alias("x")).select(F.lit(-1).cast("long").alias("conv_id"), "x.turn", "x.role", F.lit(tag).alias("text"))
    return chat_format.digests(convs.unionByName(extra))


def op6_lm_scoring(spark: SparkSession, sf_dir: str) -> DataFrame:
    return lm_scoring.score(_table(spark, sf_dir, "documents"))


def op7_exact_topk(spark: SparkSession, sf_dir: str) -> DataFrame:
    return topk_search.top_k(_table(spark, sf_dir, "embeddings"), F.col("vec_id") % 50 == 0)


def op8_byte_bpe(spark: SparkSession, sf_dir: str) -> DataFrame:
    path = public_tokenizers.path("byte_bpe_50k.tiktoken")
    return byte_bpe.digests(_table(spark, sf_dir, "documents"), path, public_tokenizers.PATTERN)


def op9_mixing(spark: SparkSession, sf_dir: str) -> DataFrame:
    mixed = mixing.mix(_table(spark, sf_dir, "documents"))
    return mixed.select("doc_id", "size", "source_size", "target", (F.col("size") * F.col("n_copies")).alias("taken"))


def op10_token_counts(spark: SparkSession, sf_dir: str) -> DataFrame:
    return token_counts.token_counts(_table(spark, sf_dir, "documents"), public_tokenizers.path("piece_bpe_32k.model"))


def url_rules(spark: SparkSession, sf_dir: str) -> DataFrame:
    return url_filter.by_rules(_table(spark, sf_dir, "pages"))


def url_filter_quality(spark: SparkSession, sf_dir: str) -> DataFrame:
    return url_filter.quality(_table(spark, sf_dir, "pages"))


def quality_ledger(spark: SparkSession, sf_dir: str) -> DataFrame:
    return quality_rules.ledger(_table(spark, sf_dir, "documents").select("doc_id", "text")).drop("text")


def quality_ablations(spark: SparkSession, sf_dir: str) -> DataFrame:
    return quality_rules.ablations(quality_rules.ledger(_table(spark, sf_dir, "documents").select("doc_id", "text")))


def quality_patterns(spark: SparkSession, sf_dir: str) -> DataFrame:
    return quality_rules.patterns(quality_rules.ledger(_table(spark, sf_dir, "documents").select("doc_id", "text")))


def queries() -> dict:
    named = (op1_url_filter, op2_ngram_jaccard_join, op3_suffix_array_dedup, op4_quality_rules, op5_chat_format, op6_lm_scoring, op7_exact_topk, op8_byte_bpe, op9_mixing, op10_token_counts, url_rules, url_filter_quality, quality_ledger, quality_ablations, quality_patterns)
    return {f.__name__: f for f in named}


_LEDGER = f"""d AS (SELECT row_number() OVER () AS rid, doc_id, coalesce(text, '') AS t FROM documents),
w AS (SELECT rid, doc_id, t, regexp_extract_all(t, '{WS}') AS ws,
             list_filter(string_split(t, chr(10)), lambda x: regexp_matches(x, '{WS}')) AS ls FROM d),
win AS (SELECT rid, unnest(range(1, len(ws) - 3)) AS i, ws FROM w WHERE len(ws) > 4),
keyed AS (SELECT rid, i, ws[i] || ' ' || ws[i+1] || ' ' || ws[i+2] || ' ' || ws[i+3] || ' ' || ws[i+4] AS k FROM win),
dup AS (SELECT rid, i FROM (SELECT rid, i, count(*) OVER (PARTITION BY rid, k) AS n FROM keyed) WHERE n > 1),
cover AS (SELECT rid, count(DISTINCT p) AS n FROM (SELECT rid, unnest(range(i, i + 5)) AS p FROM dup) GROUP BY rid),
m AS (SELECT doc_id, len(ws)::BIGINT AS n_words,
             length(array_to_string(ws, ''))::BIGINT AS word_chars,
             length(regexp_replace(t, '[^#*$%&|<>]+', '', 'g'))::BIGINT AS n_symbols,
             len(ls)::BIGINT AS n_lines,
             (len(ls) - len(list_distinct(ls)))::BIGINT AS n_dup_lines,
             coalesce(c.n, 0)::BIGINT AS n_repeat_words
      FROM w LEFT JOIN cover c USING (rid)),
j AS (SELECT *, n_words < 10 OR 100 * n_repeat_words > 20 * n_words AS base_failed FROM m)"""
OP4_SQL = f"""WITH {_LEDGER}
SELECT doc_id, n_words, word_chars, n_symbols, n_dup_lines, n_repeat_words, base_failed,
       NOT (base_failed OR 10 * n_symbols > n_words OR 10 * n_dup_lines > 3 * n_lines
            OR word_chars < 2 * n_words OR word_chars > 20 * n_words) AS kept
FROM j"""
_FAILS = {"few_words": "n_words < 10", "repeated_windows": "100 * n_repeat_words > 20 * n_words", "symbols": "10 * n_symbols > n_words", "duplicate_lines": "10 * n_dup_lines > 3 * n_lines", "word_length": "word_chars < 2 * n_words OR word_chars > 20 * n_words"}
_BITS = f"{_LEDGER}, b AS (SELECT *, (" + " + ".join(f"CASE WHEN {x} THEN {1 << i} ELSE 0 END" for i, x in enumerate(_FAILS.values())) + ")::BIGINT AS fail_bits FROM m)"
LEDGER_SQL = f"WITH {_BITS} SELECT doc_id, n_words, word_chars, n_symbols, n_lines, n_dup_lines, n_repeat_words, fail_bits FROM b"
ABLATIONS_SQL = f"WITH {_BITS} " + " UNION ALL ".join(f"SELECT 'v1' AS policy, count(*) AS n, '{r}' AS rule, count(*) FILTER (fail_bits & {1 << i} <> 0) AS n_failed, count(*) FILTER (fail_bits = {1 << i}) AS n_only FROM b" for i, r in enumerate(_FAILS))
PATTERNS_SQL = f"WITH {_BITS} SELECT fail_bits, count(*) AS n_docs, sum(n_words)::BIGINT AS n_words FROM b GROUP BY 1"

_RULES = [("example.org/en/1", "example.org", "/en/1", "block"), ("example.org/es/", "example.org", "/es/", "block"), ("com/de/", "com", "/de/", "block"), ("com/fr/", "com", "/fr/", "allow"), ("org/", "org", "/", "allow")]
URL_SQL = """WITH u AS (SELECT page_id, CASE WHEN contains(url, '://') THEN substr(url, strpos(url, '://') + 3) ELSE '' END AS rest FROM pages),
h AS (SELECT page_id, translate(regexp_extract(coalesce(rest, ''), '^[^/?#]*'), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz') AS host, regexp_extract(coalesce(rest, ''), '^[^/?#]*([^?#]*)', 1) AS path FROM u)
SELECT page_id, host, path, """ + ", ".join(
    "CASE " + " ".join(f"WHEN (host = '{h}' OR ends_with(host, '.{h}')) AND starts_with(path, '{p}') THEN '{x}'" for r, h, p, v in _RULES for x in [(r, v)[i]]) + f" END AS {name}" for i, name in enumerate(("rule", "verdict"))
) + " FROM h"

OP9_SQL = f"""
WITH d AS (SELECT doc_id, source, len(regexp_extract_all(coalesce(text, ''), '{WS}'))::BIGINT AS size,
                  ('0x' || substr(md5(coalesce(doc_id::VARCHAR, 'null')), 1, 12))::BIGINT AS h FROM documents),
s AS (SELECT source, sum(size)::BIGINT AS source_size,
             [3, 1, 2][((row_number() OVER (ORDER BY source ASC NULLS LAST) - 1) % 3)::INT + 1]::BIGINT AS weight FROM d GROUP BY source),
l AS (SELECT *, 2 * source_size AS cap,
             (1.5::DOUBLE * sum(source_size) OVER () - coalesce(sum(2 * source_size) OVER o, 0))
             / (sum(weight) OVER () - coalesce(sum(weight) OVER o, 0)) AS level
      FROM s WINDOW o AS (ORDER BY (2 * source_size)::DOUBLE / weight, source ASC NULLS LAST ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING)),
t AS (SELECT *, CASE WHEN cap::DOUBLE / weight <= level THEN cap::DOUBLE
             ELSE weight * max(CASE WHEN NOT cap::DOUBLE / weight <= level THEN level END) OVER () END AS target FROM l),
r AS (SELECT source, source_size, target, CASE WHEN source_size > 0 THEN floor(target / source_size) ELSE 0 END::BIGINT AS copies FROM t),
g AS (SELECT source, h, sum(size) AS here FROM d GROUP BY source, h),
u AS (SELECT source, h, here, coalesce(sum(here) OVER (PARTITION BY source ORDER BY h ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0) AS under FROM g),
x AS (SELECT u.source, u.h, CASE WHEN under + here <= target - copies * source_size THEN 1
             WHEN under <= target - copies * source_size AND under + here - (target - copies * source_size) < (target - copies * source_size) - under THEN 1
             ELSE 0 END AS more
      FROM u JOIN r ON u.source IS NOT DISTINCT FROM r.source)
SELECT doc_id, size, source_size, target, (size * (copies + more))::BIGINT AS taken
FROM d JOIN r ON d.source IS NOT DISTINCT FROM r.source
       JOIN x ON d.source IS NOT DISTINCT FROM x.source AND d.h = x.h
"""

OP7_SQL = """
WITH v AS (SELECT vec_id, list_transform(embedding, lambda x: floor(256 * x::DOUBLE)::BIGINT) AS e FROM embeddings
           WHERE embedding IS NOT NULL AND len(embedding) > 0 AND len(list_filter(embedding, lambda x: x IS NULL OR NOT isfinite(x))) = 0),
q AS (SELECT DISTINCT vec_id, e FROM v WHERE vec_id % 50 = 0),
p AS (SELECT q.vec_id AS query_id, q.e, c.vec_id, list_sum(list_transform(list_zip(q.e, c.e), lambda z: z[1] * z[2]))::BIGINT AS score
      FROM q JOIN v c ON q.vec_id <> c.vec_id)
SELECT query_id, rank, vec_id, score FROM
  (SELECT *, (row_number() OVER (PARTITION BY query_id, e ORDER BY score DESC, vec_id))::INT AS rank FROM p) WHERE rank <= 5
"""

OP2_SQL = f"""
WITH RECURSIVE d AS (SELECT doc_id, regexp_extract_all(coalesce(text, ''), '{WS}') AS ws FROM documents),
s AS (SELECT DISTINCT doc_id, CASE WHEN len(ws) < 5 THEN array_to_string(ws, ' ') ELSE array_to_string(ws[i:i+4], ' ') END AS k
      FROM (SELECT doc_id, ws, unnest(range(1, greatest(len(ws) - 4, 1) + 1)) AS i FROM d WHERE len(ws) > 0)),
n AS (SELECT doc_id, count(*) AS n FROM s GROUP BY doc_id),
o AS (SELECT a.doc_id AS x, b.doc_id AS y, count(*) AS inter FROM s a JOIN s b ON a.k = b.k AND a.doc_id <> b.doc_id GROUP BY 1, 2),
e AS (SELECT x, y FROM o JOIN n p ON x = p.doc_id JOIN n q ON y = q.doc_id WHERE 10 * inter >= 8 * (p.n + q.n - inter)),
c AS (SELECT doc_id AS x, doc_id AS c FROM documents UNION SELECT e.y, c.c FROM c JOIN e ON e.x = c.x AND c.c < e.y)
SELECT d.doc_id, min(c.c) AS class_id, any_value(coalesce(l.n, 0))::BIGINT AS n_links
FROM d JOIN c ON c.x = d.doc_id LEFT JOIN (SELECT x, count(*) AS n FROM e GROUP BY x) l ON l.x = d.doc_id GROUP BY d.doc_id
"""


def oracle_sql() -> dict[str, str]:
    return {"op2_ngram_jaccard_join": OP2_SQL, "op4_quality_rules": OP4_SQL, "op7_exact_topk": OP7_SQL, "op9_mixing": OP9_SQL, "url_rules": URL_SQL, "quality_ledger": LEDGER_SQL, "quality_ablations": ABLATIONS_SQL, "quality_patterns": PATTERNS_SQL}
