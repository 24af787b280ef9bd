"""Registered queries of the blocking engine and the DuckDB SQL that states the same."""

from __future__ import annotations

from collections.abc import Callable
from functools import partial, reduce

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from erblock.functions.cut import checkpoint, new_path, written
from erblock.operators import around, attr_clustering, blocks, groundtruth, iterative, measures, missed, pairs, token_blocking, uri_infix
from erblock.plans import workloads
from erblock.sources import ingest, views
from erblock.streaming import incremental

ALL = tuple(views.COLLECTIONS)
URIS = tuple(c for c in ALL if views.COLLECTIONS[c].uris)
WORD = r"[\p{L}\p{N}]+"
PART = "[/#?&=:.]*[^/#?&=:.]+"

# ---------------------------------------------------------------- SQL pieces


def _descriptions(name: str, task: str) -> str:
    return f"d AS (SELECT DISTINCT * FROM ({views.descriptions_sql(name, task)}) y), t AS ({views.truth_sql(name, task)})"


TOKENS = f"tok AS (SELECT DISTINCT collection, entity_id, attribute, kind, unnest(regexp_extract_all(lower(value), '{WORD}')) AS token FROM d)"
TOKEN_POSTINGS = f"{TOKENS}, p AS (SELECT DISTINCT token AS block_key, collection, entity_id FROM tok)"

GRAMS = """w AS (SELECT DISTINCT collection, attribute, token FROM tok),
g AS (SELECT DISTINCT collection, attribute, substr(token, i, 3) AS gram FROM (SELECT *, unnest(range(1, greatest(length(token) - 2, 1) + 1)) AS i FROM w))"""
WORD_GRAMS = "g AS (SELECT DISTINCT collection, attribute, token AS gram FROM tok)"
SIMS = """gs AS (SELECT collection, attribute, count(*) AS n FROM g GROUP BY ALL),
sim AS (SELECT l.attribute AS left_attribute, r.attribute AS right_attribute, count(*) AS inter,
               count(*) / (any_value(ls.n) + any_value(rs.n) - count(*)) AS sim
        FROM g l JOIN g r ON l.gram = r.gram AND l.collection = 'L' AND r.collection = 'R'
        JOIN gs ls ON ls.collection = 'L' AND ls.attribute = l.attribute
        JOIN gs rs ON rs.collection = 'R' AND rs.attribute = r.attribute GROUP BY 1, 2)"""
BEST = """best AS (SELECT collection, attribute, best, sim FROM (
  SELECT *, row_number() OVER (PARTITION BY collection, attribute ORDER BY sim DESC, best) AS r FROM (
    SELECT 'L' AS collection, left_attribute AS attribute, right_attribute AS best, sim FROM sim
    UNION ALL SELECT 'R', right_attribute, left_attribute, sim FROM sim) z WHERE sim > 0) z WHERE r = 1)"""
CLUSTERS = """ed AS (SELECT CASE WHEN collection = 'L' THEN 'L|' || attribute ELSE 'L|' || best END AS a,
                     CASE WHEN collection = 'L' THEN 'R|' || best ELSE 'R|' || attribute END AS b FROM best),
e2 AS (SELECT a, b FROM ed UNION SELECT b, a FROM ed),
reach AS (SELECT a AS n, a AS c FROM e2 UNION SELECT e2.b, reach.c FROM reach JOIN e2 ON e2.a = reach.n),
cl AS (SELECT substr(n, 1, 1) AS collection, substr(n, 3) AS attribute, min(c) AS cluster_id FROM reach GROUP BY n)"""
ATTRIBUTE_POSTINGS = f"{TOKENS}, {GRAMS}, {SIMS}, {BEST}, {CLUSTERS}, p AS (SELECT DISTINCT cluster_id || chr(1) || token AS block_key, collection, entity_id FROM tok JOIN cl USING (collection, attribute))"


def _uri_sql(rule: str = "support", suffix: bool = True) -> str:
    first = 0 if rule == "allow_empty" else 1
    least = "WHERE n_next >= 3" if rule == "support" else ""
    sql = f"""un AS (SELECT DISTINCT collection, entity_id, uri FROM (SELECT collection, entity_id, entity_id AS uri FROM d UNION ALL SELECT collection, entity_id, value FROM d WHERE kind = 'uri') z
  WHERE regexp_matches(uri, '^[A-Za-z][A-Za-z0-9+.-]*://')),
pa AS (SELECT uri, parts, parts[2] AS domain, least(len(list_filter(parts, lambda x, i: i < 3 OR starts_with(x, '.'))), len(parts) - 1) AS host
       FROM (SELECT uri, regexp_extract_all(uri, '{PART}') AS parts FROM (SELECT DISTINCT uri FROM un)) WHERE len(parts) > 1),
pl AS (SELECT *, array_to_string(parts[1:k], '') AS prefix FROM (SELECT *, unnest(range(1, len(parts))) AS k FROM pa)),
pn AS (SELECT domain, prefix, count(DISTINCT parts[k + 1]) AS n_next FROM pl GROUP BY 1, 2),
pb AS (SELECT * FROM (SELECT pl.*, n_next, row_number() OVER (PARTITION BY uri ORDER BY n_next DESC, k DESC) AS r FROM pl JOIN pn USING (domain, prefix)) WHERE r = 1),
st AS (SELECT uri, domain, array_to_string(parts[1:c], '') AS prefix, parts[c + 1:] AS rest FROM (SELECT *, CASE WHEN n_next > 1 THEN k ELSE host END AS c FROM pb))"""
    if not suffix:
        return sql + ", inf AS (SELECT uri, domain, prefix, array_to_string(rest, '') AS infix, '' AS suffix FROM st)"
    return (
        sql
        + f""",
rv AS (SELECT uri, list_reverse(rest) AS parts, rest FROM st),
rl AS (SELECT *, array_to_string(parts[1:k], '') AS prefix FROM (SELECT *, unnest(range({first}, len(parts))) AS k FROM rv)),
rn AS (SELECT * FROM (SELECT prefix, count(DISTINCT parts[k + 1]) AS n_next FROM rl GROUP BY 1) {least}),
rb AS (SELECT * FROM (SELECT uri, k, row_number() OVER (PARTITION BY uri ORDER BY n_next DESC, k DESC) AS r FROM rl JOIN rn USING (prefix)) WHERE r = 1),
inf AS (SELECT st.uri, domain, prefix, array_to_string(rest[1:len(rest) - coalesce(k, 0)], '') AS infix, array_to_string(rest[len(rest) - coalesce(k, 0) + 1:], '') AS suffix FROM st LEFT JOIN rb ON st.uri = rb.uri)"""
    )


def _uri_postings(rule: str = "support", suffix: bool = True) -> str:
    return f"""{TOKENS}, {_uri_sql(rule, suffix)},
p AS (SELECT DISTINCT infix AS block_key, collection, entity_id FROM un JOIN inf ON un.uri = inf.uri WHERE infix <> ''
      UNION SELECT DISTINCT token, collection, entity_id FROM tok WHERE kind = 'literal')"""


POSTINGS = {"token": TOKEN_POSTINGS, "attribute": ATTRIBUTE_POSTINGS, "uri": _uri_postings(), "uri_literal": _uri_postings("literal"), "uri_no_suffix": _uri_postings(suffix=False)}


def _summary(task: str) -> str:
    if task == "clean":
        return "s AS (SELECT * FROM (SELECT block_key, count(*) FILTER (collection <> 'R') AS n_left, count(*) FILTER (collection = 'R') AS n_right, n_left::HUGEINT * n_right AS comparisons FROM p GROUP BY 1) WHERE n_left > 0 AND n_right > 0)"
    return "s AS (SELECT * FROM (SELECT block_key, count(*) AS n_left, 0::BIGINT AS n_right, n_left::HUGEINT * (n_left - 1) // 2 AS comparisons FROM p GROUP BY 1) WHERE n_left > 1)"


def _pairs(task: str) -> str:
    cond = "a.collection = 'L' AND b.collection = 'R'" if task == "clean" else "a.entity_id < b.entity_id"
    return f"pr AS (SELECT DISTINCT a.entity_id AS left_id, b.entity_id AS right_id FROM p a JOIN p b ON a.block_key = b.block_key AND {cond})"


HITS = """ka AS MATERIALIZED (SELECT t.left_id, t.right_id, a.block_key FROM t JOIN p a ON a.entity_id = t.left_id),
hk AS MATERIALIZED (SELECT DISTINCT ka.left_id, ka.right_id FROM ka JOIN p b ON b.entity_id = ka.right_id AND b.block_key = ka.block_key),
h AS (SELECT t.left_id, t.right_id, t.link_type, hk.left_id IS NOT NULL AS hit FROM t LEFT JOIN hk ON t.left_id = hk.left_id AND t.right_id = hk.right_id)"""


def _quality_core(task: str, with_pairs: bool) -> str:
    n = "SELECT count(*) FILTER (collection <> 'R') AS nl, count(*) FILTER (collection = 'R') AS nr FROM (SELECT DISTINCT collection, entity_id FROM d)"
    z = "nl::HUGEINT * nr" if task == "clean" else "(nl + nr)::HUGEINT * (nl + nr - 1) // 2"
    dp = "(SELECT count(*) FROM pr)" if with_pairs else "NULL::BIGINT"
    return f"""q AS (SELECT (SELECT count(*) FROM s) AS blocks, (SELECT coalesce(sum(comparisons), 0)::HUGEINT FROM s) AS comparisons, {dp} AS distinct_pairs,
  (SELECT {z} FROM ({n})) AS exhaustive, (SELECT count(*) FILTER (hit) FROM h) AS tp, (SELECT count(*) FILTER (NOT hit) FROM h) AS fn),
q2 AS (SELECT *, greatest(distinct_pairs - tp, 0) AS fp0, tp::DOUBLE / nullif(tp + fn, 0) AS r0, tp::DOUBLE / nullif(distinct_pairs, 0) AS p0, tp::DOUBLE / nullif(comparisons, 0)::DOUBLE AS pr0, 1 - comparisons::DOUBLE / nullif(exhaustive, 0)::DOUBLE AS rr0 FROM q),
q3 AS (SELECT blocks, comparisons::VARCHAR AS comparisons, distinct_pairs, exhaustive::VARCHAR AS exhaustive, tp, fn, CASE WHEN distinct_pairs IS NOT NULL THEN fp0::VARCHAR END AS fp,
  CASE WHEN distinct_pairs IS NOT NULL THEN (exhaustive - tp - fp0 - fn)::VARCHAR END AS tn, round(r0, 10) AS recall, round(p0, 10) AS precision, round(pr0, 10) AS precision_raw,
  round(CASE WHEN p0 = 0 AND r0 = 0 THEN 0 ELSE 2 * p0 * r0 / nullif(p0 + r0, 0) END, 10) AS f, round(rr0, 10) AS rr,
  round(CASE WHEN rr0 >= 0 THEN CASE WHEN rr0 = 0 AND r0 = 0 THEN 0 ELSE 2 * rr0 * r0 / nullif(rr0 + r0, 0) END END, 10) AS h3r FROM q2)"""


def _quality_sql(collection: str, method: str, task: str, with_pairs: bool = True) -> str:
    """One row of all measures, as a parenthesised subquery."""
    more = f"{_pairs(task)}, " if with_pairs else ""
    head = f"WITH RECURSIVE {_descriptions(collection, task)}, {POSTINGS[method]}, {_summary(task)}, {more}{HITS}, {_quality_core(task, with_pairs)}"
    return f"({head} SELECT '{method}' AS method, '{collection}' AS collection, '{task}' AS task, q3.* FROM q3)"


def _both_tasks(collection: str, method: str) -> str:
    return " UNION ALL ".join(f"SELECT * FROM {_quality_sql(collection, method, k)} z_{k}" for k in ("clean", "dirty") if workloads.applies(method, collection, k))


def _matrix_sql(collections: tuple[str, ...], methods: tuple[str, ...] = ("token", "attribute", "uri", "uri_literal")) -> str:
    rows = []
    for c in collections:
        for m in methods:
            for k in ("clean", "dirty"):
                if workloads.applies(m, c, k):
                    rows.append(
                        f"SELECT method, collection, '{views.COLLECTIONS[c].role}' AS role, task, blocks, comparisons, distinct_pairs, tp, fn, recall, precision, precision_raw, f, rr, h3r, round(comparisons::DOUBLE / nullif(distinct_pairs, 0), 8) AS redundancy FROM {_quality_sql(c, m, k)} z{len(rows)}"
                    )
    return " UNION ALL ".join(rows)


# ---------------------------------------------------------------- queries

Query = Callable[[SparkSession, str], DataFrame]
QUERIES: dict[str, Query] = {}
ORACLE: dict[str, str] = {}


def _add(name: str, query: Query, sql: str | None = None) -> None:
    QUERIES[name] = query
    if sql is not None:
        ORACLE[name] = sql


def _on(collection: str, task: str, make: Callable[[DataFrame, DataFrame], DataFrame]) -> Query:
    return lambda spark, sf_dir: make(*views.load(spark, sf_dir, collection, task))


def _with(collection: str, task: str, ctes: str, final: str) -> str:
    return f"WITH RECURSIVE {_descriptions(collection, task)}{', ' if ctes else ''}{ctes} {final}"


def _mapped_clusters(d: DataFrame) -> DataFrame:
    return attr_clustering.find_clusters(d)


def _over(task: str, make: Callable[[DataFrame, DataFrame], DataFrame], collections: tuple[str, ...] = ALL, one_by_one: bool = False) -> Query:
    """The same of every collection, named; one by one: a collection's work is done and off the disk before the next."""

    def run(spark: SparkSession, sf_dir: str) -> DataFrame:
        of = lambda c: make(*views.load(spark, sf_dir, c, task)).withColumn("name", F.lit(c))
        return reduce(DataFrame.unionByName, [written(of(c).coalesce(1), "zstd") if one_by_one else of(c) for c in collections])

    return run


def _over_sql(task: str, ctes: str, final: str, collections: tuple[str, ...] = ALL) -> str:
    return " UNION ALL ".join(f"SELECT '{c}' AS name, z_{c}.* FROM ({_with(c, task, ctes, final)}) z_{c}" for c in collections)


# Token blocking
_add("tb_postings", _on("d6", "dirty", lambda d, t: token_blocking.build(d)), _with("d6", "dirty", TOKEN_POSTINGS, "SELECT * FROM p"))
for _task, _c in (("dirty", "d6"), ("clean", "d5")):
    _add(f"tb_blocks_{_task}", _on(_c, _task, lambda d, t, k=_task: blocks.summary(token_blocking.build(d), k).withColumn("comparisons", F.col("comparisons").cast("string"))), _with(_c, _task, f"{TOKEN_POSTINGS}, {_summary(_task)}", "SELECT block_key, n_left, n_right, comparisons::VARCHAR AS comparisons FROM s"))
_add("tb_comparisons", _on("d6", "dirty", lambda d, t: blocks.summary(token_blocking.build(d), "dirty").agg(F.count(F.lit(1)).alias("blocks"), F.sum("comparisons").cast("string").alias("comparisons"))), _with("d6", "dirty", f"{TOKEN_POSTINGS}, {_summary('dirty')}", "SELECT count(*) AS blocks, sum(comparisons)::HUGEINT::VARCHAR AS comparisons FROM s"))
for _m in ("exact", "min_key"):
    _add(f"tb_pairs_{'distinct' if _m == 'exact' else _m}", _on("d5", "clean", lambda d, t, m=_m: pairs.distinct(token_blocking.build(d), "clean", m)), _with("d5", "clean", f"{TOKEN_POSTINGS}, {_pairs('clean')}", "SELECT * FROM pr"))
_add("tb_pairs_tiled", _on("d5", "clean", lambda d, t: pairs.tiled(token_blocking.build(d), "clean", 200).groupBy("left_id").agg(F.count(F.lit(1)).alias("n"))), _with("d5", "clean", TOKEN_POSTINGS, "SELECT a.entity_id AS left_id, count(*) AS n FROM p a JOIN p b ON a.block_key = b.block_key AND a.collection = 'L' AND b.collection = 'R' GROUP BY 1"))
_add("tb_pairs_sketch", _on("d5", "clean", lambda d, t: pairs.sketch(token_blocking.build(d), "clean")))
_ESTIMATE = """u AS (SELECT block_key, collection, entity_id FROM p JOIN s USING (block_key)),
dr AS (SELECT DISTINCT block_key FROM s WHERE ('0x' || substr(md5(block_key || '|42'), 1, 8))::BIGINT < 1073741824),
rp AS (SELECT a.entity_id AS l, b.entity_id AS r, count(*) AS here FROM u a JOIN u b ON a.block_key = b.block_key AND a.entity_id < b.entity_id WHERE a.block_key IN (SELECT block_key FROM dr) GROUP BY 1, 2),
cm AS (SELECT l, r, any_value(here) AS here, count(*) AS m FROM rp JOIN u a ON a.entity_id = l JOIN u b ON b.entity_id = r AND b.block_key = a.block_key GROUP BY 1, 2)"""
_add("tb_pairs_estimate", _on("d2", "dirty", lambda d, t: pairs.estimate(token_blocking.build(d), "dirty")), _with("d2", "dirty", f"{TOKEN_POSTINGS}, {_summary('dirty')}, {_ESTIMATE}", "SELECT (SELECT count(*) FROM dr) AS sampled_blocks, (SELECT coalesce(sum(here), 0)::BIGINT FROM cm) AS sampled_pairs, (SELECT coalesce(round(sum(here / m::DOUBLE) / 0.25::DOUBLE, 4), 0) FROM cm) AS distinct_pairs"))
_add("tb_pairs_count", _over("dirty", lambda d, t: pairs.count(token_blocking.build(d), "dirty"), ("d1", "d2", "d5", "d7")), _over_sql("dirty", f"{TOKEN_POSTINGS}, {_pairs('dirty')}", "SELECT count(*) AS distinct_pairs FROM pr", ("d1", "d2", "d5", "d7")))
_add("tb_purged", _on("d6", "dirty", lambda d, t: blocks.summary(blocks.purge(blocks.hash_keys(token_blocking.build(d)), "dirty", 10_000), "dirty").agg(F.count(F.lit(1)).alias("blocks"), F.sum("comparisons").cast("string").alias("comparisons"))), _with("d6", "dirty", f"{TOKEN_POSTINGS}, {_summary('dirty')}", "SELECT count(*) AS blocks, sum(comparisons)::HUGEINT::VARCHAR AS comparisons FROM s WHERE comparisons <= 10000"))
for _c in ALL:
    _add(f"tb_quality_{_c}", partial(lambda spark, sf, c, m: workloads.quality(spark, sf, c, m), c=_c, m="token"), _both_tasks(_c, "token"))

for _c in views.EXTRA:
    _add(f"tb_quality_{_c}", lambda spark, sf, c=_c: workloads.quality(spark, sf, c, "token", ("clean",)), f"SELECT * FROM {_quality_sql(_c, 'token', 'clean')} z")

# Attribute clustering
_add("ac_grams", _on("d1", "clean", lambda d, t: attr_clustering.grams(d)), _with("d1", "clean", f"{TOKENS}, {GRAMS}", "SELECT * FROM g"))
_SIM = "SELECT left_attribute, right_attribute, inter, sim FROM sim"
_add("ac_similarity", _on("d2", "clean", lambda d, t: attr_clustering.similarities(attr_clustering.grams(d))), _with("d2", "clean", f"{TOKENS}, {GRAMS}, {SIMS}", _SIM))
_add("ac_tiled", _on("d2", "clean", lambda d, t: attr_clustering.tiled_similarities(attr_clustering.grams(d))), _with("d2", "clean", f"{TOKENS}, {GRAMS}, {SIMS}", _SIM))
_add("ac_similarity_word", _on("d2", "clean", lambda d, t: attr_clustering.similarities(attr_clustering.grams(d, unit="word"))), _with("d2", "clean", f"{TOKENS}, {WORD_GRAMS}, {SIMS}", _SIM))
_add("ac_minhash", _on("d2", "clean", lambda d, t: attr_clustering.minhash_similarities(attr_clustering.grams(d))))
_add("ac_best_match", _on("d2", "clean", lambda d, t: attr_clustering.best_match(attr_clustering.similarities(attr_clustering.grams(d)))), _with("d2", "clean", f"{TOKENS}, {GRAMS}, {SIMS}, {BEST}", "SELECT * FROM best"))
_add("ac_clusters", _on("d2", "clean", lambda d, t: _mapped_clusters(d)), _with("d2", "clean", f"{TOKENS}, {GRAMS}, {SIMS}, {BEST}, {CLUSTERS}", "SELECT * FROM cl"))
CLUSTER_STATS = "SELECT count(*) AS n_clusters, median(k)::DOUBLE AS median_attributes FROM (SELECT count(*) AS k FROM cl GROUP BY cluster_id)"
_add("ac_cluster_stats", _over("clean", lambda d, t: measures.cluster_stats(_mapped_clusters(d))), _over_sql("clean", f"{TOKENS}, {GRAMS}, {SIMS}, {BEST}, {CLUSTERS}", CLUSTER_STATS))
_UNMATCHED = f"{TOKENS}, {GRAMS}, {SIMS}, {BEST}, {CLUSTERS}, aa AS (SELECT DISTINCT collection, attribute FROM d)"
_add("ac_clusters_glue", _on("d2", "clean", lambda d, t: attr_clustering.find_clusters(d, unmatched="glue")), _with("d2", "clean", _UNMATCHED, "SELECT * FROM cl UNION ALL SELECT collection, attribute, 'rest' FROM aa WHERE NOT EXISTS (SELECT 1 FROM cl WHERE cl.collection = aa.collection AND cl.attribute = aa.attribute)"))
_add("ac_best_match_ties", _on("d4", "clean", lambda d, t: attr_clustering.best_match(attr_clustering.similarities(attr_clustering.grams(d)), ties="all")), _with("d4", "clean", f"{TOKENS}, {GRAMS}, {SIMS}", """SELECT collection, attribute, best, sim FROM (SELECT *, rank() OVER (PARTITION BY collection, attribute ORDER BY sim DESC) AS r FROM (
  SELECT 'L' AS collection, left_attribute AS attribute, right_attribute AS best, sim FROM sim UNION ALL SELECT 'R', right_attribute, left_attribute, sim FROM sim) z WHERE sim > 0) z WHERE r = 1"""))
_add("ac_postings", _on("d2", "clean", lambda d, t: attr_clustering.build(d)), _with("d2", "clean", ATTRIBUTE_POSTINGS, "SELECT * FROM p"))
for _c in ALL:
    _add(f"ac_quality_{_c}", partial(lambda spark, sf, c, m: workloads.quality(spark, sf, c, m), c=_c, m="attribute"), _both_tasks(_c, "attribute"))

# URI blocking
_add("pi_prefix", _on("d7", "clean", lambda d, t: uri_infix.strip_prefix(uri_infix.uris(d)).select("uri", "domain", "prefix", F.array_join("rest", "").alias("rest"))), _with("d7", "clean", _uri_sql(), "SELECT uri, domain, prefix, array_to_string(rest, '') AS rest FROM st"))
_add("pi_infix", _on("d7", "clean", lambda d, t: uri_infix.strip_suffix(uri_infix.strip_prefix(uri_infix.uris(d)))), _with("d7", "clean", _uri_sql(), "SELECT * FROM inf"))
_add("pi_no_suffix", _on("d7", "clean", lambda d, t: uri_infix.build(d, suffix=False)), _with("d7", "clean", _uri_postings(suffix=False), "SELECT * FROM p"))


def _rules(d: DataFrame, t: DataFrame) -> DataFrame:
    st = uri_infix.strip_prefix(uri_infix.uris(d))
    parts = [uri_infix.strip_suffix(st, suffix_rule=r).agg(F.lit(r).alias("rule"), F.count_if(F.col("suffix") != "").alias("with_suffix"), F.count_distinct("infix").alias("infixes")) for r in ("literal", "allow_empty", "support")]
    return parts[0].unionByName(parts[1]).unionByName(parts[2])


_add("pi_suffix_rules", _on("d7", "clean", _rules), " UNION ALL ".join(f"SELECT * FROM ({_with('d7', 'clean', _uri_sql(r), f'''SELECT '{r}' AS rule, count(*) FILTER (suffix <> '') AS with_suffix, count(DISTINCT infix) AS infixes FROM inf''')}) z_{r}" for r in ("literal", "allow_empty", "support")))
_add("pi_suffix_domain", _on("d7", "clean", lambda d, t: uri_infix.strip_suffix(uri_infix.strip_prefix(uri_infix.uris(d)), suffix_scope="domain")), _with("d7", "clean", _uri_sql().replace("SELECT prefix, count(DISTINCT parts[k + 1]) AS n_next FROM rl GROUP BY 1", "SELECT domain, prefix, count(DISTINCT parts[k + 1]) AS n_next FROM rl GROUP BY 1, 2").replace("SELECT uri, list_reverse(rest) AS parts, rest FROM st", "SELECT uri, domain, list_reverse(rest) AS parts, rest FROM st").replace("FROM rl JOIN rn USING (prefix)", "FROM rl JOIN rn USING (domain, prefix)"), "SELECT * FROM inf"))
_add("pi_prefix_shortest", _on("d7", "clean", lambda d, t: uri_infix.strip_prefix(uri_infix.uris(d), ties="shortest").select("uri", "domain", "prefix", F.array_join("rest", "").alias("rest"))), _with("d7", "clean", _uri_sql().replace("ORDER BY n_next DESC, k DESC) AS r FROM pl", "ORDER BY n_next DESC, k) AS r FROM pl"), "SELECT uri, domain, prefix, array_to_string(rest, '') AS rest FROM st"))
_add("pi_two_key_spaces", _on("d4", "clean", lambda d, t: uri_infix.build(d, shared_keys=False)), _with("d4", "clean", f"{TOKENS}, {_uri_sql()}", "SELECT DISTINCT 'i:' || infix AS block_key, collection, entity_id FROM un JOIN inf ON un.uri = inf.uri WHERE infix <> '' UNION SELECT DISTINCT 't:' || token, collection, entity_id FROM tok WHERE kind = 'literal'"))
_add("pi_postings", _on("d4", "clean", lambda d, t: uri_infix.build(d)), _with("d4", "clean", _uri_postings(), "SELECT * FROM p"))
_add("pi_applicable", _on("d6", "clean", lambda d, t: uri_infix.applicable(d)), _with("d6", "clean", "", "SELECT share, share >= 0.5 AS applicable FROM (SELECT avg(regexp_matches(entity_id, '^[A-Za-z][A-Za-z0-9+.-]*://')::INT) AS share FROM (SELECT DISTINCT collection, entity_id FROM d))"))
for _c in URIS:
    _add(f"pi_quality_{_c}", partial(lambda spark, sf, c, m: workloads.quality(spark, sf, c, m), c=_c, m="uri"), _both_tasks(_c, "uri"))
_add("pi_quality_literal_d4", lambda spark, sf: workloads.quality(spark, sf, "d4", "uri_literal"), _both_tasks("d4", "uri_literal"))


# Iterative blocking
def _tokens_of(d: DataFrame) -> DataFrame:
    return token_blocking.description_tokens(d).select("entity_id", "token").distinct()


def _it_oracle(d: DataFrame, t: DataFrame) -> DataFrame:
    return iterative.run_rounds(token_blocking.build(d), iterative.oracle(t)).entity_map


def _it_jaccard(d: DataFrame, t: DataFrame) -> DataFrame:
    return iterative.run_rounds(token_blocking.build(d), iterative.jaccard(_tokens_of(d), 0.8)).entity_map


def _it_comparisons(d: DataFrame, t: DataFrame) -> DataFrame:
    p, t = written(token_blocking.bags(d), "zstd"), written(t, "zstd")
    return iterative.savings(iterative.run_rounds(p, iterative.oracle(t)), p)


def _it_gain(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Recall of token blocking and after iterative blocking of its blocks, where a collection has duplicates or none."""
    out = []
    for c, task in (("d5", "dirty"), ("d2", "dirty"), ("d6", "clean")):
        d, t = views.load(spark, sf_dir, c, task)
        p = written(blocks.bags(token_blocking.build(d)), "zstd")
        out.append(iterative.gain(p, t, iterative.run_rounds(p, iterative.oracle(t), sides=task == "clean")).withColumns({"name": F.lit(c), "task": F.lit(task)}))
    return reduce(DataFrame.unionByName, out)


_CLOSURE = """e2 AS (SELECT left_id AS a, right_id AS b FROM t UNION SELECT right_id, left_id FROM t),
reach AS (SELECT DISTINCT entity_id AS n, entity_id AS c FROM p UNION SELECT e2.b, reach.c FROM reach JOIN e2 ON e2.a = reach.n AND reach.c < e2.b)"""
_add("it_rounds_oracle", _on("d5", "dirty", _it_oracle))
_add("it_rounds_oracle_d6", _on("d6", "dirty", _it_oracle), _with("d6", "dirty", f"{TOKEN_POSTINGS}, {_CLOSURE}", "SELECT n AS entity_id, min(c) AS rep_id FROM reach GROUP BY n"))
_add("it_rounds_jaccard", _on("d5", "dirty", _it_jaccard))
_add("it_comparisons", _on("d6", "dirty", _it_comparisons))
_add("it_gain", _it_gain)
_add("it_sequential", _on("d5", "dirty", lambda d, t: iterative.run_sequential(token_blocking.build(d), _tokens_of(d), truth=t)))
_add("it_first_pass", _on("d5", "dirty", lambda d, t: iterative.run_sequential(token_blocking.build(d), _tokens_of(d), truth=t, max_passes=1)))
_add("it_merged", _on("d6", "dirty", lambda d, t: iterative.merge(d, iterative.run_rounds(token_blocking.build(d), iterative.oracle(t)).entity_map).groupBy("entity_id").agg(F.count(F.lit(1)).alias("n"))), _with("d6", "dirty", f"{TOKEN_POSTINGS}, {_CLOSURE}, mp AS (SELECT n AS entity_id, min(c) AS rep_id FROM reach GROUP BY n)", "SELECT entity_id, count(*) AS n FROM (SELECT DISTINCT collection, coalesce(rep_id, d.entity_id) AS entity_id, attribute, value, kind FROM d LEFT JOIN mp ON mp.entity_id = d.entity_id) GROUP BY 1"))


# Descriptive statistics
DUPLICATES = """du AS (SELECT 'L' AS collection, (SELECT coalesce(sum(k * (k - 1) // 2), 0)::BIGINT FROM (SELECT count(*) AS k FROM (SELECT DISTINCT left_id, right_id FROM t) GROUP BY right_id)) AS duplicates
UNION ALL SELECT 'R', (SELECT coalesce(sum(k * (k - 1) // 2), 0)::BIGINT FROM (SELECT count(*) AS k FROM (SELECT DISTINCT left_id, right_id FROM t) GROUP BY left_id)))"""
CHARACTERISTICS = """SELECT *, round(triples::DOUBLE / descriptions, 8) AS pairs_per_description, round(attributes::DOUBLE / nullif(types, 0), 8) AS attributes_per_type FROM (
SELECT collection, count(*) AS triples, count(DISTINCT entity_id) AS descriptions, count(DISTINCT attribute) AS attributes, count(DISTINCT CASE WHEN attribute = 'type' THEN value END) AS types FROM dd GROUP BY collection) z JOIN du USING (collection)"""


def _raw(name: str) -> str:
    return f"dd AS ({views.descriptions_sql(name, 'clean')})"


_add("ds_characteristics", _over("clean", measures.characteristics), " UNION ALL ".join(f"SELECT '{c}' AS name, z_{c}.* FROM (WITH {_descriptions(c, 'clean')}, {_raw(c)}, {DUPLICATES} {CHARACTERISTICS}) z_{c}" for c in ALL))
_VIEW = "SELECT count(*) AS triples, count(DISTINCT entity_id) AS descriptions, count(DISTINCT attribute) AS attributes, round(count(*)::DOUBLE / count(DISTINCT entity_id), 8) AS pairs_per_description"


def _views(spark: SparkSession, sf_dir: str) -> DataFrame:
    views.register(spark, sf_dir)
    out = [measures.characteristics(spark.sql(f"SELECT '{n}' AS collection, x.* FROM ({v}) x WHERE value IS NOT NULL")) for n, v in views.KB.items()]
    return reduce(DataFrame.unionByName, out).select(F.col("collection").alias("name"), "triples", "descriptions", "attributes", "pairs_per_description")


_add("ds_views", _views, " UNION ALL ".join(f"SELECT '{n}' AS name, z_{n}.* FROM ({_VIEW} FROM ({v}) x WHERE value IS NOT NULL) z_{n}" for n, v in views.KB.items()))
COMBINED = """SELECT nl AS n_left, nr AS n_right, triples, attributes, types, round(triples::DOUBLE / (nl + nr), 8) AS pairs_per_description, matches, matches + dup AS matches_with_duplicates,
(nl::HUGEINT * nr)::VARCHAR AS clean, ((nl + nr)::HUGEINT * (nl + nr - 1) // 2)::VARCHAR AS dirty,
round(matches::DOUBLE / nullif(nl::DOUBLE * nr - matches, 0), 12) AS ratio_clean, round((matches + dup)::DOUBLE / nullif((nl + nr)::DOUBLE * (nl + nr - 1) / 2 - (matches + dup), 0), 12) AS ratio_dirty
FROM (SELECT count(DISTINCT entity_id) FILTER (collection = 'L') AS nl, count(DISTINCT entity_id) FILTER (collection = 'R') AS nr, count(*) AS triples, count(DISTINCT collection || '|' || attribute) AS attributes,
  count(DISTINCT CASE WHEN attribute = 'type' THEN collection || '|' || value END) AS types, (SELECT count(*) FROM (SELECT DISTINCT left_id, right_id FROM t)) AS matches, (SELECT sum(duplicates)::BIGINT FROM du) AS dup FROM dd)"""
_add("ds_collection", _over("clean", measures.combined), " UNION ALL ".join(f"SELECT '{c}' AS name, z_{c}.* FROM (WITH {_descriptions(c, 'clean')}, {_raw(c)}, {DUPLICATES} {COMBINED}) z_{c}" for c in ALL))
COMMON = f"""{TOKENS}, tk AS (SELECT DISTINCT collection, entity_id, '' AS cluster_id, token FROM tok),
sh AS (SELECT cluster_id, token FROM tk GROUP BY 1, 2 HAVING count(DISTINCT collection) > 1),
cn AS (SELECT collection, entity_id, count(*) AS n FROM tk JOIN sh USING (cluster_id, token) GROUP BY 1, 2),
ct AS (SELECT collection, entity_id, coalesce(n, 0) AS n FROM (SELECT DISTINCT collection, entity_id FROM d) LEFT JOIN cn USING (collection, entity_id))"""
COMMON_CLUSTER = f"{TOKENS}, {GRAMS}, {SIMS}, {BEST}, {CLUSTERS}, " + COMMON.split(", tk AS", 1)[0].replace(TOKENS, "").strip() + "tk AS" + COMMON.split("tk AS", 1)[1].replace("'' AS cluster_id, token FROM tok)", "cluster_id, token FROM tok JOIN cl USING (collection, attribute))")
for _kind, _ctes, _cluster in (("common_tokens", COMMON, False), ("cluster_tokens", COMMON_CLUSTER, True)):
    _make = lambda d, cl=_cluster: measures.common_tokens(d, _mapped_clusters(d) if cl else None)
    _add(f"ds_{_kind}_hist", _over("clean", lambda d, t, m=_make: measures.histogram(m(d)), one_by_one=True), _over_sql("clean", _ctes, "SELECT n, count(*) AS descriptions FROM ct GROUP BY n"))
    _add(f"ds_{_kind}_median", _over("clean", lambda d, t, m=_make: measures.median_of(m(d)), one_by_one=True), _over_sql("clean", _ctes, "SELECT median(n)::DOUBLE AS median FROM ct"))


def _bands(d: DataFrame, t: DataFrame) -> DataFrame:
    counts = written(measures.histogram(measures.common_tokens(d)).coalesce(1), "zstd")
    return reduce(DataFrame.unionByName, [measures.band_share(counts, lo, hi).withColumn("band", F.lit(f"{lo}-{hi}")) for lo, hi in ((0, 10), (2, 4))])


_add("ds_band_share", _over("clean", _bands), _over_sql("clean", COMMON, " UNION ALL ".join(f"SELECT '{lo}-{hi}' AS band, round(count(*) FILTER (n BETWEEN {lo} AND {hi}) / count(*)::DOUBLE, 10) AS share FROM ct" for lo, hi in ((0, 10), (2, 4)))))

# Missed matches, structure, relations
EDGES = "eg AS (SELECT DISTINCT x.entity_id AS src_id, x.value AS dst_id FROM d x JOIN (SELECT DISTINCT entity_id FROM d) y ON x.value = y.entity_id WHERE x.kind = 'uri' AND x.entity_id <> x.value)"
SYM = "tt AS (SELECT left_id AS x, right_id AS y FROM t UNION SELECT right_id, left_id FROM t)"
REPORT = f"""{EDGES}, {SYM}, {HITS}, fn AS (SELECT DISTINCT left_id, right_id FROM h WHERE NOT hit), tp AS (SELECT DISTINCT left_id, right_id FROM h WHERE hit),
lost AS (SELECT left_id AS id FROM fn UNION SELECT right_id FROM fn), rc AS (SELECT * FROM eg WHERE src_id IN (SELECT id FROM lost)),
ps AS (SELECT left_id AS x, right_id AS y FROM tp UNION SELECT right_id, left_id FROM tp),
mn AS (SELECT DISTINCT fn.left_id, fn.right_id FROM fn JOIN eg a ON a.src_id = fn.left_id JOIN tt ON tt.x = a.dst_id JOIN eg b ON b.src_id = fn.right_id AND b.dst_id = tt.y),
cm AS (SELECT DISTINCT fn.left_id, fn.right_id FROM fn JOIN ps a ON a.x = fn.left_id JOIN ps b ON b.x = fn.right_id AND b.y = a.y),
nf AS (SELECT count(*) AS n FROM fn), nl AS (SELECT count(*) AS n FROM lost),
rp AS (SELECT 'missed_pairs' AS measure, (SELECT n FROM nf) AS numerator, (SELECT n FROM nf) AS denominator
 UNION ALL SELECT 'descriptions_with_neighbours', (SELECT count(DISTINCT src_id) FROM rc), (SELECT n FROM nl)
 UNION ALL SELECT 'descriptions_with_neighbours_in_truth', (SELECT count(DISTINCT src_id) FROM rc WHERE dst_id IN (SELECT x FROM tt)), (SELECT n FROM nl)
 UNION ALL SELECT 'descriptions_with_matched_neighbours', (SELECT count(DISTINCT src_id) FROM rc WHERE dst_id IN (SELECT x FROM ps)), (SELECT n FROM nl)
 UNION ALL SELECT 'pairs_with_matching_neighbours', (SELECT count(*) FROM mn), (SELECT n FROM nf)
 UNION ALL SELECT 'pairs_with_common_match', (SELECT count(*) FROM cm), (SELECT n FROM nf))"""
for _c in ("d1", "d2", "d3", "d4", "d5"):
    _add(f"mm_report_{_c}", _on(_c, "dirty", lambda d, t: missed.report(token_blocking.build(d), t, groundtruth.edges(d))), _with(_c, "dirty", f"{TOKEN_POSTINGS}, {REPORT}", "SELECT *, round(numerator * 100.0::DOUBLE / nullif(denominator, 0), 8) AS pct FROM rp"))
_add("mm_report_literal_d2", _on("d2", "dirty", lambda d, t: missed.report(token_blocking.build(d, kinds=("literal",)), t, groundtruth.edges(d))), _with("d2", "dirty", f"{TOKENS}, p AS (SELECT DISTINCT token AS block_key, collection, entity_id FROM tok WHERE kind = 'literal'), {REPORT}", "SELECT *, round(numerator * 100.0::DOUBLE / nullif(denominator, 0), 8) AS pct FROM rp"))
LINKED = ("d1", "d2", "d3", "d4", "d5", "d7")
STRUCTURE = f"""{EDGES}, {SYM}, tr AS (SELECT DISTINCT left_id, right_id FROM t),
sm AS (SELECT 'match' AS kind, left_id, right_id FROM (SELECT * FROM tr ORDER BY md5(left_id || '|' || right_id || '|42'), left_id, right_id LIMIT 1000)),
il AS (SELECT left_id, row_number() OVER (ORDER BY h, left_id) AS i FROM (SELECT entity_id AS left_id, md5(entity_id || '|42L') AS h FROM (SELECT DISTINCT entity_id FROM d WHERE collection = 'L') ORDER BY h, left_id LIMIT 2000)),
ir AS (SELECT right_id, row_number() OVER (ORDER BY h, right_id) AS i FROM (SELECT entity_id AS right_id, md5(entity_id || '|42R') AS h FROM (SELECT DISTINCT entity_id FROM d WHERE collection = 'R') ORDER BY h, right_id LIMIT 2000)),
sn AS (SELECT 'non_match' AS kind, left_id, right_id FROM (SELECT left_id, right_id, i FROM il JOIN ir USING (i) WHERE NOT EXISTS (SELECT 1 FROM tr WHERE tr.left_id = il.left_id AND tr.right_id = ir.right_id) ORDER BY i LIMIT 1000)),
sp AS (SELECT * FROM sm UNION ALL SELECT * FROM sn), dg AS (SELECT src_id, count(*) AS deg FROM eg GROUP BY 1),
nb AS (SELECT kind, left_id, right_id, l.deg * r.deg AS k FROM sp LEFT JOIN dg l ON l.src_id = left_id LEFT JOIN dg r ON r.src_id = right_id),
mn AS (SELECT DISTINCT kind, left_id, right_id FROM sp JOIN eg a ON a.src_id = left_id JOIN tt ON tt.x = a.dst_id JOIN eg b ON b.src_id = right_id AND b.dst_id = tt.y)"""
_add("st_report", _over("clean", lambda d, t: missed.structural(d, t, groundtruth.edges(d)), LINKED), _over_sql("clean", STRUCTURE, "SELECT kind, count(*) AS pairs, count(k) AS with_neighbours, median(k)::DOUBLE AS median_neighbour_pairs, any_value((SELECT count(*) FROM mn WHERE mn.kind = nb.kind)) AS with_matching_neighbours FROM nb GROUP BY kind", LINKED))
_add("st_sample_matches", _on("d1", "clean", lambda d, t: missed.sample_matches(t, 1000)), _with("d1", "clean", "", "SELECT left_id, right_id FROM (SELECT DISTINCT left_id, right_id FROM t) ORDER BY md5(left_id || '|' || right_id || '|42'), left_id, right_id LIMIT 1000"))

# What attribute clustering and the URI method miss beside token blocking
_PAIRS_OF = "{n}k AS MATERIALIZED (SELECT t.left_id, t.right_id, a.block_key FROM t JOIN {p} a ON a.entity_id = t.left_id), {n}h AS MATERIALIZED (SELECT DISTINCT k.left_id, k.right_id FROM {n}k k JOIN {p} b ON b.entity_id = k.right_id AND b.block_key = k.block_key)"
_BOTH = ATTRIBUTE_POSTINGS.replace(", p AS (", ", pa AS (") + ", pt AS (SELECT DISTINCT token AS block_key, collection, entity_id FROM tok), " + _PAIRS_OF.format(n="x", p="pt") + ", " + _PAIRS_OF.format(n="y", p="pa") + """,
o AS (SELECT left_id, right_id, EXISTS (SELECT 1 FROM xh WHERE xh.left_id = tr.left_id AND xh.right_id = tr.right_id) AS th, EXISTS (SELECT 1 FROM yh WHERE yh.left_id = tr.left_id AND yh.right_id = tr.right_id) AS ah FROM (SELECT DISTINCT left_id, right_id FROM t) tr)"""
_add("mm_split_by_clusters", _over("clean", lambda d, t: missed.split_by_clusters(token_blocking.build(d), attr_clustering.build(d), t)), _over_sql("clean", _BOTH, "SELECT count(*) FILTER (NOT th) AS missed_token, count(*) FILTER (NOT ah) AS missed_attribute, count(*) FILTER (th AND NOT ah) AS split, count(*) FILTER (NOT th AND ah) AS missed_token_only FROM o"))
_PARTS = f"{TOKENS}, {_uri_sql()}, pl0 AS (SELECT DISTINCT token AS block_key, collection, entity_id FROM tok WHERE kind = 'literal'), pi0 AS (SELECT DISTINCT infix AS block_key, collection, entity_id FROM un JOIN inf ON un.uri = inf.uri WHERE infix <> ''), pu0 AS (SELECT * FROM pl0 UNION SELECT * FROM pi0), " + ", ".join(_PAIRS_OF.format(n=n, p=p) for n, p in (("l", "pl0"), ("i", "pi0"), ("u", "pu0"))) + """,
o AS (SELECT left_id, right_id, EXISTS (SELECT 1 FROM lh WHERE lh.left_id = tr.left_id AND lh.right_id = tr.right_id) AS l, EXISTS (SELECT 1 FROM ih WHERE ih.left_id = tr.left_id AND ih.right_id = tr.right_id) AS i, EXISTS (SELECT 1 FROM uh WHERE uh.left_id = tr.left_id AND uh.right_id = tr.right_id) AS u FROM (SELECT DISTINCT left_id, right_id FROM t) tr)"""


def _split_by_parts(d: DataFrame, t: DataFrame) -> DataFrame:
    infixes = checkpoint(uri_infix.infix_postings(uri_infix.infixes(d)))
    literals = token_blocking.build(d, kinds=("literal",))
    return missed.split_by_parts(literals, infixes, infixes.unionByName(literals).distinct(), t)


_add("mm_split_by_parts", _over("clean", _split_by_parts, URIS), _over_sql("clean", _PARTS, "SELECT count(*) FILTER (NOT u) AS missed_uri, count(*) FILTER (NOT l AND NOT i) AS without_token_and_infix, count(*) FILTER (i AND NOT l) AS common_infix_only, count(*) FILTER (l AND NOT i) AS common_token_only FROM o", URIS))


def _relations(spark: SparkSession, sf_dir: str, stats: bool = False) -> DataFrame:
    out = []
    for r in views.RELATIONS:
        d, t = views.load_relation(spark, sf_dir, r)
        if stats:
            x = measures.characteristics(d).select("collection", "triples", "descriptions", "pairs_per_description").crossJoin(t.agg(F.count(F.lit(1)).alias("links"), F.count_distinct("link_type").alias("link_types")))
        else:
            x = measures.recall_by(measures.hits(token_blocking.build(d), t), ["link_type"]).withColumn("recall", F.round("recall", 10))
        out.append(written(x.withColumn("dataset", F.lit(r)).coalesce(1), "zstd"))  # done and off the disk before the next
    return reduce(DataFrame.unionByName, out)


def _relation_rows(final: str, ctes: str) -> str:
    rows = []
    for r in views.RELATIONS:
        d, t = views.relation_sql(r)
        rows.append(f"SELECT '{r}' AS dataset, z_{r}.* FROM (WITH d AS (SELECT * FROM ({d}) y WHERE value IS NOT NULL), t AS ({t}){ctes} {final}) z_{r}")
    return " UNION ALL ".join(rows)


_add("rl_recall_by_link", _relations, _relation_rows("SELECT link_type, count(*) AS links, count(*) FILTER (hit) AS tp, round(count(*) FILTER (hit) / count(*)::DOUBLE, 10) AS recall FROM h GROUP BY 1", f", {TOKEN_POSTINGS}, {HITS}"))
_add("rl_link_stats", partial(_relations, stats=True), _relation_rows("SELECT collection, count(*) AS triples, count(DISTINCT entity_id) AS descriptions, round(count(*)::DOUBLE / count(DISTINCT entity_id), 8) AS pairs_per_description, (SELECT count(*) FROM t) AS links, (SELECT count(DISTINCT link_type) FROM t) AS link_types FROM d GROUP BY collection", ""))


def _strata(spark: SparkSession, sf_dir: str) -> DataFrame:
    d, t = views.load(spark, sf_dir, "d4", "clean")
    of = spark.table("documents").select(F.expr("'http://docs.test/doc/' || doc_id").alias("left_id"), "lang", "source").distinct()
    return measures.recall_by(measures.hits(token_blocking.build(d), t).join(of, "left_id"), ["lang", "source"], "cube").withColumn("recall", F.round("recall", 10))


_add("rl_recall_strata", _strata, f"WITH {_descriptions('d4', 'clean')}, {TOKEN_POSTINGS}, {HITS}, o AS (SELECT DISTINCT 'http://docs.test/doc/' || doc_id AS left_id, lang, source FROM documents) SELECT lang, source, count(*) AS links, count(*) FILTER (hit) AS tp, round(count(*) FILTER (hit) / count(*)::DOUBLE, 10) AS recall FROM h JOIN o USING (left_id) GROUP BY CUBE (lang, source)")

# Comparison of methods
_add("cmp_methods", lambda spark, sf: workloads.matrix(spark, sf), _matrix_sql(ALL))
_DELTA = """SELECT m.collection, m.task, m.method, round((m.recall - b.recall) * 100, 8) AS recall_points, m.fn - b.fn AS extra_misses,
round(m.precision / nullif(b.precision, 0), 8) AS precision_ratio, round(m.comparisons::DOUBLE / nullif(b.comparisons::DOUBLE, 0), 8) AS comparison_ratio
FROM m JOIN m b ON b.method = 'token' AND m.method <> 'token' AND b.collection = m.collection AND b.task = m.task"""
_add("cmp_delta", lambda spark, sf: measures.delta(workloads.matrix(spark, sf)), f"WITH m AS ({_matrix_sql(ALL)}) {_DELTA}")
_MEANS = ("recall", "precision", "rr", "h3r")
_add("cmp_cube", lambda spark, sf: workloads.matrix(spark, sf).rollup("role", "collection", "method").agg(F.count(F.lit(1)).alias("cells"), *[F.round(F.avg(x), 8).alias(x) for x in _MEANS]), f"WITH m AS ({_matrix_sql(ALL)}) SELECT role, collection, method, count(*) AS cells, {', '.join(f'round(avg({x}), 8) AS {x}' for x in _MEANS)} FROM m GROUP BY ROLLUP (role, collection, method)")


def _clusters_and_recall(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Size of the attribute clusters beside what they cost in recall and gain in precision."""
    views.register(spark, sf_dir)
    workloads.side_by_side(lambda c: workloads.clusters(spark, sf_dir, c), ALL)  # read by the matrix, too
    sizes = reduce(DataFrame.unionByName, [measures.cluster_stats(workloads.clusters(spark, sf_dir, c)).withColumn("name", F.lit(c)) for c in ALL])
    change = measures.delta(workloads.matrix(spark, sf_dir, ALL, ("token", "attribute"))).where("task = 'clean'")
    return sizes.join(change, sizes["name"] == change["collection"]).select("name", "n_clusters", "median_attributes", "recall_points", "extra_misses", "precision_ratio", "comparison_ratio")


_add("ac_delta_vs_token", _clusters_and_recall, f"WITH m AS ({_matrix_sql(ALL, ('token', 'attribute'))}), dl AS ({_DELTA}), st AS ({ORACLE['ac_cluster_stats']}) SELECT name, n_clusters, median_attributes, recall_points, extra_misses, precision_ratio, comparison_ratio FROM st JOIN dl ON dl.collection = st.name AND dl.task = 'clean'")


# Streams
def _stream(make: Callable[[DataFrame], DataFrame], mode: str = "complete") -> Query:
    return lambda spark, sf: incremental.drain(make(incremental.event_stream(spark, f"{sf}/events.parquet")), mode)


_EV = "ek AS (SELECT ts, user_id, unnest(list_concat([event_type], json_keys(props))) AS value FROM events), et AS (SELECT ts, user_id AS entity_id, unnest(list_distinct(regexp_extract_all(lower(value), '" + WORD + "'))) AS block_key FROM ek)"
_add("sm_incremental_postings", _stream(incremental.incremental_postings, "append"), f"WITH {_EV} SELECT DISTINCT block_key, entity_id FROM et")
_add("sm_block_growth", _stream(incremental.block_growth), f"WITH {_EV} SELECT time_bucket(INTERVAL '1 hour', ts) AS start, block_key, count(*) AS n FROM et GROUP BY 1, 2")
_add("sm_session_users", _stream(lambda e: incremental.sessions(incremental.closed(e)), "append"), "WITH g AS (SELECT user_id, ts, CASE WHEN ts - lag(ts) OVER (PARTITION BY user_id ORDER BY ts) < INTERVAL '30 minutes' THEN 0 ELSE 1 END AS new FROM events), k AS (SELECT *, sum(new) OVER (PARTITION BY user_id ORDER BY ts ROWS UNBOUNDED PRECEDING) AS s FROM g) SELECT user_id, min(ts) AS start, count(*) AS n FROM k GROUP BY user_id, s")


def _new_candidates(spark: SparkSession, sf: str) -> DataFrame:
    events = spark.read.parquet(f"{sf}/events.parquet")
    known = events.where("ts < TIMESTAMP_NTZ '2024-01-02'").select(F.col("event_type").alias("block_key"), F.col("user_id").alias("entity_id")).distinct()
    stream = incremental.event_stream(spark, f"{sf}/events.parquet").where("ts >= TIMESTAMP '2024-01-02'")
    found = incremental.drain(incremental.new_candidates(stream, known), "append")
    return found.groupBy("block_key", "entity_id").agg(F.count_distinct("other").alias("others"))


_add("sm_new_candidates", _new_candidates, f"WITH {_EV}, kn AS (SELECT DISTINCT event_type AS block_key, user_id AS other FROM events WHERE ts < TIMESTAMP '2024-01-02') SELECT block_key, entity_id, count(DISTINCT other) AS others FROM et JOIN kn USING (block_key) WHERE ts >= TIMESTAMP '2024-01-02' AND entity_id <> other GROUP BY 1, 2")
_add("sm_late", lambda spark, sf: incremental.drain(incremental.late(incremental.event_stream(spark, f"{sf}/events.parquet"), 86_400, "event_id % 7 * 100000000 + event_id"), "update").groupBy("user_id").agg(F.max("n").alias("n"), F.max("n_late").alias("n_late")), "WITH o AS (SELECT user_id, ts, max(ts) OVER (PARTITION BY user_id ORDER BY event_id % 7, event_id ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING) AS top FROM events) SELECT user_id, count(*) AS n, count(*) FILTER (ts < top - INTERVAL '1 day') AS n_late FROM o GROUP BY 1")
_add("sm_sliding_blocks", _stream(lambda e: incremental.block_growth(e, "1 hour", "30 minutes")), f"WITH {_EV} SELECT start, block_key, count(*) AS n FROM (SELECT block_key, unnest([time_bucket(INTERVAL '30 minutes', ts), time_bucket(INTERVAL '30 minutes', ts) - INTERVAL '30 minutes']) AS start FROM et) GROUP BY 1, 2")


# Operators around the methods
for _m, _c in (("token", "d5"), ("attribute", "d2"), ("uri", "d4")):
    _add("op_same_block" + ("" if _m == "token" else f"_{_m}"), _on(_c, "clean", lambda d, t, m=_m: blocks.same_block(workloads.postings(d, m), t)), _with(_c, "clean", f"{POSTINGS[_m]}, {HITS}", "SELECT DISTINCT left_id, right_id FROM h WHERE hit"))
_add("op_nested_descriptions", _on("d1", "clean", lambda d, t: ingest.nest(d).select("collection", "entity_id", F.size("attrs").alias("n"))), _with("d1", "clean", "", "SELECT collection, entity_id, count(*)::INT AS n FROM (SELECT DISTINCT collection, entity_id, attribute, value, kind FROM d) GROUP BY 1, 2"))
_add("op_truth_closure", _on("d6", "dirty", lambda d, t: groundtruth.close(t)), _with("d6", "dirty", "e2 AS (SELECT left_id AS a, right_id AS b FROM t UNION SELECT right_id, left_id FROM t), reach AS (SELECT a AS n, b AS c FROM e2 UNION SELECT reach.n, e2.b FROM reach JOIN e2 ON e2.a = reach.c)", "SELECT n AS left_id, c AS right_id, 'equivalence' AS link_type FROM reach WHERE n < c"))


def _of_type(spark: SparkSession, sf: str, kind: str) -> DataFrame:
    return spark.read.parquet(f"{sf}/events.parquet").where(F.col("event_type") == kind).select("event_id", "user_id", "ts")


def _candidate_sets(d: DataFrame, t: DataFrame) -> DataFrame:
    return around.compare_candidates({m: pairs.distinct(workloads.postings(d, m), "clean") for m in ("token", "attribute", "uri")})


def _surface(d: DataFrame, t: DataFrame) -> DataFrame:
    spark = d.sparkSession
    around.surface(spark, d, token_blocking.build(d), t, "clean")
    text = "SELECT x.collection, f.token, count(*) AS n, any_value(b.comparisons) AS comparisons FROM (SELECT DISTINCT collection, entity_id, value FROM descriptions WHERE attribute = :attribute) x, LATERAL tokens_of(x.value) f JOIN block_summary b ON b.block_key = f.token GROUP BY 1, 2"
    return spark.sql(text, args={"attribute": "name"}).withColumn("comparisons", F.col("comparisons").cast("string"))


_add("op_asof", lambda spark, sf: around.asof_join(_of_type(spark, sf, "purchase"), _of_type(spark, sf, "click"), "user_id", "ts").select("event_id", "as_of"), "SELECT p.event_id, c.ts AS as_of FROM (SELECT * FROM events WHERE event_type = 'purchase') p ASOF LEFT JOIN (SELECT * FROM events WHERE event_type = 'click') c ON p.user_id = c.user_id AND p.ts >= c.ts")
_add("op_interval", lambda spark, sf: around.interval_join(_of_type(spark, sf, "purchase"), _of_type(spark, sf, "click"), "user_id", "ts", "event_id", 1800), "SELECT p.event_id AS left_id, c.event_id AS right_id FROM events p JOIN events c ON p.event_type = 'purchase' AND c.event_type = 'click' AND p.user_id = c.user_id AND abs(epoch_us(p.ts) - epoch_us(c.ts)) <= 1800000000")
_SETS = ("token", "attribute", "uri")
_CLEAN_PAIRS = _pairs("clean")
_add("op_candidate_sets", _on("d2", "clean", _candidate_sets), "WITH " + ", ".join(f"c_{m} AS (SELECT * FROM ({_with('d2', 'clean', f'{POSTINGS[m]}, {_CLEAN_PAIRS}', 'SELECT * FROM pr')}) z_{m})" for m in _SETS) + " " + " UNION ALL ".join(f"SELECT '{x}' AS a, '{y}' AS b, (SELECT count(*) FROM (SELECT * FROM c_{x} INTERSECT SELECT * FROM c_{y})) AS \"both\", (SELECT count(*) FROM (SELECT * FROM c_{x} EXCEPT SELECT * FROM c_{y})) AS only_a, (SELECT count(*) FROM (SELECT * FROM c_{y} EXCEPT SELECT * FROM c_{x})) AS only_b" for x, y in (("token", "attribute"), ("token", "uri"), ("attribute", "uri"))))


def _saved(d: DataFrame, t: DataFrame) -> DataFrame:
    """Postings written to the shared folder by key, and those of one key read back."""
    spark, path = d.sparkSession, new_path(d.sparkSession)
    around.save_postings(token_blocking.build(d), path, 16)
    return around.postings_of(spark, path, "customer", 16).unionByName(around.postings_of(spark, path, "client", 16))


_add("op_saved_postings", _on("d2", "clean", _saved), _with("d2", "clean", TOKEN_POSTINGS, "SELECT * FROM p WHERE block_key IN ('customer', 'client')"))
_add("op_top_blocks", _on("d6", "dirty", lambda d, t: around.top_blocks(blocks.summary(token_blocking.build(d), "dirty"), 100)), _with("d6", "dirty", f"{TOKEN_POSTINGS}, {_summary('dirty')}", "SELECT block_key, row_number() OVER w AS rank, sum(comparisons) OVER (w ROWS UNBOUNDED PRECEDING)::HUGEINT::VARCHAR AS running FROM (SELECT * FROM s ORDER BY comparisons DESC, block_key LIMIT 100) WINDOW w AS (ORDER BY comparisons DESC, block_key)"))
_add("op_sql_surface", _on("d2", "clean", _surface), _with("d2", "clean", f"{TOKEN_POSTINGS}, {_summary('clean')}", "SELECT x.collection, x.token, count(*) AS n, any_value(s.comparisons)::VARCHAR AS comparisons FROM (SELECT collection, entity_id, value, unnest(list_distinct(regexp_extract_all(lower(value), '" + WORD + "'))) AS token FROM (SELECT DISTINCT collection, entity_id, value FROM d WHERE attribute = 'name')) x JOIN s ON s.block_key = x.token GROUP BY 1, 2"))
_add("op_metric_pivot", lambda spark, sf: workloads.matrix(spark, sf, ("d1", "d2", "d7"), ("token", "attribute")).where("task = 'clean'").groupBy("collection").pivot("method", ["token", "attribute"]).agg(F.max("recall").alias("recall"), F.max("rr").alias("rr")), f"WITH m AS ({_matrix_sql(('d1', 'd2', 'd7'), ('token', 'attribute'))}) SELECT collection, " + ", ".join(f"max({x}) FILTER (method = '{m}') AS {m}_{x}" for m in ("token", "attribute") for x in ("recall", "rr")) + " FROM m WHERE task = 'clean' GROUP BY 1")
_add("op_kept_linked", _on("d5", "dirty", lambda d, t: ingest.keep_linked(d, t, "left").groupBy("attribute").agg(F.count(F.lit(1)).alias("n"))), _with("d5", "dirty", "", "SELECT attribute, count(*) AS n FROM (SELECT * FROM (" + views.descriptions_sql("d5", "dirty") + ") y) x WHERE entity_id IN (SELECT left_id FROM t) GROUP BY 1"))
_add("op_unpivot", lambda spark, sf: ingest.combine_clean(ingest.unpivot(spark.read.parquet(f"{sf}/customer.parquet"), "x", "'c' || c_custkey", ["c_name", "c_mktsegment"]), ingest.unpivot(spark.read.parquet(f"{sf}/supplier.parquet"), "x", "'s' || s_suppkey", ["s_name"])), "SELECT 'L' AS collection, 'c' || c_custkey AS entity_id, 'c_name' AS attribute, c_name AS value, 'literal' AS kind FROM customer WHERE c_name IS NOT NULL UNION ALL SELECT 'L', 'c' || c_custkey, 'c_mktsegment', c_mktsegment, 'literal' FROM customer WHERE c_mktsegment IS NOT NULL UNION ALL SELECT 'R', 's' || s_suppkey, 's_name', s_name, 'literal' FROM supplier WHERE s_name IS NOT NULL")


def queries() -> dict[str, Query]:
    return dict(QUERIES)


def oracle_sql() -> dict[str, str]:
    return dict(ORACLE)
