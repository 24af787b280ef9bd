"""Knowledge-base views of the given tables, and the collections of the experiments with their truth.

A view is SQL that Spark and DuckDB both read, so results can be compared on the same definition.  Every
view runs over its whole table.
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

TABLES = ("region", "nation", "customer", "supplier", "part", "orders", "lineitem", "events", "documents", "embeddings", "pages", "benchmark", "labels", "conversations")


def view(table: str, entity: str, literals: dict[str, str], uris: dict[str, str] | None = None) -> str:
    """One SELECT per attribute: entity_id, attribute, value, kind."""
    rows = [(a, e, "literal") for a, e in literals.items()] + [(a, e, "uri") for a, e in (uris or {}).items()]
    return " UNION ALL ".join(f"SELECT {entity} AS entity_id, '{a}' AS attribute, CAST({e} AS STRING) AS value, '{k}' AS kind FROM {table}" for a, e, k in rows)


def _ns(kind: str, key: str, host: str = "kb.test") -> str:
    return f"'http://{host}/{kind}/' || {key}"


ARTICLE = "regexp_extract(html, '(?s)<article>(.*)</article>', 1)"
RANKED_PAGES = f"(SELECT *, {ARTICLE} AS article, row_number() OVER (PARTITION BY {ARTICLE} ORDER BY page_id) AS rn FROM pages)"
ORDER_LINES = "(SELECT DISTINCT l_orderkey, l_partkey, l_suppkey, l_shipdate FROM lineitem)"


def _excerpt(doc: str) -> str:
    """Id of an excerpt: it names the document, but for every tenth, which is opaque."""
    return f"CASE WHEN ({doc}) % 10 = 1 THEN 'https://excerpts.example/leaf/' || md5('e' || ({doc})) ELSE 'https://excerpts.example/leaf/doc/' || ({doc}) || '/page.html' END"


def _some(table: str, condition: str) -> str:
    return f"(SELECT * FROM {table} WHERE {condition})"


# Links between descriptions are on a part of them, as their host names would make blocks of all others.
PREVIOUS = "(SELECT * FROM (SELECT o_orderkey, lag(o_orderkey) OVER (PARTITION BY o_custkey ORDER BY o_orderkey) AS prev FROM orders) x WHERE prev IS NOT NULL AND o_orderkey % 20 < 4)"
NEXT_PAGE = f"(SELECT p.url, q.url AS next_url, p.rn FROM (SELECT * FROM {RANKED_PAGES} x WHERE page_id % 4 = 0) p JOIN pages q ON q.page_id = p.page_id + 1)"

KB = {
    "part_a": " UNION ALL ".join(
        [
            view("part", _ns("part", "p_partkey", "a.test"), {"type": "'part'", "name": "replace(p_name, '#', '')", "brand": "replace(p_brand, '#', '')", "ptype": "p_type", "size": "p_size"}),
            view(_some("part", "p_partkey % 5 = 0"), _ns("part", "p_partkey", "a.test"), {}, {"previous": _ns("part", "(p_partkey - 1)", "a.test")}),
        ]
    ),
    # Of every 25th part all values are hidden.
    "part_b": " UNION ALL ".join(
        [
            view("part", "'https://b.example/product/' || p_partkey || '/about'", {"type": "'product'", **{k: f"CASE WHEN p_partkey % 25 = 0 THEN md5({v}) ELSE {v} END" for k, v in {"label": "replace(p_name, '#', '') || ' ' || replace(p_brand, '#', '')", "category": "p_type", "dims": "'' || p_size"}.items()}}),
            view(_some("part", "p_partkey % 5 = 0"), "'https://b.example/product/' || p_partkey || '/about'", {}, {"after": "'https://b.example/product/' || (p_partkey + 1) || '/about'"}),
        ]
    ),
    "master": " UNION ALL ".join(
        [
            view("customer", _ns("customer", "c_custkey"), {"type": "'customer'", "name": "replace(c_name, '#', '')", "segment": "c_mktsegment"}),
            view(_some("customer", "c_custkey % 3 = 0"), _ns("customer", "c_custkey"), {}, {"nation": _ns("nation", "c_nationkey")}),
            view("supplier", _ns("supplier", "s_suppkey"), {"type": "'supplier'", "name": "replace(s_name, '#', '')"}),
            view(_some("supplier", "s_suppkey % 5 = 0"), _ns("supplier", "s_suppkey"), {}, {"nation": _ns("nation", "s_nationkey")}),
            view("nation", _ns("nation", "n_nationkey"), {"type": "'nation'", "name": "replace(n_name, '_', '')"}, {"region": _ns("region", "n_regionkey")}),
            view("region", _ns("region", "r_regionkey"), {"type": "'region'", "name": "r_name"}),
        ]
    ),
    "rest": " UNION ALL ".join(
        [
            view("customer", "'https://rest.example/c/' || c_custkey", {"kind": "'client'", "title": "CASE WHEN c_custkey % 5 = 0 THEN md5(c_name) ELSE replace(c_name, '#', '') END", "market": "CASE WHEN c_custkey % 3 = 0 THEN NULL ELSE c_mktsegment END", "ref": "CASE WHEN c_custkey % 6 = 0 THEN 'x' || c_custkey END"}),
            view(_some("customer", "c_custkey % 3 = 0"), "'https://rest.example/c/' || c_custkey", {}, {"country": "'https://rest.example/n/' || md5('n' || c_nationkey)"}),
            view(_some("customer", "c_custkey % 6 = 0"), "'https://rest.example/again/' || c_custkey", {"alias": "replace(c_name, '#', '')", "ref": "'x' || c_custkey"}),
            view("supplier", "'https://rest.example/s/' || s_suppkey", {"kind": "'vendor'", "company": "CASE WHEN s_suppkey % 5 = 0 THEN md5(s_name) ELSE replace(s_name, '#', '') END"}),
            view(_some("supplier", "s_suppkey % 5 = 0"), "'https://rest.example/s/' || s_suppkey", {}, {"country": "'https://rest.example/n/' || md5('n' || s_nationkey)"}),
            view("nation", "'https://rest.example/n/' || md5('n' || n_nationkey)", {"kind": "'country'", "land": "replace(n_name, '_', '')"}, {"continent": "'https://rest.example/r/' || n_regionkey"}),
            view("region", "'https://rest.example/r/' || r_regionkey", {"kind": "'continent'", "area": "r_name"}),
        ]
    ),
    "orders": " UNION ALL ".join(
        [
            view("orders", "'http://shop.test/' || md5(CAST(o_orderkey AS STRING))", {"type": "CASE WHEN o_orderkey % 20 < 4 THEN 'order' END", "placed": "replace(CAST(CAST(o_orderdate AS DATE) AS STRING), '-', '')", "number": "'o' || o_orderkey", "client": "'c' || o_custkey"}),
            view(PREVIOUS, "'http://shop.test/' || md5(CAST(o_orderkey AS STRING))", {}, {"previous": "'http://shop.test/' || md5(CAST(prev AS STRING))"}),
        ]
    ),
    "order_lines": " UNION ALL ".join(
        [
            view("orders", "'https://ship.example/' || md5('l' || o_orderkey)", {"reference": "CASE WHEN o_orderkey % 20 = 0 THEN md5('x' || o_orderkey) ELSE 'o' || o_orderkey END"}),
            view(ORDER_LINES, "'https://ship.example/' || md5('l' || l_orderkey)", {"shipped": "replace(CAST(CAST(l_shipdate AS DATE) AS STRING), '-', '')", "part": "'p' || l_partkey"}),
            view(PREVIOUS, "'https://ship.example/' || md5('l' || o_orderkey)", {}, {"after": "'https://ship.example/' || md5('l' || prev)"}),
        ]
    ),
    "documents": " UNION ALL ".join(
        [
            view("documents", _ns("doc", "doc_id", "docs.test"), {"text": "text", "lang": "lang", "source": "source"}),
            view(_some("documents", "doc_id % 10 = 0 OR doc_id % 7 = 0"), _ns("doc", "doc_id", "docs.test"), {}, {"next": _ns("doc", "(doc_id + 1)", "docs.test")}),
        ]
    ),
    # Of every tenth document the excerpt's lines are hidden.
    "excerpts": " UNION ALL ".join(
        [
            view("documents", _excerpt("doc_id"), {f"line{i}": f"CASE WHEN doc_id % 10 = 0 THEN md5(split_part(text, chr(10), {i})) ELSE split_part(text, chr(10), {i}) END" for i in (1, 2)}),
            view(_some("documents", "doc_id % 10 = 0"), _excerpt("doc_id"), {}, {"following": _excerpt("doc_id + 1")}),
        ]
    ),
    "benchmark": view("benchmark", "'https://bench.example/' || md5('b' || item_id)", {"passage": "CASE WHEN item_id % 4 = 0 THEN md5(text) ELSE text END"}, {"following": "'https://bench.example/' || md5('b' || (item_id + 1))"}),
    "docs_even": view("(SELECT min(doc_id) AS doc_id, text, min(lang) AS lang, min(source) AS source FROM documents WHERE doc_id % 2 = 0 GROUP BY text)", "'d' || doc_id", {"text": "text", "lang": "lang", "source": "source"}),
    "docs_odd": view("(SELECT min(doc_id) AS doc_id, text, min(lang) AS lang, min(source) AS source FROM documents WHERE doc_id % 2 = 1 GROUP BY text)", "'d' || doc_id", {"text": "text", "lang": "lang", "source": "source"}),
    "docs_all": view("documents", "'d' || doc_id", {"text": "text", "lang": "lang", "source": "source"}),
    "pages_first": " UNION ALL ".join(
        [
            view(_some(f"{RANKED_PAGES} x", "rn <> 2"), "url", {"title": "regexp_extract(html, '<title>([^<]*)</title>', 1)", "article": "article"}),
            view(_some(f"{NEXT_PAGE} x", "rn <> 2"), "url", {}, {"next": "next_url"}),
        ]
    ),
    "pages_sub": " UNION ALL ".join(
        [
            view(_some(f"{RANKED_PAGES} x", "rn = 2"), "url", {"name": "regexp_extract(html, '<title>([^<]*)</title>', 1)", "body": "article"}),
            view(_some(f"{NEXT_PAGE} x", "rn = 2"), "url", {}, {"next": "next_url"}),
        ]
    ),
    "users_before": view("(SELECT DISTINCT user_id, event_type, CAST(hour(ts) AS STRING) AS h FROM events WHERE ts < TIMESTAMP '2024-01-16')", "'u' || user_id", {"action": "event_type", "time": "'h' || h"}),
    "users_after": view("(SELECT DISTINCT user_id, event_type, CAST(hour(ts) AS STRING) AS h FROM events WHERE ts >= TIMESTAMP '2024-01-16')", "'v' || user_id", {"did": "event_type", "when": "'h' || h"}),
    "turns_user": view("(SELECT * FROM conversations WHERE role = 'user')", "'t' || conv_id || '/' || turn", {"text": "text"}),
    "turns_assistant": view("(SELECT * FROM conversations WHERE role = 'assistant')", "'t' || conv_id || '/' || turn", {"reply": "text"}, {"previous": "'t' || conv_id || '/' || (turn - 1)"}),
}


@dataclass(frozen=True)
class Collection:
    """Left and right view for the clean task, views for the dirty one, truth SQL for either, role."""

    name: str
    left: str
    right: str | None
    truth: str
    dirty: tuple[str, ...] = ()
    dirty_truth: str | None = None
    role: str = "central"
    uris: bool = True


def _link(table: str, a: str, b: str, kind: str = "equivalence") -> str:
    return f"SELECT DISTINCT {a} AS left_id, {b} AS right_id, '{kind}' AS link_type FROM {table}"


_D6_DIRTY = "SELECT 'd' || least(a.doc_id, b.doc_id) AS left_id, 'd' || greatest(a.doc_id, b.doc_id) AS right_id, 'equivalence' AS link_type FROM documents a JOIN documents b ON a.text = b.text AND a.doc_id < b.doc_id"
_D6_CLEAN = "SELECT 'd' || a.doc_id AS left_id, 'd' || b.doc_id AS right_id, 'equivalence' AS link_type FROM (SELECT min(doc_id) AS doc_id, text FROM documents WHERE doc_id % 2 = 0 GROUP BY text) a JOIN (SELECT min(doc_id) AS doc_id, text FROM documents WHERE doc_id % 2 = 1 GROUP BY text) b ON a.text = b.text"

_D2 = " UNION ALL ".join(
    [
        _link("customer", _ns("customer", "c_custkey"), "'https://rest.example/c/' || c_custkey"),
        _link(_some("customer", "c_custkey % 6 = 0"), _ns("customer", "c_custkey"), "'https://rest.example/again/' || c_custkey"),
        _link("supplier", _ns("supplier", "s_suppkey"), "'https://rest.example/s/' || s_suppkey"),
        _link("nation", _ns("nation", "n_nationkey"), "'https://rest.example/n/' || md5('n' || n_nationkey)"),
        _link("region", _ns("region", "r_regionkey"), "'https://rest.example/r/' || r_regionkey"),
    ]
)
#: In the dirty task the two descriptions that the other collection has of one customer match, too.
_D2_DIRTY = _D2 + " UNION ALL " + _link(_some("customer", "c_custkey % 6 = 0"), "'https://rest.example/c/' || c_custkey", "'https://rest.example/again/' || c_custkey")


def _contained(kind: str, right: str) -> str:
    return "SELECT DISTINCT " + _ns("doc", "d.doc_id", "docs.test") + f" AS left_id, {right} AS right_id, '{kind}' AS link_type FROM documents d JOIN benchmark b ON contains(d.text, b.text)"


COLLECTIONS = {
    "d1": Collection("d1", "part_a", "part_b", _link("part", _ns("part", "p_partkey", "a.test"), "'https://b.example/product/' || p_partkey || '/about'")),
    "d2": Collection("d2", "master", "rest", _D2, (), _D2_DIRTY, role="peripheral"),
    "d3": Collection("d3", "orders", "order_lines", _link("orders", "'http://shop.test/' || md5(CAST(o_orderkey AS STRING))", "'https://ship.example/' || md5('l' || o_orderkey)")),
    "d4": Collection("d4", "documents", "excerpts", _link("documents", _ns("doc", "doc_id", "docs.test"), _excerpt("doc_id")), role="peripheral"),
    "d5": Collection("d5", "documents", "benchmark", _contained("equivalence", "'https://bench.example/' || md5('b' || b.item_id)"), role="peripheral"),
    "d6": Collection("d6", "docs_even", "docs_odd", _D6_CLEAN, ("docs_all",), _D6_DIRTY, uris=False),
    "d7": Collection("d7", "pages_first", "pages_sub", f"SELECT DISTINCT a.url AS left_id, b.url AS right_id, 'equivalence' AS link_type FROM {RANKED_PAGES} a JOIN {RANKED_PAGES} b ON a.article = b.article AND a.rn <> 2 AND b.rn = 2"),
}

#: Collections beside the seven: users before and after a date, and turns with the replies to them.
EXTRA = {
    "users": Collection("users", "users_before", "users_after", "SELECT DISTINCT 'u' || a.user_id AS left_id, 'v' || b.user_id AS right_id, 'equivalence' AS link_type FROM (SELECT DISTINCT user_id FROM events WHERE ts < TIMESTAMP '2024-01-16') a JOIN (SELECT DISTINCT user_id FROM events WHERE ts >= TIMESTAMP '2024-01-16') b ON a.user_id = b.user_id", uris=False),
    "turns": Collection("turns", "turns_user", "turns_assistant", "SELECT DISTINCT 't' || a.conv_id || '/' || a.turn AS left_id, 't' || b.conv_id || '/' || b.turn AS right_id, 'reply' AS link_type FROM conversations a JOIN conversations b ON a.conv_id = b.conv_id AND b.turn = a.turn + 1 AND a.role = 'user' AND b.role = 'assistant'", uris=False),
}


def collection(name: str) -> Collection:
    return COLLECTIONS[name] if name in COLLECTIONS else EXTRA[name]


_SHIPMENT = "'http://ship.test/' || md5('l' || {k})"
#: Datasets with links other than equivalence: left and right descriptions, and the links. One has two kinds of link.
RELATIONS = {
    "copies": (
        KB["documents"],
        view("documents", "'copy' || doc_id", {"text": "CASE WHEN doc_id % 40 = 0 THEN md5(text) ELSE text END"}),
        "SELECT DISTINCT " + _ns("doc", "a.doc_id", "docs.test") + " AS left_id, 'copy' || b.doc_id AS right_id, 'is_like' AS link_type FROM documents a JOIN documents b ON substring(a.text, 1, 60) = substring(b.text, 1, 60) AND length(a.text) > 60 AND a.text <> b.text",
    ),
    "parts": (
        KB["part_a"],
        view("part", "'like' || p_partkey", {"name": "replace(p_name, '#', '')", "brand": "replace(p_brand, '#', '')"}),
        "SELECT DISTINCT " + _ns("part", "a.p_partkey", "a.test") + " AS left_id, 'like' || b.p_partkey AS right_id, 'is_like' AS link_type FROM part a JOIN part b ON a.p_name = b.p_name AND a.p_brand = b.p_brand AND a.p_type = b.p_type AND a.p_size = b.p_size AND a.p_partkey <> b.p_partkey",
    ),
    # Little is known of a user and of a topic, so few of their links show.
    "users": (
        view("(SELECT user_id, CAST(hour(min(ts)) AS STRING) AS h FROM events GROUP BY user_id)", "'u' || user_id", {"first": "'h' || h"}),
        view("(SELECT DISTINCT event_type FROM events)", "'topic' || event_type", {"short": "substring(event_type, 1, 3)", "hour": "'h' || (ascii(event_type) % 24)"}),
        "SELECT DISTINCT 'u' || user_id AS left_id, 'topic' || event_type AS right_id, 'subject' AS link_type FROM events",
    ),
    "passages": (
        KB["documents"],
        view("benchmark", "'item' || item_id", {"passage": "CASE WHEN item_id % 3 = 0 THEN md5(text) ELSE text END"}),
        _contained("subject", "'item' || b.item_id"),
    ),
    "shipments": (
        " UNION ALL ".join(
            [
                view("orders", _SHIPMENT.format(k="o_orderkey"), {"number": "'o' || o_orderkey"}),
                view("(SELECT DISTINCT l_orderkey, l_partkey FROM lineitem WHERE l_partkey % 2 = 0)", _SHIPMENT.format(k="l_orderkey"), {"item": "'p' || l_partkey"}),
                view("(SELECT o_orderkey, r_name FROM orders JOIN customer ON o_custkey = c_custkey JOIN nation ON c_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey WHERE o_orderkey % 5 < 2)", _SHIPMENT.format(k="o_orderkey"), {"route": "r_name"}),
            ]
        ),
        " UNION ALL ".join([view("part", "'part' || p_partkey", {"code": "'p' || p_partkey", "name": "p_name"}), view("region", "'region' || r_regionkey", {"name": "r_name"})]),
        " UNION ALL ".join(
            [
                _link("lineitem", _SHIPMENT.format(k="l_orderkey"), "'part' || l_partkey", "subject"),
                _link("orders JOIN customer ON o_custkey = c_custkey JOIN nation ON c_nationkey = n_nationkey", _SHIPMENT.format(k="o_orderkey"), "'region' || n_regionkey", "coverage"),
            ]
        ),
    ),
    "customers": (
        view("(SELECT * FROM customer JOIN nation ON c_nationkey = n_nationkey)", _ns("customer", "c_custkey"), {"name": "replace(c_name, '#', '')", "place": "CASE WHEN c_custkey % 8 < 5 THEN replace(n_name, '_', '') END"}),
        view("nation", _ns("nation", "n_nationkey"), {"label": "replace(n_name, '_', '')"}),
        _link("customer", _ns("customer", "c_custkey"), _ns("nation", "c_nationkey"), "based_near"),
    ),
}


def descriptions_sql(name: str, task: str) -> str:
    """SQL of the descriptions of a collection: collection, entity_id, attribute, value, kind."""
    c = collection(name)
    if task == "dirty" and c.dirty:
        return " UNION ALL ".join(f"SELECT 'L' AS collection, x.* FROM ({KB[v]}) x WHERE value IS NOT NULL" for v in c.dirty)
    return f"SELECT 'L' AS collection, x.* FROM ({KB[c.left]}) x WHERE value IS NOT NULL UNION ALL SELECT 'R' AS collection, x.* FROM ({KB[c.right]}) x WHERE value IS NOT NULL"


def truth_sql(name: str, task: str) -> str:
    c = collection(name)
    return c.dirty_truth if task == "dirty" and c.dirty_truth else c.truth


def relation_sql(name: str) -> tuple[str, str]:
    """(descriptions, truth) of a relation: its two ends as collections."""
    left, right, truth = RELATIONS[name]
    return f"SELECT 'L' AS collection, x.* FROM ({left}) x UNION ALL SELECT 'R' AS collection, x.* FROM ({right}) x", truth


#: The session and folder whose tables are registered now.
_REGISTERED: list = []


def register(spark: SparkSession, sf_dir: str) -> None:
    """Temporary views over the tables of a folder."""
    now = [spark.sparkContext.applicationId, id(spark), sf_dir]
    if now != _REGISTERED:
        for t in TABLES:
            spark.read.parquet(f"{sf_dir}/{t}.parquet").createOrReplaceTempView(t)
        _REGISTERED[:] = now


#: Words of a passage that find its places: the second to the sixth, which lie whole inside it.
_PROBE = 5


def contained(documents: DataFrame, benchmark: DataFrame) -> DataFrame:
    """doc_id, item_id of passages inside texts: as a join on ``contains``, by way of a run of words.

    A passage's inner words are words of every text that holds it, so a text's runs of five words are
    joined, by a hash, with one run per passage and the few hits verified.  Passages of fewer than seven words have no such run
    and are tried on every text.
    """
    words = lambda c: F.regexp_extract_all(F.col(c), F.lit(r"\S+"), F.lit(0))
    item = benchmark.select("item_id", F.col("text").alias("passage"), words("text").alias("ws")).where("passage is not null")
    run = lambda i: F.xxhash64(*[F.get("ws", i + k) for k in range(_PROBE)])
    long = item.where(F.size("ws") >= _PROBE + 2).select("item_id", "passage", run(F.lit(1)).alias("run"))
    text = documents.select("doc_id", "text").where("text is not null")
    runs = text.select("doc_id", "text", words("text").alias("ws")).where(F.size("ws") >= _PROBE)
    at = F.sequence(F.lit(0), F.size("ws") - _PROBE)
    runs = runs.select("doc_id", "text", F.explode(F.transform(at, run)).alias("run"))
    hits = runs.join(long, "run").where(F.contains("text", F.col("passage"))).select("doc_id", "item_id")
    short = item.where(F.size("ws") < _PROBE + 2).select("item_id", "passage")
    return hits.unionByName(text.join(short, F.contains("text", F.col("passage"))).select("doc_id", "item_id")).distinct()


def _truth(spark: SparkSession, sql: str, kind: str, right: str) -> DataFrame:
    """Truth of a collection or relation; that of passages in texts without comparing each with each."""
    if "contains(" not in sql:
        return spark.sql(sql)
    contained(spark.table("documents"), spark.table("benchmark")).createOrReplaceTempView("contained_passages")
    return spark.sql("SELECT DISTINCT " + _ns("doc", "doc_id", "docs.test") + f" AS left_id, {right} AS right_id, '{kind}' AS link_type FROM contained_passages")


def load(spark: SparkSession, sf_dir: str, name: str, task: str) -> tuple[DataFrame, DataFrame]:
    """(descriptions, truth) of a collection."""
    register(spark, sf_dir)
    return spark.sql(descriptions_sql(name, task)), _truth(spark, truth_sql(name, task), "equivalence", "'https://bench.example/' || md5('b' || item_id)")


def load_relation(spark: SparkSession, sf_dir: str, name: str) -> tuple[DataFrame, DataFrame]:
    """(descriptions, links) of a dataset with links other than equivalence."""
    register(spark, sf_dir)
    d, t = relation_sql(name)
    return spark.sql(d).where("value is not null"), _truth(spark, t, "subject", "'item' || item_id")
