"""Methods by collection by task: the matrix of the experiments."""

from __future__ import annotations

from collections.abc import Callable, Iterable
from concurrent.futures import ThreadPoolExecutor
from functools import reduce

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from erblock.functions.cut import discard, written
from erblock.operators import attr_clustering, blocks, measures, token_blocking, uri_infix
from erblock.sources import views


def postings(desc: DataFrame, method: str) -> DataFrame:
    """Postings of a method by name: token, attribute, uri, uri_literal (suffix always cut), uri_no_suffix."""
    if method == "token":
        return token_blocking.build(desc)
    if method == "attribute":
        return attr_clustering.build(desc)
    if method == "uri":
        return uri_infix.build(desc)
    if method == "uri_literal":
        return uri_infix.build(desc, suffix_rule="literal")
    if method == "uri_no_suffix":
        return uri_infix.build(desc, suffix=False)
    raise ValueError(method)


def bags(desc: DataFrame, method: str, found: DataFrame | None = None) -> tuple[DataFrame, DataFrame]:
    """``blocks.bags`` of a method as a table, and what its descriptions are counted from; ``found``: attribute clusters."""
    direct = {"token": token_blocking.bags, "attribute": lambda d: attr_clustering.bags(d, found)}.get(method)
    built = written(direct(desc) if direct else blocks.bags(postings(desc, method)), "zstd")
    return built, built if direct else desc


def applies(method: str, collection: str, task: str) -> bool:
    """Attribute clustering needs two collections, the URI method ids that are URIs."""
    if method == "attribute":
        return task == "clean"
    return views.collection(collection).uris or not method.startswith("uri")


def quality(spark: SparkSession, sf_dir: str, collection: str, method: str, tasks: tuple[str, ...] = ("clean", "dirty")) -> DataFrame:
    """A row of all measures per task."""
    rows = []
    for task in tasks:
        if applies(method, collection, task):
            desc, truth = views.load(spark, sf_dir, collection, task)
            built, counted = bags(desc, method)  # made once, all measures derive from it
            rows.append(measures.quality(built, counted, truth, task).select(F.lit(method).alias("method"), F.lit(collection).alias("collection"), F.lit(task).alias("task"), "*"))
    return reduce(DataFrame.unionByName, rows)


#: Cells of a matrix that are computed at the same time.
SIDE_BY_SIDE = 4
#: Rows of a matrix that was computed in this application, by the folder of its tables.
_MATRIX: dict[tuple, list] = {}
#: Attribute clusters that were found in this application, by the folder and collection.
_CLUSTERS: dict[tuple, DataFrame] = {}
MATRIX = "method string, collection string, role string, task string, blocks long, comparisons string, distinct_pairs long, tp long, fn long, recall double, precision double, precision_raw double, f double, rr double, h3r double, redundancy double"


def clusters(spark: SparkSession, sf_dir: str, collection: str) -> DataFrame:
    """Attribute clusters of a collection (clean task), as a table that is made once."""
    key = (spark.sparkContext.applicationId, sf_dir, collection)
    if key not in _CLUSTERS:
        _CLUSTERS[key] = written(attr_clustering.find_clusters(views.load(spark, sf_dir, collection, "clean")[0]).coalesce(1), "zstd")
    return _CLUSTERS[key]


def side_by_side(make: Callable, of: Iterable) -> list:
    with ThreadPoolExecutor(SIDE_BY_SIDE) as pool:
        return list(pool.map(make, of))


def matrix(spark: SparkSession, sf_dir: str, collections: tuple[str, ...] = tuple(views.COLLECTIONS), methods: tuple[str, ...] = ("token", "attribute", "uri", "uri_literal")) -> DataFrame:
    """A row per method, collection and task with all measures; redundancy: comparisons per distinct pair.

    A row is one line of figures; the rows are kept, as several reports are made of the same matrix.  Cells are
    independent chains of short jobs, so a few run side by side; tasks on the same descriptions share their bags, and the cells
    of a collection its truth.
    """
    application = spark.sparkContext.applicationId
    cells = [(application, sf_dir, c, m, task) for c in collections for m in methods for task in ("clean", "dirty") if applies(m, c, task)]

    def row(c: str, m: str, task: str, built: DataFrame, counted: DataFrame) -> list:
        q = measures.quality(built, counted, truths[c, views.truth_sql(c, task)], task)
        redundancy = F.round(F.try_divide(F.col("comparisons").cast("double"), F.col("distinct_pairs")), 8)
        head = {"method": m, "collection": c, "role": views.COLLECTIONS[c].role, "task": task}
        return q.select(*[F.lit(v).alias(k) for k, v in head.items()], "blocks", "comparisons", "distinct_pairs", "tp", "fn", "recall", "precision", "precision_raw", "f", "rr", "h3r", redundancy.alias("redundancy")).collect()

    def of_one(group: list) -> None:
        _, _, c, m, task = group[0]
        built, counted = bags(views.load(spark, sf_dir, c, task)[0], m, clusters(spark, sf_dir, c) if m == "attribute" else None)
        for x in group:
            _MATRIX[x] = row(*x[2:], built, counted)
        discard(built)

    todo = [x for x in cells if x not in _MATRIX]
    views.register(spark, sf_dir)
    asked = {(c, views.truth_sql(c, task)): task for _, _, c, _, task in todo}
    truths = dict(zip(asked, side_by_side(lambda x: written(views.load(spark, sf_dir, x[0][0], x[1])[1], "zstd"), asked.items()), strict=True))
    groups: dict[tuple, list] = {}
    for x in todo:
        groups.setdefault((x[2], x[3], views.descriptions_sql(x[2], x[4])), []).append(x)
    side_by_side(of_one, groups.values())
    return spark.createDataFrame([r for x in cells for r in _MATRIX[x]], MATRIX)
