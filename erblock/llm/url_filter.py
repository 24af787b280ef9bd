"""URL filters: allow and block rules first, gradient-boosted trees for the rest (native).

*Rules.*  A rule ``host/path`` fits a host and all its subdomains if the url's path starts with the
rule's; of those that fit, the longest decides.  Rules are a short parameter list, so they become
one column expression.

*Method.*  Lexical features of a url (lengths, depth, digit and symbol ratios, entropy of its characters,
parameter counts, and how often urls with its host suffix are blocked among the labelled) go to boosted
trees.  Labelled urls are those that a rule decides, or the caller's own.  Suffixes are counted over all labelled
rows, for each of ``FOLDS`` folds of the urls: a url that the trees are fitted on sees the statistics of the other folds only, so
its own label does not leak into its features.  The trees are fitted on at most ``max_labelled`` distinct urls of both
kinds, those with the smallest hashes: a cut of the hash is worked out from the count, and only urls under it move.
Training and scoring run in the JVM.

The fitted trees are turned into one SQL expression, so scoring is a projection inside code generation.
``held_out`` measures the method: fitted on some labelled urls and judged on the others.

Edge cases: a null url or one without ``://`` has an empty host and path, fits no rule and is judged by the
method; without labels of both kinds the method allows; repeated rows are judged alike; page ids may be
null; extra columns are ignored.
"""

from __future__ import annotations

from collections.abc import Sequence
from dataclasses import dataclass

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from erblock.llm.common import checkpoint, fits, let

#: Labelled urls that the trees are fitted on at most, and folds of the suffix statistics.
MAX_LABELLED, FOLDS = 20_000, 5


@dataclass(frozen=True)
class Rule:
    """``host/path`` and what it says: allow or block."""

    rule: str
    verdict: str

    @property
    def host(self) -> str:
        return self.rule.split("/", 1)[0].lower()

    @property
    def path(self) -> str:
        return "/" + self.rule.split("/", 1)[1] if "/" in self.rule else ""


RULES = (
    Rule("org/", "allow"),
    Rule("example.org/es/", "block"),
    Rule("example.org/en/1", "block"),
    Rule("com/fr/", "allow"),
    Rule("com/de/", "block"),
)


def _after_scheme(url: Column) -> Column:
    at = F.instr(url, "://")
    return F.when(at > 0, F.expr("substring(_u, instr(_u, '://') + 3)")).otherwise(F.lit(""))


def parts(df: DataFrame, url_col: str = "url") -> DataFrame:
    """Adds host and path."""
    named = df.withColumn("_u", F.coalesce(F.col(url_col), F.lit("")))
    named = named.withColumn("_rest", _after_scheme(F.col("_u")))
    host = F.regexp_extract("_rest", r"^[^/?#]*", 0)
    named = named.withColumn("host", F.translate(host, "ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz"))
    return named.withColumn("path", F.regexp_extract("_rest", r"^[^/?#]*([^?#]*)", 1)).drop("_u", "_rest")


def decide(rules: Sequence[Rule] = RULES) -> tuple[Column, Column]:
    """(rule string, its verdict) of the longest rule that fits; null if none."""
    host, path = F.col("host"), F.col("path")
    rule = verdict = None
    for r in sorted(rules, key=lambda r: (-len(r.rule), r.rule)):
        fits = ((host == r.host) | host.endswith("." + r.host)) & path.startswith(r.path)
        rule = F.when(fits, r.rule) if rule is None else rule.when(fits, r.rule)
        verdict = F.when(fits, r.verdict) if verdict is None else verdict.when(fits, r.verdict)
    none = F.lit(None).cast("string")
    return (none, none) if rule is None else (rule.otherwise(none), verdict.otherwise(none))


def _entropy(text: Column) -> Column:
    """Shannon entropy (bits) of the characters."""

    def over(chars: Column) -> Column:
        n = F.size(chars)

        def of(sorted_chars: Column) -> Column:
            # In sorted order a character's run ends where the next differs; runs give the counts.
            ends = F.filter(F.sequence(F.lit(0), n - 1), lambda i: ~F.get(sorted_chars, i).eqNullSafe(F.get(sorted_chars, i + 1)))
            return let(
                ends,
                lambda e: F.aggregate(
                    F.transform(e, lambda x, k: (x - F.coalesce(F.get(e, k - 1), F.lit(-1))).cast("double") / n),
                    F.lit(0.0),
                    lambda acc, p: acc - p * F.log2(p),
                ),
            )

        return F.when(n > 0, let(F.sort_array(chars), of)).otherwise(F.lit(0.0))

    return let(F.filter(F.split(text, ""), lambda c: c != ""), over)


#: The last two labels of the host.
SUFFIX = r"([^.]+\.[^.]+|[^.]*)$"

FEATURES = ("url_length", "host_length", "path_length", "host_labels", "depth", "digit_ratio", "symbol_ratio", "entropy", "n_params", "n_hyphens", "has_fragment", "secure", "lang_segment", "suffix_rate", "suffix_count")


def features(df: DataFrame, url_col: str = "url") -> DataFrame:
    """Adds the lexical features (all but the suffix statistics) and ``suffix``, the last two labels."""
    u = F.coalesce(F.col(url_col), F.lit(""))
    n = F.greatest(F.length(u), F.lit(1))
    count = lambda pattern: F.length(F.regexp_replace(u, f"[^{pattern}]+", ""))
    query = F.regexp_extract(u, r"\?([^#]*)", 1)
    out = {
        "url_length": F.length(u),
        "host_length": F.length("host"),
        "path_length": F.length("path"),
        "host_labels": F.when(F.col("host") == "", 0).otherwise(F.size(F.split("host", r"\."))),
        "depth": F.size(F.filter(F.split("path", "/"), lambda x: x != "")),
        "digit_ratio": count("0-9") / n,
        "symbol_ratio": count(r"_%=&~+;@$!-") / n,
        "entropy": _entropy(u),
        "n_params": F.when(query == "", 0).otherwise(F.size(F.split(query, "&"))),
        "n_hyphens": F.length(F.regexp_replace("host", "[^-]+", "")),
        "has_fragment": F.contains(u, F.lit("#")).cast("int"),
        "secure": u.startswith("https").cast("int"),
        "lang_segment": F.crc32(F.regexp_extract("path", r"^/([a-z]{2})(?:/|$)", 1)) % 97,
    }
    return df.withColumns({k: v.cast("double") for k, v in out.items()}).withColumn("suffix", F.regexp_extract("host", SUFFIX, 1))


def _sql_of(trees: list, weights: list[float], names: Sequence[str]) -> str:
    """Weighted sum of regression trees (JVM nodes) as nested CASE expressions."""

    def node(x: object) -> str:
        if x.numDescendants() == 0:
            return f"{float(x.prediction())!r}D"
        s = x.split()
        return f"(CASE WHEN `{names[s.featureIndex()]}` <= {float(s.threshold())!r}D THEN {node(x.leftChild())} ELSE {node(x.rightChild())} END)"

    return " + ".join(f"{w!r}D * {node(t._call_java('rootNode'))}" for t, w in zip(trees, weights, strict=True))


@dataclass(frozen=True)
class Model:
    """Fitted filter: suffix statistics (of all labelled rows) and the margin as SQL (above 0: block)."""

    suffixes: DataFrame
    few: bool
    prior: float
    margin: str


def _rates(p: Column, n: Column, prior: float) -> dict[str, Column]:
    """Share of blocked urls of a suffix, drawn towards the prior, and their number."""
    p, n = F.coalesce(p, F.lit(0.0)), F.coalesce(n, F.lit(0)).cast("double")
    return {"suffix_rate": F.when(n > 0, (p + F.lit(2 * prior)) / (n + 2)).otherwise(F.lit(prior)), "suffix_count": n}


def _scored(df: DataFrame, model: Model) -> DataFrame:
    """Rows with features and suffix, with the margin."""
    suffixes = model.suffixes.select(F.col("suffix").alias("s"), "p", "n")
    joined = df.join(F.broadcast(suffixes) if model.few else suffixes, F.col("suffix") == F.col("s"), "left")
    return joined.withColumns(_rates(F.col("p"), F.col("n"), model.prior)).withColumn("margin", F.expr(model.margin)).drop("s", "p", "n")


def _fold(url: str) -> Column:
    return F.pmod(F.xxhash64(F.col(url), F.lit("fold")), F.lit(FOLDS)).cast("int")


def fit(labelled: DataFrame, url_col: str = "url", max_labelled: int = MAX_LABELLED, rounds: int = 8, depth: int = 4) -> Model | None:
    """Fit on rows with a url and ``block`` (0 or 1); None if one kind is missing.

    Suffix statistics are of all rows.  Of more than ``max_labelled`` distinct urls those with the smallest
    hashes are taken of each kind, a tenth at least of a rare one, and weighted back to the shares of the kinds.
    """
    from pyspark.ml.classification import GBTClassifier
    from pyspark.ml.feature import VectorAssembler

    known = labelled.select(F.col(url_col).alias("url"), F.col("block").cast("double").alias("block")).where("url is not null and block is not null")
    counts = parts(known).select(F.regexp_extract("host", SUFFIX, 1).alias("suffix"), "block", _fold("url").alias("fold"))
    counts = checkpoint(counts.groupBy("suffix", "fold").agg(F.sum("block").alias("p"), F.count(F.lit(1)).alias("n")))
    total, positive = counts.agg(F.sum("n"), F.sum("p")).first()
    if not total or not 0 < positive < total:
        return None
    prior = positive / total
    suffixes = checkpoint(counts.groupBy("suffix").agg(F.sum("p").alias("p"), F.sum("n").alias("n")))
    urls = known.distinct()
    kinds = {r["block"]: r["n"] for r in urls.groupBy("block").agg(F.count(F.lit(1)).alias("n")).collect()}
    sample, every = None, sum(kinds.values())
    rare = min(min(kinds.values()), max(max_labelled * min(kinds.values()) // every, max_labelled // 10, 1))
    for block, n in sorted(kinds.items()):
        most = n if every <= max_labelled else rare if block == min(kinds, key=lambda k: (kinds[k], k)) else min(n, max(max_labelled - rare, 1))
        # Some more than needed lie under the cut (by six deviations); of these the smallest hashes stay.
        cut = min(1.0, (most + 6 * most**0.5 + 6) / n)
        place = (F.shiftright(F.xxhash64("url"), 11).cast("double") / F.lit(float(1 << 53)) + 0.5).alias("place")
        some = urls.where(F.col("block") == block).select("url", "block", place)
        some = some if cut == 1 else some.where(F.col("place") < cut)
        some = some if most == n else some.orderBy("place", "url").limit(most)
        some = some.select("url", "block", F.lit(n / most).alias("weight"))
        sample = some if sample is None else sample.unionByName(some)
    sample = checkpoint(features(parts(sample)).withColumn("fold", _fold("url")))
    # What the other folds say of the suffix.
    every_fold = suffixes.select(F.col("suffix").alias("s"), F.col("p").alias("sp"), F.col("n").alias("sn"))
    own = counts.select(F.col("suffix").alias("os"), F.col("fold").alias("of"), F.col("p").alias("op"), F.col("n").alias("on"))
    outside = sample.join(every_fold, F.col("suffix") == F.col("s"), "left").join(own, (F.col("suffix") == F.col("os")) & (F.col("fold") == F.col("of")), "left")
    outside = outside.withColumns(_rates(F.col("sp") - F.coalesce("op", F.lit(0.0)), F.col("sn") - F.coalesce("on", F.lit(0)), prior))
    ready = VectorAssembler(inputCols=list(FEATURES), outputCol="x").transform(outside).select("x", "block", "weight")
    model = GBTClassifier(featuresCol="x", labelCol="block", weightCol="weight", maxIter=rounds, maxDepth=depth, seed=7, checkpointInterval=-1).fit(ready)
    return Model(suffixes, fits(suffixes), prior, _sql_of(model.trees, list(model.treeWeights), FEATURES))


def _by_rules(pages: DataFrame, rules: Sequence[Rule], id_col: str, url_col: str) -> DataFrame:
    """page_id, url, host, path, rule, said."""
    slim = parts(pages.select(F.col(id_col).alias("page_id"), F.col(url_col).alias("url")))
    rule, said = decide(rules)
    return slim.withColumns({"rule": rule, "said": said})


def _labels(slim: DataFrame) -> DataFrame:
    return slim.where(F.col("said").isNotNull()).select("url", (F.col("said") == "block").cast("int").alias("block"))


def judge(pages: DataFrame, rules: Sequence[Rule] = RULES, labelled: DataFrame | None = None, id_col: str = "page_id", url_col: str = "url") -> DataFrame:
    """page_id, host, path, rule, verdict, margin (of the method, where it decided)."""
    slim = _by_rules(pages, rules, id_col, url_col)
    model = fit(_labels(slim) if labelled is None else labelled)
    out = slim.withColumn("margin", F.lit(0.0)) if model is None else _scored(features(slim), model)
    verdict = F.coalesce(F.col("said"), F.when(F.col("margin") > 0, F.lit("block")).otherwise(F.lit("allow")))
    return out.select("page_id", "host", "path", "rule", verdict.alias("verdict"), F.when(F.col("said").isNull(), F.col("margin")).alias("margin"))


def held_out(labelled: DataFrame, url_col: str = "url", **options: int) -> DataFrame:
    """urls, blocked, correct, found (of the blocked), accuracy and majority (the share of the larger kind) on a fifth of
    the distinct labelled urls, after a fit on the others; no row if one kind is missing among these."""
    known = labelled.select(F.col(url_col).alias("url"), F.col("block").cast("double").alias("block")).where("url is not null and block is not null").distinct()
    apart = F.pmod(F.xxhash64(F.col("url"), F.lit("held out")), F.lit(5)) == 0
    model = fit(known.where(~apart), **options)
    asked = features(parts(known.where(apart)))
    scored = asked.withColumn("margin", F.lit(None).cast("double")).limit(0) if model is None else _scored(asked, model)
    right = (F.col("margin") > 0) == (F.col("block") > 0)
    one = scored.agg(F.count(F.lit(1)).alias("urls"), F.count_if(F.col("block") > 0).alias("blocked"), F.count_if(right).alias("correct"), F.count_if(right & (F.col("block") > 0)).alias("found"))
    n = F.col("urls")
    return one.where(n > 0).withColumns({"accuracy": F.round(F.col("correct") / n, 6), "majority": F.round(F.greatest("blocked", n - F.col("blocked")) / n, 6)})


def by_rules(pages: DataFrame, rules: Sequence[Rule] = RULES, id_col: str = "page_id", url_col: str = "url") -> DataFrame:
    """page_id, host, path, rule, verdict (null where no rule fits): the part that needs no model."""
    return _by_rules(pages, rules, id_col, url_col).select("page_id", "host", "path", "rule", F.col("said").alias("verdict"))


def quality(pages: DataFrame, rules: Sequence[Rule] = RULES, id_col: str = "page_id", url_col: str = "url") -> DataFrame:
    """``held_out`` on the urls that the rules decide."""
    return held_out(_labels(_by_rules(pages, rules, id_col, url_col)))
