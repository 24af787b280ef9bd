"""Quality rules as a bitmask ledger (native: DataFrame functions only).

Every rule is evaluated once per document; its measurement and one failure bit go to the
ledger.  A *policy* is a versioned set of bits: applying one, comparing two or asking what a
rule alone rejects are bit operations on the ledger and never touch the text again.

Edge cases: a null text counts as empty (no words, fails ``few_words``); ids may be null or
repeat, rows are judged one by one; other columns are passed through by ``ledger``, but for those named as one of
``MEASURES`` or ``fail_bits``, which the ledger's own replace (``kept_rows`` passes all); an empty table gives an empty one.
The work per text is O(n log n) in its words and needs no shuffle.
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from erblock.llm.common import WORD, let, row_of, words

MEASURES = ("n_words", "word_chars", "n_symbols", "n_lines", "n_dup_lines", "n_repeat_words")
WINDOW = 5


@dataclass(frozen=True)
class Rule:
    """One rule: its bit and the SQL condition on the measurements under which a text fails."""

    name: str
    bit: int
    fails: str


RULES = (
    Rule("few_words", 0, "n_words < 10"),
    Rule("repeated_windows", 1, "100 * n_repeat_words > 20 * n_words"),
    Rule("symbols", 2, "10 * n_symbols > n_words"),
    Rule("duplicate_lines", 3, "10 * n_dup_lines > 3 * n_lines"),
    Rule("word_length", 4, "word_chars < 2 * n_words or word_chars > 20 * n_words"),
)


@dataclass(frozen=True)
class Policy:
    """A version and the rules that it enforces."""

    version: str
    rules: tuple[str, ...]

    @property
    def mask(self) -> int:
        return sum(1 << r.bit for r in RULES if r.name in self.rules)


BASE = Policy("base", ("few_words", "repeated_windows"))
PRODUCTION = Policy("v1", tuple(r.name for r in RULES))


def _repeat_words(ws: Column) -> Column:
    """Words that lie in a window of five words found twice or more in the text.

    Hash every window, and only if two agree sort (hash, place), keep the places whose hash has a
    neighbour that equals it, and add up how far each such place reaches before the next one.
    """
    n = F.size(ws)

    def covered(wins: Column) -> Column:
        pairs = F.sort_array(F.transform(wins, lambda h, i: F.struct(h.alias("h"), i.alias("i"))))

        def places(s: Column) -> Column:
            same = F.filter(
                s,
                lambda x, k: ((k > 0) & (F.get(s, k - 1)["h"] == x["h"]))
                | ((k + 1 < F.size(s)) & (F.get(s, k + 1)["h"] == x["h"])),
            )
            return F.sort_array(F.transform(same, lambda x: x["i"]))

        def reach(at: Column) -> Column:
            steps = F.transform(at, lambda p, k: F.least(F.lit(WINDOW), F.coalesce(F.get(at, k + 1) - p, F.lit(WINDOW))))
            return F.aggregate(steps, F.lit(0), lambda acc, x: acc + x)

        return let(pairs, lambda s: let(places(s), reach))

    wins = F.transform(F.sequence(F.lit(0), n - WINDOW), lambda i: F.xxhash64(*[F.get(ws, i + j) for j in range(WINDOW)]))
    return F.when(
        n > WINDOW,
        let(wins, lambda w: F.when(F.size(F.array_distinct(w)) == F.size(w), F.lit(0)).otherwise(covered(w))),
    ).otherwise(F.lit(0))


def measures(text: Column) -> Column:
    """Struct with the fields of MEASURES."""
    t = F.coalesce(text, F.lit(""))
    lines = F.filter(F.split(t, "\n", -1), lambda x: x.rlike(WORD))

    def both(ws: Column) -> Column:
        return let(
            lines,
            lambda ls: F.struct(
                F.size(ws).cast("long").alias("n_words"),
                F.length(F.array_join(ws, "")).cast("long").alias("word_chars"),
                F.length(F.regexp_replace(t, r"[^#*$%&|<>]+", "")).cast("long").alias("n_symbols"),
                F.size(ls).cast("long").alias("n_lines"),
                (F.size(ls) - F.size(F.array_distinct(ls))).cast("long").alias("n_dup_lines"),
                _repeat_words(ws).cast("long").alias("n_repeat_words"),
            ),
        )

    return let(words(text), both)


def ledger(docs: DataFrame, text_col: str = "text") -> DataFrame:
    """The columns of ``docs`` with the measurements and the failure bits of all rules."""
    own = {*MEASURES, "fail_bits"}
    others = [F.col("`" + c.replace("`", "``") + "`") for c in docs.columns if c.lower() not in own]
    measured = docs.select(F.struct(*others).alias("row") if others else F.lit(None).alias("row"), measures(F.col(text_col)).alias("m"))
    bits = " + ".join(f"if({r.fails}, {1 << r.bit}L, 0L)" for r in RULES)
    return measured.select(*(["row.*"] if others else []), "m.*").withColumn("fail_bits", F.expr(bits))


def kept_rows(docs: DataFrame, policy: Policy = PRODUCTION, text_col: str = "text") -> DataFrame:
    """The rows of ``docs`` that the policy keeps, unchanged."""
    led = ledger(docs.select(row_of(docs).alias("row"), F.col(text_col).alias("text")))
    return led.where(passes(policy)).select("row.*")


def passes(policy: Policy, bits: Column | None = None) -> Column:
    return (F.col("fail_bits") if bits is None else bits).bitwiseAND(F.lit(policy.mask)) == 0


def apply_policy(led: DataFrame, policy: Policy = PRODUCTION) -> DataFrame:
    """Ledger with ``policy`` (its version) and ``kept``."""
    return led.withColumn("policy", F.lit(policy.version)).withColumn("kept", passes(policy))


def ablations(led: DataFrame, policy: Policy = PRODUCTION) -> DataFrame:
    """A row per rule of the policy: documents that fail it, and that only it rejects.

    One pass: conditional counts over the bits, then a pivot of one row.
    """
    held = F.col("fail_bits").bitwiseAND(F.lit(policy.mask))
    used = [r for r in RULES if r.name in policy.rules]
    one = led.agg(
        F.count(F.lit(1)).alias("n"),
        *[F.count_if(held.bitwiseAND(F.lit(1 << r.bit)) != 0).alias(f"f{r.bit}") for r in used],
        *[F.count_if(held == (1 << r.bit)).alias(f"s{r.bit}") for r in used],
    )
    rows = F.array(*[F.struct(F.lit(r.name).alias("rule"), F.col(f"f{r.bit}").alias("n_failed"), F.col(f"s{r.bit}").alias("n_only")) for r in used])
    return one.select(F.lit(policy.version).alias("policy"), "n", F.explode(rows).alias("x")).select("policy", "n", "x.*")


def patterns(led: DataFrame) -> DataFrame:
    """Documents per combination of failure bits: enough to replay any policy without the texts."""
    return led.groupBy("fail_bits").agg(F.count(F.lit(1)).alias("n_docs"), F.sum("n_words").alias("n_words"))
