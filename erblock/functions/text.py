"""Column functions: tokens, grams and URI parts."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F

#: A token: a run of letters and digits.
WORD = r"[\p{L}\p{N}]+"
#: A part of a URI: the delimiters before it, and what follows up to the next ones.
PART = r"[/#?&=:.]*[^/#?&=:.]+"


def tokens(value: Column, pattern: str = WORD, lower: bool = True, min_len: int = 1) -> Column:
    """Distinct tokens of a value; null has none."""
    text = F.coalesce(value, F.lit(""))
    found = F.array_distinct(F.regexp_extract_all(F.lower(text) if lower else text, F.lit(pattern), F.lit(0)))
    return found if min_len <= 1 else F.filter(found, lambda t: F.length(t) >= min_len)


def grams(value: Column, n: int = 3) -> Column:
    """Distinct character n-grams; a shorter value is its own gram."""
    last = F.greatest(F.length(value) - (n - 1), F.lit(1))
    return F.array_distinct(F.transform(F.sequence(F.lit(1), last), lambda i: F.substring(value, i, F.lit(n))))


def uri_parts(uri: Column, pattern: str = PART) -> Column:
    """Parts of a URI, delimiters kept in front."""
    return F.regexp_extract_all(uri, F.lit(pattern), F.lit(0))


def try_ratio(num: Column, den: Column) -> Column:
    """num / den as double, null where den is 0."""
    return F.try_divide(num.cast("double"), den.cast("double"))


def harmonic(a: Column, b: Column) -> Column:
    """Harmonic mean; 0 where both are 0."""
    return F.when((a == 0) & (b == 0), F.lit(0.0)).otherwise(F.try_divide(2 * a * b, a + b))
