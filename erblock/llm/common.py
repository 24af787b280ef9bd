"""Shared pieces: words, checkpoints, vectorised hashing of texts."""

from __future__ import annotations

import ctypes
import gc
from collections.abc import Callable, Iterator

import numpy as np
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from erblock.functions.cut import BROADCAST_BYTES, checkpoint, discard, fits, written

__all__ = ["BROADCAST_BYTES", "SPACE", "WORD", "checkpoint", "discard", "fits", "keeps", "let", "light_batches", "mix64", "powers", "prefix_hash", "row_of", "settle", "shingle_hashes", "texts", "word_bounds", "words", "written"]

#: A word: a run of anything but the ASCII white space characters.
WORD = r"[^\x20\x09-\x0D]+"
#: The same white space, as a Python string for str.translate and friends.
SPACE = " \t\n\x0b\x0c\r"


def let(value: Column, body: Callable[[Column], Column]) -> Column:
    """Bind ``value`` once: an expression used many times in ``body`` is evaluated a single time."""
    return F.get(F.transform(F.array(value), body), F.lit(0))


def words(text: Column) -> Column:
    """Array of the words of a text; a null text has none."""
    return F.regexp_extract_all(F.coalesce(text, F.lit("")), F.lit(WORD), F.lit(0))


def row_of(df: DataFrame, *without: str) -> Column:
    """All columns (but some) as one struct, so that columns of any name pass beside those that an operator adds."""
    return F.struct(*[F.col("`" + c.replace("`", "``") + "`") for c in df.columns if c not in without])


#: Setting of a session, its default, and what texts that go to Python are sent in.
_BATCH, _DEFAULT, _LIGHT = "spark.sql.execution.arrow.maxBytesPerBatch", "67108864b", "8m"


def light_batches(df: DataFrame) -> DataFrame:
    """``df``; its session sends batches of at most 8 MB to Python from now on, unless it was given a bound of its own.

    A task holds a batch several times over (in the JVM, on the way and in Python), and 10,000 texts make tens of MB.
    """
    conf = df.sparkSession.conf
    if conf.get(_BATCH, None) == _DEFAULT:
        conf.set(_BATCH, _LIGHT)
    return df


#: By module, what drops the tables that its tasks leave in a worker for later ones; the module whose task came last.
_KEPT: dict[str, Callable[[], None]] = {}
_LAST: list[str] = []


def keeps(module: str, drop: Callable[[], None]) -> None:
    """Tasks of ``module`` leave tables in their worker; ``drop`` lets them go."""
    _KEPT[module] = drop


def settle(module: str) -> None:
    """To be called first by a task in Python.  Workers serve one operator after the other: what others' tasks left is dropped,
    and memory that is free goes back to the system, as all workers of an executor count towards its bound."""
    import pyarrow as pa

    if _LAST != [module]:
        for other, drop in _KEPT.items():
            if other != module:
                drop()
        gc.collect()
        _LAST[:] = [module]
    pa.default_memory_pool().release_unused()
    trim = getattr(ctypes.CDLL(None), "malloc_trim", None)  # glibc has it
    if trim:
        trim(0)


# ---------------------------------------------------------------- numpy hashing of byte strings

_BASE = np.uint64(0x9E3779B97F4A7C15)  # odd, so it has an inverse modulo 2**64
_INV = np.uint64(pow(int(_BASE), -1, 1 << 64))
_POW: dict[str, np.ndarray] = {}


def powers(n: int) -> tuple[np.ndarray, np.ndarray]:
    """base**i and base**-i modulo 2**64 for i < n, kept for the next call."""
    have = _POW.get("up")
    if have is None or len(have) < n:
        size = max(n, 1 << 16)
        with np.errstate(over="ignore"):
            for name, b in (("up", _BASE), ("down", _INV)):
                x = np.full(size, b, dtype=np.uint64)
                x[0] = 1
                _POW[name] = np.multiply.accumulate(x)
    return _POW["up"][:n], _POW["down"][:n]


def mix64(x: np.ndarray) -> np.ndarray:
    """Finaliser of splitmix64: spreads a 64-bit key evenly."""
    with np.errstate(over="ignore"):
        x = x ^ (x >> np.uint64(30))
        x = x * np.uint64(0xBF58476D1CE4E5B9)
        x = x ^ (x >> np.uint64(27))
        x = x * np.uint64(0x94D049BB133111EB)
        return x ^ (x >> np.uint64(31))


def prefix_hash(data: np.ndarray) -> np.ndarray:
    """P with P[j] - P[i] = base**i * hash(data[i:j]); bytes count as value + 1."""
    up, _ = powers(len(data))
    out = np.zeros(len(data) + 1, dtype=np.uint64)
    with np.errstate(over="ignore"):
        np.cumsum((data.astype(np.uint64) + np.uint64(1)) * up, out=out[1:])
    return out


def word_bounds(data: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Starts and ends of the words in UTF-8 bytes."""
    space = np.ones(len(data) + 2, dtype=bool)
    np.logical_or(data == 32, (data >= 9) & (data <= 13), out=space[1:-1])
    edge = np.flatnonzero(space[1:] != space[:-1])
    return edge[0::2], edge[1::2]


def shingle_hashes(text: bytes, n: int = 5) -> np.ndarray:
    """Sorted distinct 64-bit hashes of the n-word shingles; a shorter text counts as one shingle."""
    data = np.frombuffer(text, dtype=np.uint8)
    a, b = word_bounds(data)
    if not len(a):
        return np.empty(0, dtype=np.uint64)
    p = prefix_hash(data)
    _, down = powers(len(data) + 1)
    with np.errstate(over="ignore"):
        w = mix64((p[b] - p[a]) * down[a])
        k = min(n, len(w))
        s = np.zeros(len(w) - k + 1, dtype=np.uint64)
        for j in range(k):
            s = s * np.uint64(0xD6E8FEB86659FD93) + w[j : len(w) - k + 1 + j]
    return np.unique(mix64(s + np.uint64(k)))


def texts(batches: Iterator, name: str) -> Iterator:
    """(batch, iterator of Python values of one string column, null as '') of Arrow batches."""
    for batch in batches:
        col = batch.column(batch.schema.get_field_index(name))
        yield batch, ((v.as_py() or "") for v in col)
