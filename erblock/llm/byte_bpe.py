"""Byte-level BPE encoding and decoding with a hierarchical-bitmap rank queue.

A pre-token's bytes form a linked list.  Every adjacent pair that is a vocabulary entry lies in the
bucket of its rank; two levels of wide words say which buckets are filled, so the next rank is
two find-first-set steps away however long the pre-token is.  Entries are never searched for and
removed: a popped position whose pair has changed since is skipped.  Within a rank the leftmost
position goes first.  Encoding n bytes takes O(n log n) at worst (the heap inside one bucket), so a
pre-token of a megabyte is no problem.

Pre-tokens repeat, so each worker keeps a bounded table of those already encoded.

Edge cases: null text is encoded as an empty one (no tokens); ids may be null or repeat; white
space only, invalid or very long pre-tokens are ordinary; extra columns are ignored.
"""

from __future__ import annotations

import base64
import hashlib
from collections.abc import Iterator
from heapq import heappop, heappush
from itertools import chain, pairwise

from pyspark.sql import DataFrame
from pyspark.sql import types as T

from erblock.llm.common import keeps, light_batches, settle

#: Fixed value: the pattern under which a lone space always belongs to what follows it.
SPACE_FIRST = r"""'s|'t|'re|'ve|'m|'ll|'d| ?\p{L}+| ?\p{N}+| ?[^\s\p{L}\p{N}]+|\s+(?!\S)|\s+"""
#: Entries of each table (pre-tokens, chunks) of a worker; what comes later is merged anew (speed only).
CACHE = 500_000
#: Longer pre-tokens (characters) aren't kept.
CACHE_CHARS = 64
#: Binary logarithm of the bits in a word of the bitmap, and the mask of a bit's number.
WORD = 8
LOW_BITS = (1 << WORD) - 1
#: Bytes up to which a pre-token's list is a copy of the beginning of a ready one.
SHORT = 64
AFTER, BEFORE = list(range(1, SHORT + 1)), list(range(-1, SHORT - 1))


class ByteBPE:
    """Encoder and decoder of a rank table and the pattern that makes pre-tokens."""

    def __init__(self, ranks: dict[bytes, int], pattern: str):
        import regex

        self.ranks = ranks
        self.table = [b""] * (max(ranks.values()) + 1)
        for b, i in ranks.items():
            self.table[i] = b
        self.split = regex.compile(pattern).findall
        self.low = [0] * ((len(self.table) >> WORD) + 1)
        self.bits = [1 << b for b in range(max(LOW_BITS + 1, len(self.low)))]
        self.two = [ranks.get(bytes((a, b)), -1) for a in range(256) for b in range(256)]  # ranks of two bytes
        self.known: dict[str, tuple[int, ...]] = {}
        self.chunks = _Chunks(self)
        self.by_space = pattern == SPACE_FIRST

    @classmethod
    def from_file(cls, path: str, pattern: str) -> ByteBPE:
        with open(path, "rb") as f:
            return cls({base64.b64decode(a): int(b) for a, b in (line.split() for line in f if line.strip())}, pattern)

    def merge(self, piece: bytes) -> tuple[int, ...]:
        """Ids of one pre-token.

        The queue is inlined: ``buckets`` holds a position or a heap of several for each rank, bit b of ``low[a]`` says that
        rank ``a << WORD | b`` has one, and bit a of ``top`` that ``low[a]`` isn't zero.  ``low`` is all zero between calls;
        entries that are stale when no pair is ``live`` any more are dropped together.
        """
        ranks = self.ranks
        whole = ranks.get(piece)
        if whole is not None:
            return (whole,)
        rank_of, bits, low, two = ranks.get, self.bits, self.low, self.two
        n, top = len(piece), 0
        after = list(range(1, n + 1)) if n > SHORT else AFTER[:n]  # start of the next symbol
        before = list(range(-1, n - 1)) if n > SHORT else BEFORE[:n]
        pair = [two[a << 8 | b] for a, b in pairwise(piece)]  # rank of the pair that starts here, -1: none
        live = n - 1 - pair.count(-1)
        pair.append(-1)
        buckets: dict[int, int | list[int]] = {}
        for i, r in enumerate(pair):
            if r < 0:
                continue
            if r in buckets:
                old = buckets[r]
                if old.__class__ is int:
                    buckets[r] = [old, i]  # positions come in order, which is a heap
                else:
                    old.append(i)
            else:
                buckets[r] = i
                a = r >> WORD
                low[a] |= bits[r & LOW_BITS]
                top |= bits[a]
        only = -1  # the one live pair, if it is new: nothing lies before it in the queue
        while live:
            if only >= 0:
                i, only = only, -1
            else:
                a = (top & -top).bit_length() - 1
                word = low[a]
                first = word & -word
                r = a << WORD | (first.bit_length() - 1)
                i = buckets[r]
                if i.__class__ is int:
                    del buckets[r]
                    word ^= first
                    low[a] = word
                    if not word:
                        top &= top - 1
                else:
                    bucket = i
                    i = heappop(bucket)
                    if len(bucket) == 1:
                        buckets[r] = bucket[0]
                if pair[i] != r:
                    continue  # stale
            j = after[i]
            k = after[i] = after[j]
            live -= 1
            if pair[j] >= 0:
                live -= 1
                pair[j] = -1
            if k < n:
                before[k] = i
                right = pair[i] = rank_of(piece[i : after[k]], -1)
                if right >= 0:
                    live += 1
            else:
                right = pair[i] = -1
            p = before[i]
            if p >= 0:
                left = rank_of(piece[p:k], -1)
                was = pair[p]
                if left == was:
                    left = -1
                else:
                    if was >= 0:
                        live -= 1
                    pair[p] = left
                    if left >= 0:
                        live += 1
            else:
                left = -1
            if live == 1 and (left >= 0 or right >= 0):
                only = i if right >= 0 else p
                continue
            if right >= 0:
                if right in buckets:
                    old = buckets[right]
                    if old.__class__ is int:
                        buckets[right] = [old, i] if old < i else [i, old]
                    else:
                        heappush(old, i)
                else:
                    buckets[right] = i
                    a = right >> WORD
                    low[a] |= bits[right & LOW_BITS]
                    top |= bits[a]
            if left >= 0:
                if left in buckets:
                    old = buckets[left]
                    if old.__class__ is int:
                        buckets[left] = [old, p] if old < p else [p, old]
                    else:
                        heappush(old, p)
                else:
                    buckets[left] = p
                    a = left >> WORD
                    low[a] |= bits[left & LOW_BITS]
                    top |= bits[a]
        for r in buckets:
            low[r >> WORD] = 0
        out = []
        i = 0
        while i < n:
            k = after[i]
            out.append(ranks[piece[i:k]])
            i = k
        return tuple(out)

    def pretokens(self, text: str) -> list[int]:
        """Ids by splitting the whole text with the pattern."""
        return self.each(self.split(text))

    def each(self, pieces: list[str]) -> list[int]:
        """Ids of pre-tokens."""
        known, chunks, out = self.known, self.chunks, []
        for x in pieces:
            # A pre-token behind a space is kept with the chunks, as the chunk that it is.
            table, key = (chunks, x[1:]) if x[0] == " " and len(x) > 1 and not x[1].isspace() and not x[-1].isspace() else (known, x)
            ids = table.get(key)
            if ids is None:
                ids = self.merge(x.encode())
                if len(x) <= CACHE_CHARS and len(table) < CACHE:
                    table[key] = ids
            out.extend(ids)
        return out

    def encode(self, text: str) -> list[int]:
        """Ids of a text.

        With ``by_space`` a single space between characters that aren't white space always opens a pre-token,
        so such a text is cut there without the pattern, and each chunk looked up.
        """
        if not self.by_space:
            return self.pretokens(text)
        first, *rest = text.split(" ")
        if first and (first[0].isspace() or first[-1].isspace()):
            return self.pretokens(text)
        try:
            return self.pretokens(first) + list(chain.from_iterable(map(self.chunks.__getitem__, rest)))
        except _NotAlone:
            return self.pretokens(text)

    def decode(self, ids: list[int]) -> bytes:
        return b"".join(map(self.table.__getitem__, ids))


class _NotAlone(Exception):
    """A chunk that borders on other white space."""


class _Chunks(dict):
    """Ids of a space and the chunk behind it."""

    def __init__(self, bpe: ByteBPE):
        super().__init__()
        self.bpe = bpe

    def __missing__(self, chunk: str) -> tuple[int, ...]:
        if not chunk or chunk[0].isspace() or chunk[-1].isspace():
            raise _NotAlone
        # Letters alone are one pre-token; a chunk that is one is kept here alone.
        pieces = [" " + chunk] if chunk.isascii() and chunk.isalpha() else self.bpe.split(" " + chunk)
        ids = self.bpe.merge(pieces[0].encode()) if len(pieces) == 1 else tuple(self.bpe.each(pieces))
        if len(chunk) <= CACHE_CHARS and len(self) < CACHE:
            self[chunk] = ids
        return ids


_LOADED: dict[tuple[str, str], ByteBPE] = {}


def tokenizer(path: str, pattern: str) -> ByteBPE:
    """The tokenizer of this process; read once."""
    if (path, pattern) not in _LOADED:
        _LOADED[path, pattern] = ByteBPE.from_file(path, pattern)
    return _LOADED[path, pattern]


keeps("byte_bpe", _LOADED.clear)


def encode_documents(docs: DataFrame, path: str, pattern: str, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """doc_id, ids array<int> of each text."""
    schema = T.StructType([T.StructField("doc_id", docs.schema[id_col].dataType), T.StructField("ids", T.ArrayType(T.IntegerType()))])

    def run(batches: Iterator) -> Iterator:
        import pyarrow as pa

        settle("byte_bpe")
        bpe = tokenizer(path, pattern)
        for batch in batches:
            for lo in range(0, batch.num_rows, 512):
                part = batch.slice(lo, 512)
                ids = [bpe.encode(v.as_py() or "") for v in part.column(1)]
                yield pa.RecordBatch.from_arrays([part.column(0), pa.array(ids, type=pa.list_(pa.int32()))], names=["doc_id", "ids"])

    return light_batches(docs.select(id_col, text_col)).mapInArrow(run, schema)


def decode_documents(encoded: DataFrame, path: str, pattern: str) -> DataFrame:
    """doc_id, data binary: the bytes that the ids stand for."""
    schema = T.StructType([T.StructField("doc_id", encoded.schema["doc_id"].dataType), T.StructField("data", T.BinaryType())])

    def run(batches: Iterator) -> Iterator:
        import pyarrow as pa

        settle("byte_bpe")
        bpe = tokenizer(path, pattern)
        for batch in batches:
            for lo in range(0, batch.num_rows, 512):
                part = batch.slice(lo, 512)
                data = [bpe.decode(v.as_py() or []) for v in part.column(1)]
                yield pa.RecordBatch.from_arrays([part.column(0), pa.array(data, type=pa.binary())], names=["doc_id", "data"])

    return encoded.select("doc_id", "ids").mapInArrow(run, schema)


def digests(docs: DataFrame, path: str, pattern: str, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """Per document the token count and the digests of its ids and of what they decode to.

    The same encoder and decoder, in one pass, so that ids needn't travel between processes.
    """
    schema = T.StructType(
        [T.StructField("doc_id", docs.schema[id_col].dataType), T.StructField("n_tokens", T.LongType()), T.StructField("ids_sha256", T.StringType()), T.StructField("decoded_sha256", T.StringType())]
    )

    def run(batches: Iterator) -> Iterator:
        import pyarrow as pa

        settle("byte_bpe")
        bpe = tokenizer(path, pattern)
        shown = [str(i) for i in range(len(bpe.table))]
        for batch in batches:
            n, a, b = [], [], []
            for v in batch.column(1):
                ids = bpe.encode(v.as_py() or "")
                n.append(len(ids))
                a.append(hashlib.sha256(" ".join(map(shown.__getitem__, ids)).encode()).hexdigest())
                b.append(hashlib.sha256(bpe.decode(ids)).hexdigest())
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(n, type=pa.int64()), pa.array(a, type=pa.string()), pa.array(b, type=pa.string())], names=schema.names)

    return light_batches(docs.select(id_col, text_col)).mapInArrow(run, schema)
