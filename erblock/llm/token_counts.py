"""Token counts for a sentence-piece BPE vocabulary with the whole-token shortcut.

*Pre-tokens.*  The library turns spaces into U+2581, puts one in front and merges over the whole
text, best score first.  A merge never joins two characters that are adjacent in no vocabulary
string, so a text may be cut before every U+2581 that follows another character if no entry
holds that pair (checked when the model is read).  Each cut piece, a *pre-token*, is counted alone.

*Whole tokens.*  Once per process, each vocabulary string is encoded by merging; those which come
out as themselves are proven to be one token wherever they are a whole pre-token.  They are
counted by look-up; only the rest is merged, and kept in a bounded table.

Edge cases: null text is empty (0 tokens, 0 bytes); an empty text has no tokens; ids may be null or
repeat; special strings in a text are ordinary characters; characters that the vocabulary
lacks count their UTF-8 bytes; very long pre-tokens are merged with a heap in O(n log n).
"""

from __future__ import annotations

import re
from collections.abc import Iterator
from heapq import heapify, heappop, heappush

from pyspark.sql import DataFrame
from pyspark.sql import types as T

MARK = "▁"
#: Entries of the table of merged pre-tokens of a worker; later ones are merged anew (speed only).
CACHE = 400_000
CACHE_CHARS = 64


class PieceCounter(dict):
    """Maps a pre-token (without its first mark) to its token count."""

    def __init__(self, pieces: list[tuple[str, float]], byte_fallback: bool = True):
        super().__init__()
        self.rank = {p: i for i, (p, _) in enumerate(sorted(pieces, key=lambda x: -x[1]))}
        self.byte_fallback = byte_fallback
        if any(re.search(f"[^{MARK}]{MARK}", p) for p in self.rank):
            raise ValueError("this vocabulary merges across word starts")
        #: strings (without their mark) proven to be one token when they are a whole pre-token
        self.whole = {p[1:]: 1 for p in self.rank if p[0] == MARK and self.merge(p) == 1}
        self.update(self.whole)
        self.pre = re.compile(f"{MARK}+[^{MARK}]*").findall

    @classmethod
    def from_file(cls, path: str) -> PieceCounter:
        import sentencepiece as sp

        m = sp.SentencePieceProcessor(model_file=path)
        ids = [i for i in range(m.get_piece_size()) if not (m.is_control(i) or m.is_unknown(i) or m.is_byte(i) or m.is_unused(i))]
        if m.encode(" a  b ") != m.encode(f"{MARK}a{MARK}{MARK}b{MARK}"):
            raise ValueError("only models that keep white space as it is are supported")
        return cls([(m.id_to_piece(i), m.get_score(i)) for i in ids])

    def merge(self, piece: str) -> int:
        """Tokens of a pre-token by merging its best pair, leftmost first, until none is left."""
        rank, n = self.rank, len(piece)
        after, before = list(range(1, n + 1)), list(range(-1, n - 1))
        alive = [True] * n
        heap = [(rank[piece[i : i + 2]], i, i + 2) for i in range(n - 1) if piece[i : i + 2] in rank]
        heapify(heap)
        while heap:
            _, i, end = heappop(heap)
            if not alive[i]:
                continue
            j = after[i]
            if j >= n or after[j] != end:
                continue  # stale
            after[i] = end
            alive[j] = False
            if end < n:
                before[end] = i
                x = piece[i : after[end]]
                if x in rank:
                    heappush(heap, (rank[x], i, after[end]))
            p = before[i]
            if p >= 0:
                x = piece[p:end]
                if x in rank:
                    heappush(heap, (rank[x], p, end))
        count = i = 0
        while i < n:
            x = piece[i : after[i]]
            count += 1 if x in rank else (len(x.encode("utf-8", "surrogatepass")) if self.byte_fallback else 1)
            i = after[i]
        return count

    def __missing__(self, key: str) -> int:
        n = self.merge(MARK + key)
        if len(key) <= CACHE_CHARS and len(self) < CACHE + len(self.whole):
            self[key] = n
        return n

    def count(self, text: str) -> int:
        if not text:
            return 0
        if MARK in text:
            text = text.replace(MARK, " ")
        if "  " in text or text[0] == " " or text[-1] == " ":  # a pre-token may have several marks
            return sum(self[p[1:]] for p in self.pre(MARK + text.replace(" ", MARK)))
        return sum(map(self.__getitem__, text.split(" ")))


_LOADED: dict[str, PieceCounter] = {}


def counter(path: str) -> PieceCounter:
    if path not in _LOADED:
        _LOADED[path] = PieceCounter.from_file(path)
    return _LOADED[path]


def token_counts(docs: DataFrame, path: str, limit: int = 4096, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """doc_id, n_bytes, n_tokens and over_limit (n_tokens > limit) of each document."""
    schema = T.StructType(
        [T.StructField("doc_id", docs.schema[id_col].dataType), T.StructField("n_bytes", T.LongType()), T.StructField("n_tokens", T.LongType()), T.StructField("over_limit", T.BooleanType())]
    )

    def run(batches: Iterator) -> Iterator:
        import pyarrow as pa
        import pyarrow.compute as pc

        c = counter(path)
        for batch in batches:
            col = batch.column(1)
            n = pa.array([c.count(v.as_py() or "") for v in col], type=pa.int64())
            size = pc.fill_null(pc.binary_length(col), 0).cast(pa.int64())
            yield pa.RecordBatch.from_arrays([batch.column(0), size, n, pc.greater(n, limit)], names=schema.names)

    return docs.select(id_col, text_col).mapInArrow(run, schema)
