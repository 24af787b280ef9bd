"""Removal of byte strings that repeat anywhere in the corpus, by external induced suffix sorting.

What must go: each byte inside a string of ``length`` bytes that also starts at another place.

*Samples.*  Suffix sorting of the whole corpus would move every byte many times.  Induced sorting sorts a
locally consistent sample of the suffixes and derives the others from it; here the sample is chosen
so that it also prunes: of each window of ``length`` bytes the leftmost least hash of a 16-byte gram is
the window's *anchor*.  Equal windows have equal anchors at equal offsets.  The windows of an anchor are halved by the
offset of the anchor, and all windows of a half share about half their bytes: the half's *key* is a hash of these, and
a window whose key occurs once cannot repeat.  Only texts around keys that occur twice or more are moved.

*Keys.*  Tasks count their keys before they hand them on: a key that a task meets twice is known to repeat, its rows are
spread and one row with the count stands for them.  So a key has at most a row per task where keys are counted.

*Shards.*  The bytes around an anchor (its *context*: the windows of one half, at most 1.5 * length bytes)
go to the shard of its key.  Equal contexts are merged with their number before they travel.  Contexts
of very frequent keys are cut by blocks of ``SPLIT`` offsets, and the blocks are split by a hash of the bytes that all
their windows share, so a hot key stays together only as far as its texts agree on almost a whole window.

*Sorting.*  In a shard the suffixes at the anchors are sorted through a disk-backed priority queue (sorted
runs of bounded size, merged), which also yields the common prefix of neighbours.  Then the suffixes
one byte further left are induced from these, and again from the result, recursively: a suffix is ordered by its first byte and
the rank of the suffix after it, so dealing suffixes in order to a queue per byte sorts them, and the common prefix of two new
neighbours that start with the same byte is one more than the least common prefix between their successors.
A window repeats if a neighbour shares ``length`` bytes or its context occurs more than once.

Contexts reach a shard's task in order, so equal ones are neighbours and none is looked up.  Small groups are sorted many
at a time in arrays.  A group whose contexts exceed a bound is never held: its bytes lie in a file, its suffix tuples (context, common
prefix with the one before) stream from queue to queue, a chunk at a time, and the queues go to disk beyond a memory bound.

Results are joined back to the texts that hold the contexts, and cut out.  Texts are named by 128 bits, contexts by 128 bits;
keys have 64, but a clash of keys costs work only.

Edge cases: null text is empty; texts shorter than ``length`` keep all bytes; ids may be null or repeat, rows are
separate occurrences; overlapping matches inside one text count; texts whose bytes are one long run or very
long are handled in linear time; extra columns of any name are ignored (``with_text`` keeps them in ``row``).
"""

from __future__ import annotations

import hashlib
import heapq
import os
import pickle
import tempfile
from collections.abc import Iterator

import numpy as np
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F
from pyspark.sql import types as T

from erblock.llm.common import discard, fits, light_batches, mix64, powers, prefix_hash, row_of, settle, written

LENGTH, GRAM = 200, 16
#: Keys that occur more often than this have their contexts cut by blocks of SPLIT offsets.
HOT, SPLIT = 2000, 8
#: Bytes of contexts that a task merges before it hands them on; texts whose names a task remembers.
CONTEXT_BYTES, REMEMBERED = 12 << 20, 200_000
#: Keys that a task counts together.
COUNTED = 150_000
#: Bytes of an array above which it is mapped to disk, and of the suffixes a sorted run of the queue holds.
MEMORY_BYTES, RUN_BYTES = 32 << 20, 32 << 20
#: Contexts that are sorted together (whole anchors; a larger anchor is a chunk of its own).
CHUNK = 40_000
#: Bytes of the contexts of one group (with their overhead) above which it goes through the disk-backed queue window by window.
GROUP_BYTES = 32 << 20


# ---------------------------------------------------------------- anchors


def keys(data: np.ndarray, length: int = LENGTH) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """(key, first window, offset of the anchor in it, windows less one) of each half of each anchor of a text."""
    out = []
    step = 1 << 19  # windows per piece: places inside a piece fit the low 20 bits
    last = len(data) - length + 1
    for lo in range(0, last, step):
        hi = min(lo + step, last)
        key, at, o, w = _halves(data[lo : hi + length - 1], length)
        out.append((key, at + lo, o, w))
    if not out:
        return tuple(np.empty(0, np.int64) for _ in range(4))
    return tuple(np.concatenate(x) for x in zip(*out, strict=True))


def _halves(data: np.ndarray, length: int) -> tuple[np.ndarray, ...]:
    a, b, p = _anchors(data, length)
    half = (length - GRAM) // 2
    prefix = prefix_hash(data)
    down = powers(len(data) + 1)[1]

    def key(start: np.ndarray, size: int, side: int) -> np.ndarray:
        with np.errstate(over="ignore"):
            return mix64((prefix[start + size] - prefix[start]) * down[start] + np.uint64(side)).view(np.int64)

    # Windows that start at most ``half`` bytes before the anchor share the bytes from it on, the others those up to its end.
    right, left = p - b <= half, p - a > half
    ra, la = np.maximum(a, p - half)[right], a[left]
    return (
        np.concatenate([key(p[right], length - half, 0), key(p[left] - half - 1, half + 1 + GRAM, 1)]),
        np.concatenate([ra, la]),
        np.concatenate([p[right] - ra, p[left] - la]),
        np.concatenate([b[right] - ra, np.minimum(b, p - half - 1)[left] - la]),
    )


def _anchors(data: np.ndarray, length: int) -> tuple[np.ndarray, ...]:
    raw = np.ascontiguousarray(data)
    words = np.ndarray((len(raw) - 7,), dtype="<u8", buffer=raw.data, strides=(1,)).copy()
    with np.errstate(over="ignore"):
        h = words[:-8] * np.uint64(0x9E3779B97F4A7C15) + (words[8:] ^ np.uint64(0x5851F42D4C957F2D)) * np.uint64(0xD6E8FEB86659FD93)
    h = mix64(h)
    v = (h & ~np.uint64(0xFFFFF)) | np.arange(len(h), dtype=np.uint64)
    span, width = 1, length - GRAM + 1
    least = v
    while span * 2 <= width:
        least = np.minimum(least[:-span], least[span:])
        span *= 2
    if width > span:
        n = len(v) - width + 1
        least = np.minimum(least[:n], least[width - span : width - span + n])
    place = (least & np.uint64(0xFFFFF)).astype(np.int64)
    cut = np.flatnonzero(np.diff(place))
    a = np.concatenate([[0], cut + 1])
    b = np.concatenate([cut, [len(place) - 1]])
    return a, b, place[a]


# ---------------------------------------------------------------- external sorting and induction


class DiskQueue:
    """Priority queue of (group, suffix bytes, number): sorted runs on disk, merged on the way out."""

    def __init__(self, run_bytes: int = RUN_BYTES):
        self.run_bytes, self.held, self.size, self.runs = run_bytes, [], 0, []
        self.dir: tempfile.TemporaryDirectory | None = None

    def push(self, group: int, suffix: bytes, number: int) -> None:
        self.held.append((group, suffix, number))
        self.size += len(suffix) + 100
        if self.size > self.run_bytes:
            self._spill()

    def _spill(self) -> None:
        self.dir = self.dir or tempfile.TemporaryDirectory(prefix="suffix-runs-")
        path = os.path.join(self.dir.name, str(len(self.runs)))
        self.held.sort()
        with open(path, "wb") as f:
            for lo in range(0, len(self.held), 4096):
                pickle.dump(self.held[lo : lo + 4096], f, protocol=5)
        self.runs.append(path)
        self.held, self.size = [], 0

    @staticmethod
    def _read(path: str) -> Iterator[tuple[int, bytes, int]]:
        with open(path, "rb") as f:
            while True:
                try:
                    yield from pickle.load(f)
                except EOFError:
                    return

    def drain(self) -> Iterator[tuple[int, bytes, int]]:
        """All entries in order."""
        self.held.sort()
        yield from heapq.merge(*map(self._read, self.runs), self.held) if self.runs else self.held
        self.held = []
        if self.dir:
            self.dir.cleanup()


class Scratch:
    """Arrays in memory, or mapped to files beyond a bound."""

    def __init__(self, memory_bytes: int = MEMORY_BYTES):
        self.memory_bytes = memory_bytes
        self.dir: tempfile.TemporaryDirectory | None = None
        self.n = 0

    def array(self, shape: tuple[int, ...], dtype: type) -> np.ndarray:
        if int(np.prod(shape)) * np.dtype(dtype).itemsize <= self.memory_bytes:
            return np.zeros(shape, dtype=dtype)
        self.dir = self.dir or tempfile.TemporaryDirectory(prefix="suffix-arrays-")
        self.n += 1
        return np.memmap(os.path.join(self.dir.name, str(self.n)), dtype=dtype, mode="w+", shape=shape)

    def close(self) -> None:
        if self.dir:
            self.dir.cleanup()


def _range_min(values: np.ndarray, lo: np.ndarray, hi: np.ndarray) -> np.ndarray:
    """Least of values[lo:hi] for every pair (hi > lo), by doubling."""
    span = hi - lo
    level = np.zeros(len(span), dtype=np.int64)
    most = int(span.max()) if len(span) else 0
    tables = [values]
    while (1 << len(tables)) <= most:
        prev, half = tables[-1], 1 << (len(tables) - 1)
        tables.append(np.minimum(prev[:-half], prev[half:]))
    for k in range(1, len(tables)):
        level += span >= (1 << k)
    out = np.empty(len(span), dtype=values.dtype)
    for k, table in enumerate(tables):
        at = np.flatnonzero(level == k)
        out[at] = np.minimum(table[lo[at]], table[hi[at] - (1 << k)])
    return out


def repeated_windows(contexts: list[tuple[int, int, bytes, int]], length: int = LENGTH, run_bytes: int = RUN_BYTES, memory_bytes: int = MEMORY_BYTES) -> list[list[tuple[int, int]]]:
    """Of each context (group, place of its anchor, bytes, times) the maximal runs [first, last] of
    windows that occur more than once among the windows of its group.
    """
    n = len(contexts)
    scratch, queue = Scratch(memory_bytes), DiskQueue(run_bytes)
    groups = {}
    group = np.array([groups.setdefault(c[0], len(groups)) for c in contexts], dtype=np.int64)
    place = np.array([c[1] for c in contexts], dtype=np.int64)
    size = np.array([len(c[2]) for c in contexts], dtype=np.int64)
    # A shared start of all contexts in one buffer; the anchors' suffixes go through the queue.
    data = scratch.array((int(size.sum()) + 1,), np.uint8)
    start = np.concatenate([[0], np.cumsum(size)[:-1]])
    for i, c in enumerate(contexts):
        data[start[i] : start[i] + size[i]] = np.frombuffer(c[2], dtype=np.uint8)
        queue.push(int(group[i]), c[2][c[1] :], i)
    order, common = scratch.array((n,), np.int64), scratch.array((n,), np.int64)
    before = (-1, b"", -1)
    for t, entry in enumerate(queue.drain()):
        order[t] = entry[2]
        common[t] = _common(before[1], entry[1]) if before[0] == entry[0] else 0
        before = entry
    last = size - length  # last window
    marked = scratch.array((n, int(last.max()) + 1), np.bool_)
    many = np.array([c[3] > 1 for c in contexts], dtype=bool)
    for i in np.flatnonzero(many):
        marked[i, : last[i] + 1] = True
    offset = 0
    while True:
        # Windows whose anchor is ``offset`` bytes behind their start.
        at = place[order] - offset
        alike = common >= length
        hit = alike.copy()
        hit[:-1] |= alike[1:]
        hit &= at <= last[order]
        marked[order[hit], at[hit]] = True
        keep = np.flatnonzero(at > 0)
        if not len(keep):
            break
        offset += 1
        member = order[keep]
        byte = data[start[member] + place[member] - offset]
        key = group[member] * 256 + byte
        by = np.argsort(key, kind="stable")
        from_ = keep[by]
        key = key[by]
        same = np.flatnonzero(key[1:] == key[:-1]) + 1
        new_common = np.zeros(len(by), dtype=np.int64)
        if len(same):
            new_common[same] = 1 + _range_min(common, from_[same - 1] + 1, from_[same] + 1)
        order, common = member[by], new_common
    out = []
    for i in range(n):
        out.append(_runs(marked[i, : last[i] + 1]))
    scratch.close()
    return out


class Queues:
    """One first-in first-out queue of suffix tuples (context, common prefix) per first byte; on disk beyond a bound."""

    def __init__(self, memory_bytes: int):
        self.memory_bytes, self.size, self.parts = memory_bytes, 0, {}
        self.dir: tempfile.TemporaryDirectory | None = None

    def put(self, byte: int, tuples: np.ndarray) -> None:
        self.parts.setdefault(byte, []).append(tuples)
        self.size += tuples.nbytes
        if self.size > self.memory_bytes:
            self.dir = self.dir or tempfile.TemporaryDirectory(prefix="suffix-queues-")
            for k, held in self.parts.items():
                with open(os.path.join(self.dir.name, str(k)), "ab") as f:
                    for x in held:
                        x.tofile(f)
            self.parts, self.size = {}, 0

    def chunks(self, rows: int) -> Iterator[np.ndarray]:
        """All tuples in the order of their bytes, at most ``rows`` at a time."""
        for byte in range(256):
            path = self.dir and os.path.join(self.dir.name, str(byte))
            if path and os.path.exists(path):
                with open(path, "rb") as f:
                    while len(x := np.fromfile(f, dtype=np.int64, count=2 * rows)):
                        yield x.reshape(-1, 2)
            for x in self.parts.get(byte, []):
                for lo in range(0, len(x), rows):
                    yield x[lo : lo + rows]

    def close(self) -> None:
        if self.dir:
            self.dir.cleanup()


class LargeGroup:
    """A group that memory does not hold: bytes in a file, suffix tuples in queues, a chunk of them at a time."""

    def __init__(self, length: int = LENGTH, run_bytes: int = RUN_BYTES, memory_bytes: int = MEMORY_BYTES):
        self.length, self.memory_bytes = length, memory_bytes
        self.queue, self.scratch = DiskQueue(run_bytes), Scratch(memory_bytes)
        self.rows = max(256, memory_bytes // 256)  # tuples of a chunk
        self.dir = tempfile.TemporaryDirectory(prefix="suffix-group-")
        self.data, self.facts, self.names = (open(os.path.join(self.dir.name, x), "wb+") for x in ("bytes", "facts", "names"))
        self.n = self.width = self.end = 0

    def add(self, o: int, cid: object, x: bytes, times: int) -> None:
        windows = len(x) - self.length + 1
        self.width = max(self.width, windows)
        self.data.write(x)
        self.facts.write(np.array([self.end + o, o, windows - 1], dtype=np.int64).tobytes())
        pickle.dump((o, cid, windows, times), self.names, protocol=5)
        self.queue.push(0, x[o:], self.n)
        self.n, self.end = self.n + 1, self.end + len(x)

    def _sample(self) -> Queues:
        """The suffixes at the anchors in order, with common prefixes."""
        out, held, before = Queues(self.memory_bytes), [], b""
        for _, suffix, number in self.queue.drain():
            held.append((number, _common(before, suffix)))
            before = suffix
            if len(held) >= self.rows:
                out.put(0, np.array(held, dtype=np.int64))
                held = []
        if held:
            out.put(0, np.array(held, dtype=np.int64))
        return out

    def _induce(self, level: Queues, offset: int, data: np.ndarray, facts: np.ndarray, marked: np.ndarray) -> Queues:
        """Mark the windows whose anchor is ``offset`` bytes behind their start, and sort the suffixes one byte further left."""
        far = np.iinfo(np.int64).max
        out, since, pushed, last = Queues(self.memory_bytes), np.full(256, far), np.zeros(256, dtype=bool), -1
        for chunk in level.chunks(self.rows):
            member, common = chunk[:, 0], chunk[:, 1]
            spot, place, final = facts[member].T
            at = place - offset
            alike = common >= self.length
            hit = alike.copy()
            hit[:-1] |= alike[1:]
            hit &= at <= final
            marked[member[hit], at[hit]] = True
            if alike[0] and last >= 0 and 0 <= facts[last, 1] - offset <= facts[last, 2]:
                marked[last, facts[last, 1] - offset] = True
            last = int(member[-1])
            lows = np.minimum.accumulate(common)
            keep = np.flatnonzero(at > 0)
            byte = data[spot[keep] - offset - 1].astype(np.int64)
            by = np.argsort(byte, kind="stable")
            from_, byte = keep[by], byte[by]
            fresh = np.empty(len(by), dtype=np.int64)
            if len(by):
                first = np.concatenate([[True], byte[1:] != byte[:-1]])
                later = np.flatnonzero(~first)
                if len(later):
                    fresh[later] = 1 + _range_min(common, from_[later - 1] + 1, from_[later] + 1)
                heads = np.flatnonzero(first)
                kinds = byte[heads]
                fresh[heads] = np.where(pushed[kinds], 1 + np.minimum(np.minimum(since[kinds], lows[from_[heads]]), far - 1), 0)
                ends = np.concatenate([heads[1:], [len(by)]])
                # What lies behind a byte's last tuple counts towards its next one.
                behind = np.concatenate([np.minimum.accumulate(common[::-1])[::-1], [far]])
                since = np.minimum(since, lows[-1])
                since[kinds] = behind[from_[ends - 1] + 1]
                pushed[kinds] = True
                for k, a, b in zip(kinds.tolist(), heads.tolist(), ends.tolist(), strict=True):
                    out.put(k, np.stack([member[from_[a:b]], fresh[a:b]], axis=1))
            else:
                since = np.minimum(since, lows[-1])
        return out

    def solve(self) -> Iterator[tuple[int, object, list[tuple[int, int]]]]:
        """(place, id, runs of repeated windows) of the contexts that have some."""
        for f in (self.data, self.facts):
            f.flush()
        data = np.memmap(self.data.name, dtype=np.uint8, mode="r")
        facts = np.memmap(self.facts.name, dtype=np.int64, mode="r").reshape(-1, 3)
        marked = self.scratch.array((self.n, self.width), np.bool_)
        level, offset = self._sample(), 0
        while True:
            after = self._induce(level, offset, data, facts, marked)
            level.close()
            if not after.size and after.dir is None:
                break
            level, offset = after, offset + 1
        self.names.seek(0)
        for i in range(self.n):
            o, cid, windows, times = pickle.load(self.names)
            runs = [(0, windows - 1)] if times > 1 else _runs(marked[i, :windows])
            if runs:
                yield o, cid, runs
        for f in (self.data, self.facts, self.names):
            f.close()
        self.scratch.close()
        self.dir.cleanup()


def _runs(marks: np.ndarray) -> list[tuple[int, int]]:
    """Maximal runs [first, last] of marks."""
    m = np.flatnonzero(np.diff(np.concatenate([[False], marks, [False]]).astype(np.int8)))
    return [(int(a), int(b) - 1) for a, b in zip(m[0::2], m[1::2], strict=True)]


def shard_runs(rows: Iterator[tuple], length: int = LENGTH, group_bytes: int = GROUP_BYTES, run_bytes: int = RUN_BYTES, memory_bytes: int = MEMORY_BYTES) -> Iterator[tuple]:
    """(h, c, o, cid, runs of repeated windows) of contexts (h, c, o, cid, bytes, times) that come in order.

    Holds whole groups of up to CHUNK contexts together, and one group of up to ``group_bytes`` besides.
    """
    held: list[tuple] = []  # whole groups
    group: list[tuple] = []  # the group that is being read
    size, large, last = 0, None, None

    def solve(items: list[tuple]) -> Iterator[tuple]:
        if items:
            found = repeated_windows([((h, c), o, x, t) for h, c, o, _, x, t in items], length, run_bytes, memory_bytes)
            yield from ((*item[:4], runs) for item, runs in zip(items, found, strict=True) if runs)

    def merged() -> Iterator[tuple]:
        """Equal neighbours as one row; None at the end."""
        now = None
        for row in rows:
            if now is not None and now[:5] == row[:5]:
                now = (*now[:5], now[5] + row[5])
            else:
                if now is not None:
                    yield now
                now = row
        if now is not None:
            yield now
        yield None

    for row in merged():
        if row is None or row[:2] != last:
            if large is not None:
                yield from ((*last, *x) for x in large.solve())
                large = None
            held += group
            group, size = [], 0
            if row is None or len(held) > CHUNK:
                yield from solve(held)
                held = []
            if row is None:
                return
            last = row[:2]
        if large is None:
            group.append(row)
            size += len(row[4]) + 200
            if size <= group_bytes:
                continue
            large = LargeGroup(length, run_bytes, memory_bytes)
            for _, _, o, cid, x, t in group:
                large.add(o, cid, x, t)
            group, size = [], 0
        else:
            large.add(*row[2:])


def _common(a: bytes, b: bytes) -> int:
    """Length of the common prefix."""
    n = min(len(a), len(b))
    if a[:n] == b[:n]:
        return n
    lo, hi = 0, n
    while hi - lo > 1:
        mid = (lo + hi) // 2
        if a[:mid] == b[:mid]:
            lo = mid
        else:
            hi = mid
    return lo


# ---------------------------------------------------------------- Spark side


def _named(docs: DataFrame, text_col: str, *more: object) -> DataFrame:
    """k, k2: the name of the text (two hashes of 64 bits), text, and what else is asked for."""
    t = F.coalesce(F.col(text_col), F.lit(""))
    return docs.select(F.xxhash64(t).alias("k"), F.xxhash64(t, F.octet_length(t), F.lit("second")).alias("k2"), F.col(text_col).alias("text"), *more)


def _key_rows(texts: DataFrame, length: int) -> DataFrame:
    """g (key), k (text), at (first window), ow (offset and windows less one), times of the halves of every text.

    A key that the task meets once is a row with times 1; of others each place is a row with times 0, and a row
    with at = -1 has their number.  A text that the task meets again is counted, not listed again.
    """
    schema = T.StructType([T.StructField("g", T.LongType()), T.StructField("k", T.LongType())] + [T.StructField(c, T.IntegerType()) for c in ("at", "ow", "times")])

    def run(batches: Iterator) -> Iterator:
        import pyarrow as pa

        settle("suffix_dedup")
        parts: list[tuple] = []
        copies: dict[int, int] = {}
        total = 0

        def flush() -> Iterator[pa.RecordBatch]:
            g, k, at, ow = (np.concatenate(x) for x in zip(*parts, strict=True))
            times = np.concatenate([np.full(len(x[0]), copies[int(x[1][0])], np.int32) for x in parts])
            order = np.argsort(g, kind="stable")
            sorted_g = g[order]
            start = np.flatnonzero(np.concatenate([[True], sorted_g[1:] != sorted_g[:-1]]))
            number = np.add.reduceat(times[order], start)
            size = np.diff(np.concatenate([start, [len(g)]]))
            several = number > 1
            once = np.empty(len(g), dtype=np.int32)
            once[order] = np.repeat(np.where(several, 0, 1), size)
            n = int(several.sum())
            fill = lambda x: np.full(n, x, dtype=np.int32)
            columns = [
                np.concatenate([g, sorted_g[start[several]]]), np.concatenate([k, np.zeros(n, np.int64)]), np.concatenate([at, fill(-1)]),
                np.concatenate([ow, fill(0)]), np.concatenate([once, number[several].astype(np.int32)]),
            ]
            for lo in range(0, len(columns[0]), 200_000):
                yield pa.RecordBatch.from_arrays([pa.array(c[lo : lo + 200_000]) for c in columns], names=schema.names)

        for batch in batches:
            for k, v in zip(batch.column(0), batch.column(1).cast(pa.binary()), strict=True):
                k, text = k.as_py(), v.as_py()
                if text is None or len(text) < length:
                    continue
                if k in copies:
                    copies[k] += 1
                    continue
                copies[k] = 1
                g, at, o, w = keys(np.frombuffer(text, dtype=np.uint8), length)
                parts.append((g, np.full(len(g), k, np.int64), at.astype(np.int32), (o << 8 | w).astype(np.int32)))
                total += len(g)
                if total > COUNTED:
                    yield from flush()
                    parts, copies, total = [], {}, 0
        if parts:
            yield from flush()

    return texts.select("k", "text").mapInArrow(run, schema)


def _squeezed(df: DataFrame, level: int = 6, most: int | None = None) -> DataFrame:
    """The text, last column of ``df`` after k and k2, as compressed bytes: it is moved and kept.

    With ``most`` no task passes a text on more often: whether something occurs once or twice is all that counts.
    """
    schema = T.StructType([*df.schema.fields[:-1], T.StructField("text", T.BinaryType())])

    def run(batches: Iterator) -> Iterator:
        import pyarrow as pa
        import zstandard

        settle("suffix_dedup")
        press = zstandard.ZstdCompressor(level=level).compress
        seen: dict[tuple[int, int], int] = {}
        for batch in batches:
            if most is not None:
                keep = []
                for i, name in enumerate(zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), strict=True)):
                    seen[name] = seen.get(name, 0) + 1
                    if seen[name] <= most:
                        keep.append(i)
                if len(seen) > REMEMBERED:
                    seen.clear()
                batch = batch.take(pa.array(keep, pa.int64()))
            data = [None if v.as_py() is None else press(v.as_py()) for v in batch.column(batch.num_columns - 1).cast(pa.binary())]
            yield pa.RecordBatch.from_arrays([*batch.columns[:-1], pa.array(data, pa.binary())], names=schema.names)

    return df.mapInArrow(run, schema)


def _blocks(text: bytes, at: int, o: int, w: int, hot: bool, length: int) -> Iterator[tuple[int, int, int]]:
    """(c, highest offset, lowest offset) of the pieces in which the windows of a spot are compared: all of them, or
    for a hot key blocks of offsets, with a hash of the bytes that a block's windows share."""
    import xxhash

    if not hot:
        yield 0, o, o - w
        return
    for block in range((o - w) // SPLIT, o // SPLIT + 1):
        first, last = block * SPLIT, block * SPLIT + SPLIT - 1
        lo, hi = max(o - w, first), min(o, last)
        anchor = at + o
        # Windows of the block reach from anchor - first (at the latest) to anchor - last + length (at least).
        yield xxhash.xxh64(text[anchor - first : anchor - last + length], seed=block + 1).intdigest() - (1 << 63), hi, lo


def _occurrences(candidates: DataFrame, length: int, with_bytes: bool) -> DataFrame:
    """A row per context of each candidate text: group g, c, place o, id of the bytes (two numbers); and
    either the bytes with their number (merged inside the task), or the text's name and the start."""
    base = [T.StructField("g", T.LongType()), T.StructField("c", T.LongType()), T.StructField("o", T.IntegerType()), T.StructField("cid", T.LongType()), T.StructField("cid2", T.LongType())]
    more = [T.StructField("bytes", T.BinaryType()), T.StructField("times", T.LongType())] if with_bytes else [T.StructField("k", T.LongType()), T.StructField("k2", T.LongType()), T.StructField("start", T.IntegerType())]
    schema = T.StructType(base + more)

    def run(batches: Iterator) -> Iterator:
        import pyarrow as pa
        import xxhash
        import zstandard
        from pyspark.sql.pandas.types import to_arrow_schema

        settle("suffix_dedup")
        expand = zstandard.ZstdDecompressor().decompress
        arrow = to_arrow_schema(schema)
        merged: dict[tuple[int, int, int, bytes], int] = {}
        seen: dict[tuple[int, int], int] = {}
        size = 0

        def named(x: bytes) -> tuple[int, int]:
            d = xxhash.xxh3_128_intdigest(x)
            return (d >> 64) - (1 << 63), (d & ((1 << 64) - 1)) - (1 << 63)

        def table(rows: list) -> pa.RecordBatch:
            return pa.RecordBatch.from_arrays([pa.array(x, type=f.type) for x, f in zip(zip(*rows, strict=True), arrow, strict=True)], schema=arrow)

        def flush() -> pa.RecordBatch:
            # in order, so that contexts of a key lie together and the exchange compresses them
            return table([(g, c, o, *named(x), x, t) for (g, c, o, x), t in sorted(merged.items())])

        for batch in batches:
            rows = []
            for k, k2, v, spots in zip(*(batch.column(i) for i in range(4)), strict=True):
                name = (k.as_py(), k2.as_py())
                # The places of a text are asked for once, its contexts occur once or more often.
                seen[name] = seen.get(name, 0) + 1
                if seen[name] > (2 if with_bytes else 1):
                    continue
                if len(seen) > REMEMBERED:
                    seen.clear()
                text = expand(v.as_py())
                for s in spots.as_py():
                    g, at, o, w = s["g"], s["at"], s["ow"] >> 8, s["ow"] & 255
                    if at + w + length > len(text):  # of another text whose 64-bit name is the same
                        continue
                    for c, hi, lo in _blocks(text, at, o, w, s["hot"], length):
                        start = at + o - hi
                        x = text[start : at + o - lo + length]
                        if with_bytes:
                            key = (g, c, hi, x)
                            if key in merged:
                                merged[key] += 1
                            else:
                                merged[key] = 1
                                size += len(x) + 250
                        else:
                            rows.append((g, c, hi, *named(x), *name, start))
                if with_bytes and size > CONTEXT_BYTES:
                    yield flush()
                    merged, size = {}, 0
                elif len(rows) > 100_000:
                    yield table(rows)
                    rows = []
            if rows:
                yield table(rows)
        if merged:
            yield flush()

    return candidates.select("k", "k2", "text", "spots").mapInArrow(run, schema)


def _sort_shards(contexts: DataFrame, length: int, group_bytes: int) -> DataFrame:
    """g, c, o, cid, cid2 and spans (first byte, end) of the contexts with repeated windows."""
    span = T.StructType([T.StructField("a", T.IntegerType()), T.StructField("b", T.IntegerType())])
    schema = T.StructType([contexts.schema[c] for c in ("g", "c", "o", "cid", "cid2")] + [T.StructField("spans", T.ArrayType(span))])

    def run(batches: Iterator) -> Iterator:
        import pyarrow as pa
        from pyspark.sql.pandas.types import to_arrow_schema

        settle("suffix_dedup")
        arrow = to_arrow_schema(schema)

        def rows() -> Iterator[tuple]:
            for batch in batches:
                for g, c, o, cid, cid2, x, t in zip(*(col.to_pylist() for col in batch.columns), strict=True):
                    yield g, c, o, (cid, cid2), x, t

        found = []
        for g, c, o, cid, runs in shard_runs(rows(), length, group_bytes):
            found.append({"g": g, "c": c, "o": o, "cid": cid[0], "cid2": cid[1], "spans": [{"a": a, "b": b + length} for a, b in runs]})
            if len(found) >= 10_000:
                yield pa.RecordBatch.from_pylist(found, schema=arrow)
                found = []
        if found:
            yield pa.RecordBatch.from_pylist(found, schema=arrow)

    dealt = contexts.repartition(F.col("g"), F.col("c")).sortWithinPartitions("g", "c", "o", "cid", "cid2", "bytes")
    return dealt.select("g", "c", "o", "cid", "cid2", "bytes", "times").mapInArrow(run, schema)


def _merged(spans: list[tuple[int, int]]) -> list[tuple[int, int]]:
    """Union of half-open intervals as maximal runs (touching ones join)."""
    out: list[list[int]] = []
    for a, b in sorted(spans):
        if out and a <= out[-1][1]:
            out[-1][1] = max(out[-1][1], b)
        else:
            out.append([a, b])
    return [(a, b) for a, b in out]


def whole_characters(text: bytes, cut: list[tuple[int, int]]) -> bytes:
    """What is left of a UTF-8 text without the cuts; a character that a cut goes through is left out whole."""
    pieces = []
    for a, b in zip([0, *(b for _, b in cut)], [*(a for a, _ in cut), len(text)], strict=True):
        while a < b and text[a] & 0xC0 == 0x80:
            a += 1
        if b < len(text):
            while b > a and text[b] & 0xC0 == 0x80:
                b -= 1
        pieces.append(text[a:b])
    return b"".join(pieces)


def _cut(joined: DataFrame, with_text: bool) -> DataFrame:
    """Cut the spans out of the texts (strings, or compressed bytes); the first column passes through."""
    packed = isinstance(joined.schema["text"].dataType, T.BinaryType)
    extra = [T.StructField("n_bytes", T.LongType()), T.StructField("n_removed", T.LongType()), T.StructField("n_spans", T.LongType()), T.StructField("kept_sha256", T.StringType())]
    schema = T.StructType([joined.schema.fields[0], *extra] + ([T.StructField("kept_text", T.StringType())] if with_text else []))

    def run(batches: Iterator) -> Iterator:
        import pyarrow as pa
        import zstandard
        from pyspark.sql.pandas.types import to_arrow_schema

        settle("suffix_dedup")
        arrow, expand = to_arrow_schema(schema), zstandard.ZstdDecompressor().decompress
        for batch in batches:
            n, gone, runs, sha, kept = [], [], [], [], []
            for v, spans in zip(batch.column(1).cast(pa.binary()), batch.column(2), strict=True):
                text, spans = v.as_py(), spans.as_py()
                if packed and text is not None:
                    text = expand(text)
                rest = data = text or b""
                if spans:
                    cut = _merged([(s["a"], s["b"]) for s in spans])
                    rest = b"".join(data[a:b] for a, b in zip([0, *(b for _, b in cut)], [*(a for a, _ in cut), len(data)], strict=True))
                    if with_text:
                        text = whole_characters(data, cut)
                n.append(len(data))
                gone.append(len(data) - len(rest))
                runs.append(len(cut) if spans else 0)
                sha.append(hashlib.sha256(rest).hexdigest())
                kept.append(text)
            cols = [batch.column(0), *(pa.array(x, pa.int64()) for x in (n, gone, runs)), pa.array(sha, pa.string()), *([pa.array(kept, pa.binary()).cast(pa.string())] if with_text else [])]
            yield pa.RecordBatch.from_arrays(cols, schema=arrow)

    return joined.mapInArrow(run, schema)


def _islands(spans: DataFrame) -> DataFrame:
    """k, k2, spans: the maximal runs that the intervals (a, b) of each text cover."""
    of = Window.partitionBy("k", "k2").orderBy("a", "b")
    reach = F.max("b").over(of.rowsBetween(Window.unboundedPreceding, -1))
    marked = spans.withColumn("new", F.when(F.col("a") <= reach, 0).otherwise(1)).withColumn("island", F.sum("new").over(of.rowsBetween(Window.unboundedPreceding, 0)))
    runs = marked.groupBy("k", "k2", "island").agg(F.min("a").alias("a"), F.max("b").alias("b"))
    return runs.groupBy("k", "k2").agg(F.collect_list(F.struct("a", "b")).alias("spans"))


def _small(df: DataFrame) -> DataFrame:
    """Marked for broadcast if its bytes are few, for a sort-merge join else."""
    return F.broadcast(df) if fits(df) else df.hint("merge")


def remove_repeats(docs: DataFrame, length: int = LENGTH, id_col: str = "doc_id", text_col: str = "text", with_text: bool = False, hot_times: int = HOT, group_bytes: int = GROUP_BYTES) -> DataFrame:
    """Per row doc_id, n_bytes, n_removed, n_spans (maximal removed runs), kept_sha256.

    With ``with_text`` instead of doc_id ``row``, a struct of all columns of ``docs`` but the text, and ``kept_text``: the
    remaining text (null for a null text), without characters that a cut goes through.  Keys met more than ``hot_times`` are cut
    by offsets, groups of more than ``group_bytes`` are sorted outside memory.
    """
    if not GRAM < length <= 255 + GRAM:
        raise ValueError("length must lie above 16 and be at most 271")
    texts = _named(light_batches(docs), text_col)
    # Rows of a key that its task met once go to the key's partition, with the counts of the others; the rest is spread.
    rows = _key_rows(texts, length).withColumn("x", F.when(F.col("times") == 0, F.xxhash64("k", "at")).otherwise(F.col("g")))
    counted = rows.withColumn("total", F.sum("times").over(Window.partitionBy("x"))).where("times = 0 or total > 1")
    counted = written(counted.select("g", "k", "at", "ow", F.when(F.col("times") > 0, F.col("total")).alias("total")))
    hot = counted.where(F.col("total") > hot_times).select("g").distinct().withColumn("hot", F.lit(True))
    spots = counted.where("at >= 0").select("g", "k", "at", "ow").join(_small(hot), "g", "left").withColumn("hot", F.coalesce("hot", F.lit(False)))
    spots = written(spots.groupBy("k").agg(F.collect_set(F.struct("g", "at", "ow", "hot")).alias("spots")))
    discard(counted)
    names = spots.select("k")
    near = texts.join(F.broadcast(names), "k", "left_semi") if fits(names) else texts
    candidates = written(_squeezed(near.select("k", "k2", "text"), most=2).join(spots.hint("merge"), "k").select("k", "k2", "text", "spots"))
    discard(spots)

    shards = written(_sort_shards(_occurrences(candidates, length, True), length, group_bytes))
    places = _occurrences(candidates, length, False).join(_small(shards), ["g", "c", "o", "cid", "cid2"])
    spans = written(_islands(places.select("k", "k2", F.explode(F.transform("spans", lambda s: F.struct((F.col("start") + s["a"]).alias("a"), (F.col("start") + s["b"]).alias("b")))).alias("s")).select("k", "k2", "s.*")))
    discard(candidates, shards)
    first = row_of(docs, text_col).alias("row") if with_text else F.col(id_col).alias("doc_id")
    rows = _named(docs, text_col, first)
    if fits(spans):
        joined = rows.join(F.broadcast(spans), ["k", "k2"], "left")
    else:  # all texts travel, compressed
        joined = _squeezed(rows.select("k", "k2", rows.columns[3], "text"), level=1).join(spans.hint("merge"), ["k", "k2"], "left")
    return _cut(joined.select(rows.columns[3], "text", "spans"), with_text)
