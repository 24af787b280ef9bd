"""Log-likelihood of whole documents under a gated recurrent class language model.

*Factoring.*  A word's probability is P(class | all words before) * P(word | class, all words before).  The most
frequent words are dealt by rank to classes of ``WIDTH`` words; any other word falls into a class by its form (its
last letters), so unseen words have one, too; the end of a text is a class.  The class softmax and the word
softmax inside the classes of frequent words are computed from the recurrent state.  In a class by form the word
softmax has a bias per word and no state; its optimum is the word's smoothed share of its class, counted over
the whole corpus - so the vocabulary is unbounded, lives in a table of the cluster and is never collected.
Every factor sums to 1.

*Network.*  A gated recurrent unit in numpy, trained by truncated back-propagation through time: documents
run side by side, windows of ``WINDOW`` words, state carried from window to window (gradients stop there).
Every partition trains from the common weights on all its documents; the weights are averaged by words
seen, in two levels of bounded groups.  Rounds deal all training documents out by hash, so
that each is learnt from once.  Only averages (one per 4,096 partitions) reach the driver.

*Scoring.*  State is carried over all windows of a document: nothing is cut.  The states of many documents are
gathered, as they do not depend on the outputs, and the two softmaxes are computed in blocks, one matrix per class.
Words of the frequent head are looked up in a broadcast of ``HEAD`` entries at most (the cut is found from a
histogram of counts, so no more than the head is collected); the rest meets its counts in a join.

Edge cases: null text is empty (only the end token); ids may be null (they count as the word ``null`` in the
split) or repeat, each row is scored on its own; without training documents all tokens are equally
unknown and scores stay finite; very long texts run on in the same state; extra columns are ignored.
"""

from __future__ import annotations

import math
from collections import Counter
from collections.abc import Iterator
from dataclasses import dataclass
from itertools import repeat

import numpy as np
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from erblock.llm.common import checkpoint, light_batches

#: Classes of frequent words and words in each, classes by word form, hidden units.
BLOCKS, WIDTH, FORMS, HIDDEN = 32, 32, 32, 16
#: Slots: a frequent word's own, one per form, the end; a text's first input is one more.
OWN = BLOCKS * WIDTH
END = OWN + FORMS
START = END + 1
CLASSES = BLOCKS + FORMS + 1
CLASS_OF = np.concatenate([np.repeat(np.arange(BLOCKS), WIDTH), np.arange(BLOCKS, CLASSES)]).astype(np.int16)
#: Frequent words whose counts are broadcast at most.
HEAD = 262_144
#: Words in a window of truncated back-propagation; documents side by side; bytes of the texts in one sweep.
WINDOW, LANES, SWEEP_BYTES = 20, 512, 32 << 20
#: States whose softmaxes are computed together.
ROWS = 8192
#: Shares of the training documents in each round of training.
ROUNDS = (1 / 8, 7 / 8)
RATE = 0.02
#: Distinct words that a worker counts before it hands them on.
COUNT_WORDS = 400_000


def tokens(text: bytes | None) -> list[bytes]:
    """Words of a UTF-8 text: A-Z lower-cased (other letters stay), cut at the six ASCII white space bytes."""
    return text.lower().split() if text else []


def training(id_col: str = "doc_id") -> Column:
    """True for rows that are learnt from."""
    return _crc(id_col) % 5 != 1


def _crc(id_col: str) -> Column:
    return F.crc32(F.coalesce(F.col(id_col).cast("string"), F.lit("null")).cast("binary"))


def form(word: bytes) -> int:
    """Slot of a word that has none of its own: by its last two letters."""
    h = 7
    for c in word.rstrip(b".,;:!?")[-2:]:
        h = (h * 131 + c) % 1_000_003
    return OWN + h % FORMS


@dataclass
class Head:
    """Frequent words: number of each, and by number log10(count + 0.5), slot, and what the model adds for it:
    log10 of its share of its class by form (0 for a word with a slot of its own, which the network covers)."""

    number: dict[bytes, int]
    logs: np.ndarray
    slots: np.ndarray
    share: np.ndarray

    def read(self, words: list[bytes], forms: dict[bytes, int]) -> tuple[np.ndarray, np.ndarray, list[bytes]]:
        """(numbers, slots with the end, the words without a number)."""
        numbers = np.fromiter(map(self.number.get, words, repeat(-1)), dtype=np.int32, count=len(words))
        slots = np.empty(len(words) + 1, dtype=np.int16)
        slots[-1] = END
        rare: list[bytes] = []
        if len(self.slots):
            slots[:-1] = self.slots[numbers]
        spots = np.flatnonzero(numbers < 0)
        if len(spots):
            rare = [words[i] for i in spots.tolist()]
            if len(forms) > 200_000:
                forms.clear()
            found = []
            for w in rare:
                f = forms.get(w)
                if f is None:
                    f = forms[w] = form(w)
                found.append(f)
            slots[spots] = found
        return numbers, slots, rare


# ---------------------------------------------------------------- the network

SHAPES = {"x": (START + 1, 3 * HIDDEN), "u": (HIDDEN, 3 * HIDDEN), "w": (HIDDEN, CLASSES), "b": (CLASSES,), "v": (BLOCKS, HIDDEN, WIDTH), "c": (BLOCKS, WIDTH)}
SIZE = sum(math.prod(s) for s in SHAPES.values())


def unpack(flat: np.ndarray) -> dict[str, np.ndarray]:
    out, at = {}, 0
    for k, s in SHAPES.items():
        n = math.prod(s)
        out[k] = flat[at : at + n].reshape(s)
        at += n
    return out


def initial(own_counts: np.ndarray, class_counts: np.ndarray) -> np.ndarray:
    """Small fixed weights; the output biases start at the log shares of the classes, and of the words in theirs.

    own_counts: occurrences of the frequent words in the order of their slots; a slot without a word gets none.
    """
    rng = np.random.default_rng(11)
    flat = (rng.standard_normal(SIZE) * 0.15).astype(np.float32)
    p = unpack(flat)
    p["b"][:] = np.log((class_counts + 0.5) / (class_counts + 0.5).sum())
    inside = np.zeros(OWN)
    inside[: len(own_counts)] = own_counts
    inside = inside.reshape(BLOCKS, WIDTH)
    total = inside.sum(axis=1, keepdims=True)
    p["c"][:] = np.where(inside > 0, np.log(np.maximum(inside, 1) / np.maximum(total, 1)), -30)
    return flat


def _gates(table: np.ndarray, at: np.ndarray) -> list[np.ndarray]:
    """Rows of the input weights, an array for each of the three gates: what follows runs over contiguous memory."""
    return [table[:, k : k + HIDDEN][at] for k in range(0, 3 * HIDDEN, HIDDEN)]


def _step(p: dict, gx: list[np.ndarray], h: np.ndarray) -> tuple:
    """One word for all lanes, from its rows of the input weights: new state, and z, r, n, u_n h."""
    u = p["u"]
    zr = np.empty((2, *h.shape), dtype=np.float32)
    for k in (0, 1):
        np.matmul(h, u[:, k * HIDDEN : (k + 1) * HIDDEN], out=zr[k])
        zr[k] += gx[k]
    zr *= 0.5  # the logistic function by way of tanh
    np.tanh(zr, out=zr)
    zr *= 0.5
    zr += 0.5
    z, r = zr
    ghn = h @ u[:, 2 * HIDDEN :]
    n = r * ghn
    n += gx[2]
    np.tanh(n, out=n)
    new = h - n
    new *= z
    new += n
    return new, (z, r, n, ghn)


def _exp(logits: np.ndarray) -> np.ndarray:
    """exp in place, from the greatest down where one could overflow."""
    if logits.size and float(logits.max()) > 60:
        logits -= logits.max(axis=1, keepdims=True)
    return np.exp(logits, out=logits)


def _by_class(slots: np.ndarray) -> Iterator[tuple[int, np.ndarray]]:
    """(class, rows) of the rows whose word is in a class of frequent words."""
    classes = CLASS_OF[slots]
    order = np.argsort(classes, kind="stable")
    edges = np.searchsorted(classes[order], np.arange(BLOCKS + 1))
    for k in range(BLOCKS):
        if edges[k + 1] > edges[k]:
            yield k, order[edges[k] : edges[k + 1]]


def _log_softmax_at(logits: np.ndarray, at: np.ndarray) -> np.ndarray:
    if logits.size and float(logits.max()) > 60:
        logits -= logits.max(axis=1, keepdims=True)
    hit = logits[np.arange(len(at)), at]
    np.exp(logits, out=logits)
    return hit - np.log(logits.sum(axis=1))


def log_outputs(p: dict, h: np.ndarray, slots: np.ndarray) -> np.ndarray:
    """Natural log of P(class) * P(word | class) for states and the slots that follow (forms: only their class)."""
    out = np.empty(len(slots))
    for lo in range(0, len(slots), 2048):  # logits that stay in the cache
        part = slice(lo, lo + 2048)
        logits = h[part] @ p["w"]
        logits += p["b"]
        out[part] = _log_softmax_at(logits, CLASS_OF[slots[part]])
    for k, rows in _by_class(slots):
        logits = h[rows] @ p["v"][k]
        logits += p["c"][k]
        out[rows] += _log_softmax_at(logits, slots[rows] - k * WIDTH)
    return out


def log_likelihood(flat: np.ndarray, docs: list[np.ndarray]) -> np.ndarray:
    """Natural log probability of each sequence of slots; state runs from its first to its last word."""
    p = unpack(flat)
    out = np.zeros(len(docs))
    if not docs:
        return out
    order = sorted(range(len(docs)), key=lambda i: -len(docs[i]))
    lengths = np.array([len(docs[i]) for i in order])
    stream = np.concatenate([docs[i] for i in order])
    starts = np.concatenate([[0], np.cumsum(lengths)[:-1]])
    total = np.zeros(len(docs))
    live_at = len(docs) - np.searchsorted(lengths[::-1], np.arange(int(lengths[0])), side="right")
    h = np.zeros((len(docs), HIDDEN), dtype=np.float32)
    before = np.full(len(docs), START, dtype=np.int16)
    states: list[np.ndarray] = []
    targets: list[np.ndarray] = []
    held = 0

    def flush() -> None:
        logs = log_outputs(p, np.concatenate(states), np.concatenate(targets))
        at = 0
        for t in targets:
            total[: len(t)] += logs[at : at + len(t)]
            at += len(t)

    for t, live in enumerate(live_at.tolist()):
        h = _step(p, _gates(p["x"], before[:live]), h[:live])[0]
        before = stream[starts[:live] + t]
        states.append(h)
        targets.append(before)
        held += live
        if held >= ROWS:
            flush()
            states, targets, held = [], [], 0
    if held:
        flush()
    out[order] = total
    return out


class Trainer:
    """Adam over truncated back-propagation; documents flow through fixed lanes."""

    def __init__(self, flat: np.ndarray):
        self.flat = flat.copy()
        self.m, self.v, self.t, self.seen = np.zeros(SIZE, np.float32), np.zeros(SIZE, np.float32), 0, 0

    def sweep(self, docs: list[np.ndarray]) -> None:
        """Learn from all words of the documents, laid end to end in lanes; a document starts from
        a zero state wherever it begins."""
        docs = [d for d in docs if len(d)]
        if not docs:
            return
        stream = np.concatenate(docs)
        first = np.zeros(len(stream), dtype=bool)
        first[np.cumsum([0] + [len(d) for d in docs[:-1]])] = True
        before = np.empty_like(stream)
        before[1:] = stream[:-1]
        before[first] = START
        lanes = max(1, min(LANES, len(stream) // (4 * WINDOW)))
        steps = -(-len(stream) // lanes)
        pad = steps * lanes - len(stream)

        def lay(x: np.ndarray, fill: int) -> np.ndarray:
            return np.concatenate([x, np.full(pad, fill, dtype=x.dtype)]).reshape(lanes, steps).T.copy()

        target, source, fresh = lay(stream, END), lay(before, START), lay(first, True)
        real = lay(np.ones(len(stream), bool), False)
        h = np.zeros((lanes, HIDDEN), dtype=np.float32)
        for a in range(0, steps, WINDOW):
            h = self._window(target[a : a + WINDOW], source[a : a + WINDOW], fresh[a : a + WINDOW], real[a : a + WINDOW], h)
        self.seen += len(stream)

    def gradient(self, target: np.ndarray, source: np.ndarray, fresh: np.ndarray, real: np.ndarray, h: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """(gradient of the mean negative log-likelihood of a window, state after it)."""
        p, g = unpack(self.flat), np.zeros(SIZE, dtype=np.float32)
        d = unpack(g)
        steps, lanes = target.shape
        gx = _gates(p["x"], source)
        starting = fresh.any(axis=1)
        kept, out = [], np.empty((steps, lanes, HIDDEN), dtype=np.float32)
        for t in range(steps):
            if starting[t]:
                h = h.copy()
                h[fresh[t]] = 0
            new, parts = _step(p, [x[t] for x in gx], h)
            kept.append((h, parts))
            out[t] = h = new
        flat_out, slots = out.reshape(-1, HIDDEN), target.reshape(-1)
        scale = np.float32(1 / max(1, int(real.sum())))
        weight = np.where(real.reshape(-1, 1), scale, np.float32(0))
        dout = np.empty_like(flat_out)
        for lo in range(0, len(slots), 2048):
            part = slice(lo, lo + 2048)
            logits = flat_out[part] @ p["w"]
            logits += p["b"]
            _exp(logits)
            logits *= weight[part] / logits.sum(axis=1, keepdims=True)
            logits[np.arange(len(logits)), CLASS_OF[slots[part]]] -= weight[part, 0]
            d["w"] += flat_out[part].T @ logits
            d["b"] += logits.sum(axis=0)
            dout[part] = logits @ p["w"].T
        for k, rows in _by_class(slots):
            states = flat_out[rows]
            logits = states @ p["v"][k]
            logits += p["c"][k]
            _exp(logits)
            logits *= weight[rows] / logits.sum(axis=1, keepdims=True)
            logits[np.arange(len(rows)), slots[rows] - k * WIDTH] -= weight[rows, 0]
            d["v"][k] = states.T @ logits
            d["c"][k] = logits.sum(axis=0)
            dout[rows] += logits @ p["v"][k].T
        dout = dout.reshape(steps, lanes, HIDDEN)
        carry = np.zeros((lanes, HIDDEN), dtype=np.float32)
        dz, dr, dn = gx  # gx has served
        dnr = np.empty_like(dn)
        uz, ur, un = (p["u"][:, k : k + HIDDEN].T.copy() for k in range(0, 3 * HIDDEN, HIDDEN))
        for t in range(steps - 1, -1, -1):
            prev, (z, r, n, ghn) = kept[t]
            dh = dout[t]
            dh += carry
            carry = dh * z
            x = np.subtract(prev, n, out=dz[t])
            x *= carry
            x *= 1 - z
            x = np.subtract(dh, carry, out=dn[t])
            x *= 1 - n * n
            np.multiply(x, r, out=dnr[t])
            x = np.multiply(dnr[t], ghn, out=dr[t])
            x *= 1 - r
            carry += dz[t] @ uz
            carry += dr[t] @ ur
            carry += dnr[t] @ un
            if starting[t]:
                carry[fresh[t]] = 0
        before = np.concatenate([k[0] for k in kept]).T
        order = np.argsort(source.reshape(-1), kind="stable")
        ids, at = np.unique(source.reshape(-1)[order], return_index=True)
        for k, (inner, outer) in enumerate(((dz, dz), (dr, dr), (dnr, dn))):
            part = slice(k * HIDDEN, (k + 1) * HIDDEN)
            d["u"][:, part] = before @ inner.reshape(-1, HIDDEN)
            d["x"][ids, part] = np.add.reduceat(outer.reshape(-1, HIDDEN)[order], at, axis=0)
        return g, h

    def _window(self, target: np.ndarray, source: np.ndarray, fresh: np.ndarray, real: np.ndarray, h: np.ndarray) -> np.ndarray:
        g, h = self.gradient(target, source, fresh, real, h)
        norm = float(np.sqrt(g @ g))
        if norm > 1:
            g /= norm
        self.t += 1
        self.m += 0.1 * (g - self.m)
        self.v += 0.01 * (g * g - self.v)
        rate = RATE / (1 + self.t / 400)
        self.flat -= rate * (self.m / (1 - 0.9**self.t)) / (np.sqrt(self.v / (1 - 0.99**self.t)) + 1e-7)
        return h


# ---------------------------------------------------------------- Spark side


def word_counts(docs: DataFrame, text_col: str = "text") -> DataFrame:
    """word, c: occurrences over all rows given; the end token is the word '' (no word is empty).

    Counted in each worker first, so a frequent word sends a row per worker and not per occurrence.
    """
    schema = T.StructType([T.StructField("word", T.StringType()), T.StructField("n", T.LongType())])

    def run(batches: Iterator) -> Iterator:
        import pyarrow as pa

        def out(c: Counter) -> pa.RecordBatch:
            return pa.RecordBatch.from_arrays([pa.array(list(c.keys()), type=pa.string()), pa.array(list(c.values()), type=pa.int64())], names=["word", "n"])

        count: Counter = Counter()
        for batch in batches:
            for v in batch.column(0).cast(pa.binary()):
                count.update(tokens(v.as_py()))
                count[b""] += 1
                if len(count) > COUNT_WORDS:
                    yield out(count)
                    count = Counter()
        if count:
            yield out(count)

    return docs.select(text_col).mapInArrow(run, schema).groupBy("word").agg(F.sum("n").alias("c"))


def head_words(counts: DataFrame, most: int = HEAD) -> list[tuple[bytes, int]]:
    """(word, count) of at most ``most`` frequent words, by falling count; the end token is not among them.

    The least count is read off a histogram by powers of 2 ** (1/8), so only the head itself is collected.
    """
    level = F.floor(F.log2("c") * 8)
    words = counts.where("word <> ''")
    cut, total = None, 0
    for r in sorted(words.groupBy(level.alias("level")).agg(F.count(F.lit(1)).alias("n")).collect(), key=lambda r: -r["level"]):
        total += r["n"]
        if total > most:
            break
        cut = r["level"]
    if cut is None:
        return []
    found = words.where(level >= cut).select(F.col("word").cast("binary").alias("word"), "c").toArrow()
    return sorted(zip(map(bytes, found.column("word").to_pylist()), found.column("c").to_pylist(), strict=True), key=lambda x: (-x[1], x[0]))


def _sequences(batches: Iterator, column: int, head: Head, forms: dict) -> Iterator[list[np.ndarray]]:
    """Slots of the batches' texts, a sweep of bounded size at a time."""
    import pyarrow as pa

    held, size = [], 0
    for batch in batches:
        for v in batch.column(column).cast(pa.binary()):
            text = v.as_py() or b""
            held.append(head.read(tokens(text), forms)[1])
            size += len(text) + 64
            if size > SWEEP_BYTES:
                yield held
                held, size = [], 0
    if held:
        yield held


def _averaged(parts: DataFrame, group: int) -> DataFrame:
    """g, flat, w: averages of flat (weights of the network, as bytes) by words seen (w) of ``group`` neighbouring g each."""

    def add(table: object) -> object:
        import pyarrow as pa

        total, seen = np.zeros(SIZE), table.column("w").to_pylist()
        for x, w in zip(table.column("flat"), seen, strict=True):
            total += w * np.frombuffer(x.as_py(), dtype=np.float32)
        mean = (total / sum(seen)).astype(np.float32).tobytes()
        return pa.table({"g": pa.array([table.column("g")[0].as_py()], pa.int32()), "flat": pa.array([mean], pa.binary()), "w": [float(sum(seen))]})

    return parts.withColumn("g", F.floor(F.col("g") / group).cast("int")).groupBy("g").applyInArrow(add, parts.schema)


def train(docs: DataFrame, shared: object, begin: np.ndarray, id_col: str = "doc_id", text_col: str = "text") -> np.ndarray:
    """Weights after all rounds over the training rows; shared: broadcast of the head."""
    flat = begin
    spot = (F.shiftright(_crc(id_col), 3) * 2654435761 % 1_000_003) / F.lit(1_000_003.0)
    schema = T.StructType([T.StructField("g", T.IntegerType()), T.StructField("flat", T.BinaryType()), T.StructField("w", T.DoubleType())])
    done = 0.0
    for share in ROUNDS:
        part = docs.where(training(id_col) & (spot >= done) & (spot < (done + share if done + share < 0.999 else 2.0))).select(text_col)
        done += share

        def run(batches: Iterator, flat: np.ndarray = flat) -> Iterator:
            import pyarrow as pa
            from pyspark import TaskContext

            trainer, forms = Trainer(flat), {}
            for docs_ in _sequences(batches, 0, shared.value, forms):
                trainer.sweep(docs_)
            if trainer.seen:
                w = float(trainer.seen)
                yield pa.RecordBatch.from_arrays([pa.array([TaskContext.get().partitionId()], pa.int32()), pa.array([trainer.flat.tobytes()], pa.binary()), pa.array([w])], names=schema.names)

        means = _averaged(_averaged(part.mapInArrow(run, schema), 64), 64).collect()
        if means:
            flat = (sum(np.frombuffer(r["flat"], dtype=np.float32).astype(np.float64) * r["w"] for r in means) / sum(r["w"] for r in means)).astype(np.float32)
    return flat


def _form_totals(counts: DataFrame, own: list[bytes]) -> tuple[np.ndarray, np.ndarray]:
    """Tokens and distinct words of each class by form, over the whole table of counts."""
    schema = T.StructType([T.StructField("form", T.IntegerType()), T.StructField("n", T.LongType()), T.StructField("v", T.LongType())])
    mine = set(own)

    def run(batches: Iterator) -> Iterator:
        import pyarrow as pa

        n, v = np.zeros(FORMS, np.int64), np.zeros(FORMS, np.int64)
        for batch in batches:
            words = batch.column(0).cast(pa.binary()).to_pylist()
            ids = np.array([FORMS if not w or w in mine else form(w) - OWN for w in words], dtype=np.int64)
            n += np.bincount(ids, weights=batch.column(1).to_numpy(), minlength=FORMS + 1)[:FORMS].astype(np.int64)
            v += np.bincount(ids, minlength=FORMS + 1)[:FORMS]
        yield pa.RecordBatch.from_arrays([pa.array(np.arange(FORMS), type=pa.int32()), pa.array(n), pa.array(v)], names=["form", "n", "v"])

    total, distinct = np.zeros(FORMS), np.zeros(FORMS)
    for r in counts.select("word", "c").mapInArrow(run, schema).groupBy("form").agg(F.sum("n").alias("n"), F.sum("v").alias("v")).collect():
        total[r["form"]], distinct[r["form"]] = r["n"], r["v"]
    return total, distinct


def score(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """doc_id, held_out, n_tokens, n_known, train_tokens, base_score, score of every row."""
    counts = checkpoint(word_counts(light_batches(docs).where(training(id_col)), text_col))
    n_all, vocabulary, n_end = counts.agg(F.coalesce(F.sum("c"), F.lit(0)), F.count(F.lit(1)), F.coalesce(F.max(F.when(F.col("word") == "", F.col("c"))), F.lit(0))).first()
    frequent = head_words(counts)
    own = [w for w, _ in frequent[:OWN]]
    form_n, form_v = _form_totals(counts, own)
    # A word's share of its class by form: (c + 0.5) / (n + 0.5 (v + 1)); all unseen words are the one more.
    form_log = np.log10(form_n + 0.5 * (form_v + 1))
    c = np.array([n for _, n in frequent], dtype=np.float64)
    slots = np.array([*range(len(own)), *(form(w) for w, _ in frequent[OWN:])], dtype=np.int16)
    logs = np.log10(c + 0.5)
    share = np.where(slots < OWN, 0.0, logs - form_log[np.maximum(slots - OWN, 0)]) if len(slots) else logs
    head = Head({w: i for i, (w, _) in enumerate(frequent)}, logs, slots, share)
    spark = docs.sparkSession
    shared = spark.sparkContext.broadcast(head)
    blocks_n = np.zeros(OWN)
    blocks_n[: len(own)] = c[: len(own)]
    flat = train(docs, shared, initial(c[: len(own)], np.concatenate([blocks_n.reshape(BLOCKS, WIDTH).sum(axis=1), form_n, [n_end]])), id_col, text_col)
    whole_log = math.log10(n_all + 0.5 * (vocabulary + 1))
    end_log, end_known = math.log10(n_end + 0.5), int(n_end > 0)

    info = T.StructType([T.StructField("n_tokens", T.LongType()), T.StructField("n_known", T.LongType()), T.StructField("logs", T.DoubleType()), T.StructField("model", T.DoubleType())])
    id_type = docs.schema[id_col].dataType
    schema = T.StructType(
        [T.StructField("rid", T.LongType()), T.StructField("word", T.StringType()), T.StructField("n", T.IntegerType()), T.StructField("doc_id", id_type), T.StructField("info", info)]
    )

    def run(batches: Iterator) -> Iterator:
        """Per text one row with what the head and the network give, and one row per rare word.

        The first kind has a key with a space, which no word has: it joins nothing and is spread.
        """
        import pyarrow as pa
        from pyspark.sql.pandas.types import to_arrow_schema

        known, forms = shared.value, {}
        arrow = to_arrow_schema(schema)

        def flush(rids: object, ids: object, heads: list, rare: list, seqs: list) -> Iterator:
            network = log_likelihood(flat, seqs) / math.log(10)
            infos = [{"n_tokens": n, "n_known": k, "logs": x, "model": float(p) + m} for (n, k, x, m), p in zip(heads, network, strict=True)]
            keys = rids.to_pylist()
            n = len(keys)
            yield pa.RecordBatch.from_arrays([rids, pa.array([f" {k}" for k in keys]), pa.nulls(n, pa.int32()), ids, pa.array(infos, type=arrow.field("info").type)], schema=arrow)
            words = [w for r in rare for w in r]
            for lo in range(0, len(words), 1 << 20):
                part = slice(lo, lo + (1 << 20))
                m = len(words[part])
                rep = np.repeat(np.array(keys, dtype=np.int64), [len(r) for r in rare])[part]
                times = np.fromiter((c for r in rare for c in r.values()), dtype=np.int32, count=len(words))[part]
                yield pa.RecordBatch.from_arrays(
                    [pa.array(rep), pa.array(words[part], type=pa.binary()).cast(pa.string()), pa.array(times), pa.nulls(m, ids.type), pa.nulls(m, arrow.field("info").type)], schema=arrow
                )

        named: list = []  # (rids, ids) of the texts that are held
        heads, rare, seqs, size = [], [], [], 0
        for batch in batches:
            at = 0
            for i, v in enumerate(batch.column(2).cast(pa.binary()), 1):
                text = v.as_py() or b""
                words = tokens(text)
                numbers, slots_, unknown = known.read(words, forms)
                have = numbers[numbers >= 0] if unknown else numbers
                seqs.append(slots_)
                # Of a rare word the share of its class is all that is known here; its count comes by the join.
                lacks = float(form_log[[forms[w] - OWN for w in unknown]].sum()) if unknown else 0.0
                rare.append(Counter(unknown))
                heads.append((len(words) + 1, len(have) + end_known, float(known.logs[have].sum()) + end_log, float(known.share[have].sum()) - lacks))
                size += len(text) + 64
                if size > SWEEP_BYTES or i == batch.num_rows:
                    named.append([batch.column(c).slice(at, i - at) for c in (0, 1)])
                    at = i
                if size > SWEEP_BYTES:
                    yield from flush(*map(pa.concat_arrays, zip(*named, strict=True)), heads, rare, seqs)
                    named, heads, rare, seqs, size = [], [], [], [], 0
        if heads:
            yield from flush(*map(pa.concat_arrays, zip(*named, strict=True)), heads, rare, seqs)

    rows = docs.select(F.monotonically_increasing_id().alias("rid"), F.col(id_col).alias("doc_id"), F.col(text_col).alias("text"))
    met = rows.mapInArrow(run, schema).join(counts.withColumnRenamed("word", "w"), F.col("word") == F.col("w"), "left")
    of_rare = F.coalesce(F.sum(F.col("n") * F.log10(F.coalesce("c", F.lit(0)) + F.lit(0.5))), F.lit(0.0))
    per = met.groupBy("rid").agg(
        F.max("doc_id").alias("doc_id"),
        F.max("info.n_tokens").alias("n_tokens"),
        (F.max("info.n_known") + F.coalesce(F.sum(F.when(F.col("c").isNotNull(), F.col("n"))), F.lit(0))).alias("n_known"),
        (F.max("info.logs") + of_rare).alias("logs"),
        (F.max("info.model") + of_rare).alias("model"),
    )
    return per.select(
        "doc_id",
        (_crc("doc_id") % 5 == 1).alias("held_out"),
        "n_tokens",
        "n_known",
        F.lit(n_all).cast("long").alias("train_tokens"),
        (F.col("logs") - F.col("n_tokens") * F.lit(whole_log)).alias("base_score"),
        F.col("model").alias("score"),
    )
