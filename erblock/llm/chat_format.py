"""Chat formatting over a prefix tree of conversations.

A turn is written as ``<|role|>\\n text <|end|>\\n``.  Strings that steer chat templates (``<|``,
``</s>``, ``[INST]``, ``[/INST]``) are escaped in roles and texts by a backslash after their first
character; one that already stands there gets another, so the escape can be undone exactly.

Conversations that start with the same turns share them.  They are range-partitioned and sorted by
the chain of their turns' digests: that *is* the depth-first order of the tree, so one stack per
partition is all the state.  A shared turn is emitted the first time the walk meets it; each
conversation's row carries the new part, and for the whole path down to its leaf the intervals
of the packed sequence it may attend to, with their position ids and loss flags.  Equal paths are
spread by the id behind the path, so one hot opening or conversation does not fill a task.  A shard is one
packed sequence and attends to nothing outside it: a shared turn is emitted once in each shard that its
subtree reaches into, which is one but for subtrees that a boundary between shards cuts.

Units are tokens with a ``codec`` (head, text and end of a turn are encoded apart, so the loss mask lies between
tokens and a shared turn has the same tokens everywhere), else code points.  ``read_back`` needs the stored rows alone: it
puts them in order by shard and number.

Edge cases: null text or role is empty; turns are ordered by turn (null first), role, text, and repeated
rows are kept as turns; a null id is one conversation; an empty table gives an empty result; extra
columns are ignored.  One conversation must fit in a task's memory, as a training sequence.
"""

from __future__ import annotations

import hashlib
import re
from collections.abc import Callable, Iterator, Sequence
from dataclasses import dataclass

from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

_ESCAPE = re.compile(r"(<)(\\*)(?=\||/s>)|(\[)(\\*)(?=/?INST\])")
_UNESCAPE = re.compile(r"(<)\\(\\*)(?=\||/s>)|(\[)\\(\\*)(?=/?INST\])")
_TURN = re.compile(r"<\|(.*?)\|>\n(.*?)<\|end\|>\n", re.S)


def escape(text: str) -> str:
    return _ESCAPE.sub(lambda m: f"{m[1] or m[3]}\\{m[2] or m[4] or ''}", text)


def unescape(text: str) -> str:
    return _UNESCAPE.sub(lambda m: f"{m[1] or m[3]}{m[2] or m[4] or ''}", text)


def _role(role: str) -> str:
    """Roles also hide the closing mark and line ends, so that a header is one line."""
    return escape(role).replace("%", "%25").replace("|>", "%7C>").replace("\n", "%0A")


def _unrole(role: str) -> str:
    return unescape(role.replace("%0A", "\n").replace("%7C>", "|>").replace("%25", "%"))


@dataclass(frozen=True)
class Codec:
    """Tokens of a text and back; a tokenizer made in each worker by ``make`` has ``encode`` and ``decode`` (to bytes)."""

    make: Callable[[], object]

    @staticmethod
    def byte_bpe(path: str, pattern: str) -> Codec:
        from erblock.llm import byte_bpe

        return Codec(lambda: byte_bpe.tokenizer(path, pattern))


def format_turn(role: str, text: str) -> tuple[str, str, str]:
    """The turn as its head, its escaped text and its end."""
    return f"<|{_role(role)}|>\n", escape(text), "<|end|>\n"


SPAN = T.StructType(
    [T.StructField(n, T.LongType()) for n in ("start", "stop", "position")] + [T.StructField("loss_start", T.LongType()), T.StructField("loss_stop", T.LongType())]
)


def conversations_by_path(convs: DataFrame) -> DataFrame:
    """conv_id, turns (ordered), path (chained digest prefix per turn, fixed width)."""
    turns = F.sort_array(F.collect_list(F.struct("turn", F.coalesce("role", F.lit("")).alias("role"), F.coalesce("text", F.lit("")).alias("text"))))
    grouped = convs.groupBy("conv_id").agg(turns.alias("turns"))
    step = F.transform("turns", lambda t: F.substring(F.sha2(F.concat(t["role"], F.lit("\n"), t["text"]), 256), 1, 16))
    return grouped.withColumn("path", F.array_join(step, ""))


def prefix_tree(convs: DataFrame, partitions: int | None = None, loss_role: str = "assistant", codec: Codec | None = None) -> DataFrame:
    """A row per conversation, in depth-first order within its shard:

    shard, seq, conv_id, new_text (emitted here; with a codec new_ids, its tokens), new_start (its place in the shard's packed sequence),
    spans array<start, stop, position, loss_start, loss_stop>: the path from the root, a span per turn,
    with packed offsets, the position id of its first unit and the packed interval under the loss mask
    (empty where the role isn't ``loss_role``).  A unit at packed offset p inside its span attends to all spans
    before it on the path and to [start, p] of its own.
    """
    by_path = conversations_by_path(convs)
    spread = [F.col("path"), F.xxhash64("conv_id")]
    by_path = by_path.repartitionByRange(partitions, *spread) if partitions else by_path.repartitionByRange(*spread)
    ordered = by_path.sortWithinPartitions("path", "conv_id")
    schema = T.StructType(
        [
            T.StructField("shard", T.IntegerType()),
            T.StructField("seq", T.LongType()),
            T.StructField("conv_id", convs.schema["conv_id"].dataType),
            T.StructField("new_ids", T.ArrayType(T.IntegerType())) if codec else T.StructField("new_text", T.StringType()),
            T.StructField("new_start", T.LongType()),
            T.StructField("spans", T.ArrayType(SPAN)),
        ]
    )

    def run(batches: Iterator) -> Iterator:
        import pyarrow as pa
        from pyspark import TaskContext

        units: Callable[[str], Sequence] = codec.make().encode if codec else lambda x: x
        from pyspark.sql.pandas.types import to_arrow_schema

        shard, seq, end = TaskContext.get().partitionId(), 0, 0
        stack: list[tuple[tuple[str, str], dict]] = []
        arrow = to_arrow_schema(schema)
        for batch in batches:
            rows = []
            for conv_id, turns in zip(batch.column(0), batch.column(1), strict=True):
                keys = [(t["role"], t["text"]) for t in turns.as_py()]
                same = 0
                while same < len(keys) and same < len(stack) and stack[same][0] == keys[same]:
                    same += 1
                del stack[same:]
                new, start = [], end
                for key in keys[same:]:
                    pieces = [units(x) for x in format_turn(*key)]
                    a, b, size = len(pieces[0]), len(pieces[0]) + len(pieces[1]), sum(map(len, pieces))
                    at = stack[-1][1]["position"] + stack[-1][1]["stop"] - stack[-1][1]["start"] if stack else 0
                    on = key[0] == loss_role
                    stack.append((key, {"start": end, "stop": end + size, "position": at, "loss_start": end + (a if on else 0), "loss_stop": end + (b if on else 0)}))
                    end += size
                    new += pieces
                emitted = {"new_ids": [i for x in new for i in x]} if codec else {"new_text": "".join(new)}
                rows.append({"shard": shard, "seq": seq, "conv_id": conv_id.as_py(), **emitted, "new_start": start, "spans": [x for _, x in stack]})
                seq += 1
            yield pa.RecordBatch.from_pylist(rows, schema=arrow)

    return ordered.select("conv_id", "turns").mapInArrow(run, schema)


def parse(formatted: str) -> list[tuple[str, str]]:
    """(role, text) of each turn of a formatted conversation."""
    return [(_unrole(r), unescape(t)) for r, t in _TURN.findall(formatted)]


def read_back(tree: DataFrame, codec: Codec | None = None) -> DataFrame:
    """Per conversation, read from the packed output alone: its formatted string and its text under
    the loss mask.  Follows a shard's rows by their number; only the pieces on the current path are held.
    """
    emitted = "new_ids" if codec else "new_text"
    schema = T.StructType(
        [
            tree.schema["conv_id"],
            T.StructField("formatted", T.StringType()),
            T.StructField("loss_text", T.StringType()),
        ]
    )

    def run(batches: Iterator) -> Iterator:
        import pyarrow as pa
        from pyspark.sql.pandas.types import to_arrow_schema

        text_of: Callable[[Sequence], str] = (lambda decode: lambda x: decode(x).decode())(codec.make().decode) if codec else lambda x: x
        path: list[tuple[int, int, Sequence]] = []  # start, stop, units of the spans last read
        now = None
        arrow = to_arrow_schema(schema)
        for batch in batches:
            rows = []
            for shard, conv_id, new, start, spans in zip(*(batch.column(i) for i in range(5)), strict=True):
                shard, new, start, spans = shard.as_py(), new.as_py(), start.as_py(), spans.as_py()
                if shard != now:
                    path, now = [], shard
                formatted, loss = [], []
                for d, s in enumerate(spans):
                    if s["start"] >= start and s["stop"] <= start + len(new):
                        path[d:] = [(s["start"], s["stop"], new[s["start"] - start : s["stop"] - start])]
                    if d >= len(path) or path[d][:2] != (s["start"], s["stop"]):
                        raise ValueError("an interval points outside the path")
                    formatted.append(text_of(path[d][2]))
                    if s["loss_stop"] > s["loss_start"]:
                        loss.append(text_of(path[d][2][s["loss_start"] - s["start"] : s["loss_stop"] - s["start"]]))
                del path[len(spans) :]
                rows.append({"conv_id": conv_id.as_py(), "formatted": "".join(formatted), "loss_text": "".join(map(unescape, loss))})
            yield pa.RecordBatch.from_pylist(rows, schema=arrow)

    ordered = tree.repartition("shard").sortWithinPartitions("shard", "seq")
    return ordered.select("shard", "conv_id", emitted, "new_start", "spans").mapInArrow(run, schema)


def attention(spans: Sequence[dict], depth: int, place: int) -> list[tuple[int, int]]:
    """Packed intervals [start, stop) that the unit ``place`` of the span at ``depth`` attends to: its ancestors and itself."""
    return [(s["start"], s["stop"]) for s in spans[:depth]] + [(spans[depth]["start"], spans[depth]["start"] + place + 1)]


def digests(convs: DataFrame, partitions: int | None = None, codec: Codec | None = None) -> DataFrame:
    """Counts and digests per conversation of what ``read_back`` finds in the formatted output."""
    schema = T.StructType(
        [
            convs.schema["conv_id"],
            T.StructField("n_turns", T.LongType()),
            T.StructField("turns_sha256", T.StringType()),
            T.StructField("loss_chars", T.LongType()),
            T.StructField("loss_sha256", T.StringType()),
            T.StructField("formatted_chars", T.LongType()),
        ]
    )

    def run(batches: Iterator) -> Iterator:
        import pyarrow as pa
        from pyspark.sql.pandas.types import to_arrow_schema

        def sha(x: str) -> str:
            return hashlib.sha256(x.encode()).hexdigest()

        arrow = to_arrow_schema(schema)
        for batch in batches:
            rows = []
            for conv_id, formatted, loss in zip(*(batch.column(i) for i in range(3)), strict=True):
                formatted, loss = formatted.as_py(), loss.as_py()
                turns = parse(formatted)
                rows.append(
                    {
                        "conv_id": conv_id.as_py(),
                        "n_turns": len(turns),
                        "turns_sha256": sha("".join(f"{r}\n{t}\n" for r, t in turns)),
                        "loss_chars": len(loss),
                        "loss_sha256": sha(loss),
                        "formatted_chars": len(formatted),
                    }
                )
            yield pa.RecordBatch.from_pylist(rows, schema=arrow)

    return read_back(prefix_tree(convs, partitions, codec=codec), codec).mapInArrow(run, schema)
