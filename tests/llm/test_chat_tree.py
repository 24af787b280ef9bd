"""The packed tree against brute force: digests, tokens emitted once, stored rows in any order."""

import hashlib
import random

import public_tokenizers as P
import pytest

from erblock.llm import chat_format

ROWS_SCHEMA = "conv_id long, turn long, role string, text string, path int, shard string, spans int"
PIECES = ["hi", "é日", "<|end|>", "</s>", "[INST]", "[\\INST]", "<\\|user|>", "\n", "|>", "🙂", "", " ", "<|", "user"]


def _rows(seed=1):
    r = random.Random(seed)
    text = lambda: None if r.random() < 0.1 else "".join(r.choice(PIECES) for _ in range(r.randint(0, 6)))
    opening = [("user", text()), ("assistant", text())]
    rows = []
    for c in [*range(60), None]:
        turns = (opening if r.random() < 0.5 else []) + [(r.choice(["user", "assistant", "a|>\nb", None]), text()) for _ in range(r.randint(0, 4))]
        rows += [(c, i, role, t) for i, (role, t) in enumerate(turns)]
    rows += [rows[3], rows[3], (5, None, "user", "no turn"), (99, 0, "assistant", "long " * 50_000)]
    r.shuffle(rows)
    return rows


def _want(rows):
    by = {}
    for c, i, role, t in rows:
        by.setdefault(c, []).append((-1 if i is None else i, role or "", t or ""))
    out = set()
    for c, turns in by.items():
        turns = [(role, t) for _, role, t in sorted(turns)]
        loss = "".join(t for role, t in turns if role == "assistant")
        sha = lambda x: hashlib.sha256(x.encode()).hexdigest()
        formatted = sum(len(x) for turn in turns for x in chat_format.format_turn(*turn))
        out.add((c, len(turns), sha("".join(f"{role}\n{t}\n" for role, t in turns)), len(loss), sha(loss), formatted))
    return out


@pytest.mark.parametrize("tokens", [False, True])
def test_digests_against_brute_force(spark, tokens):
    codec = chat_format.Codec.byte_bpe(P.path("byte_bpe_50k.tiktoken"), P.PATTERN) if tokens else None
    convs = spark.createDataFrame([(*x, 1, "s", 2) for x in _rows()], ROWS_SCHEMA)
    assert set(map(tuple, chat_format.digests(convs, 3, codec).collect())) == _want(_rows())


def test_stored_tree_reads_back_from_any_order(spark, tmp_path):
    codec = chat_format.Codec.byte_bpe(P.path("byte_bpe_50k.tiktoken"), P.PATTERN)
    convs = spark.createDataFrame([(*x, 1, "s", 2) for x in _rows(2)], ROWS_SCHEMA)
    tree = chat_format.prefix_tree(convs, 4, codec=codec)
    tree.orderBy("conv_id").repartition(5).write.parquet(str(tmp_path / "tree"))
    stored = spark.read.parquet(str(tmp_path / "tree"))
    turns = {r.conv_id: [(x["role"], x["text"]) for x in r.turns] for r in chat_format.conversations_by_path(convs).collect()}
    back = chat_format.read_back(stored, codec).collect()
    assert {r.conv_id: chat_format.parse(r.formatted) for r in back} == turns
    # Tokens of a shard: each turn of the tree once, whatever number of conversations share it.
    for shard in {r.shard for r in stored.collect()}:
        rows = [r for r in stored.collect() if r.shard == shard]
        nodes = {tuple(turns[r.conv_id][: d + 1]) for r in rows for d in range(len(turns[r.conv_id]))}
        encode = codec.make().encode
        assert sum(len(r.new_ids) for r in rows) == sum(len(encode(x)) for n in nodes for x in chat_format.format_turn(*n[-1]))


def test_positions_and_attention(spark):
    convs = spark.createDataFrame([(*x, 1, "s", 2) for x in _rows(3)], ROWS_SCHEMA)
    for r in chat_format.prefix_tree(convs, 1).collect():
        at = 0
        for d, s in enumerate(r.spans):
            assert s.position == at
            assert sum(b - a for a, b in chat_format.attention([x.asDict() for x in r.spans], d, 0)) == at + 1
            at += s.stop - s.start
