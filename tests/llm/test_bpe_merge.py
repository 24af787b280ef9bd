"""The rank queue beside merging the lowest pair again and again."""

import random

import public_tokenizers

from erblock.llm import byte_bpe


def test_queue_is_empty_again_and_ids_are_those_of_plain_merging():
    bpe = byte_bpe.tokenizer(public_tokenizers.path("byte_bpe_50k.tiktoken"), public_tokenizers.PATTERN)
    r = random.Random(2)
    for _ in range(400):
        piece = bytes(r.choices(b"aabeinst \xc3\xa9", k=r.randint(1, 80)))
        parts = [piece[i : i + 1] for i in range(len(piece))]
        while found := [(bpe.ranks[a + b], i) for i, (a, b) in enumerate(zip(parts, parts[1:])) if a + b in bpe.ranks]:
            _, i = min(found)
            parts[i : i + 2] = [parts[i] + parts[i + 1]]
        if piece not in bpe.ranks:
            assert bpe.merge(piece) == tuple(bpe.ranks[x] for x in parts)
        assert not any(bpe.low)


def test_a_new_chunk_is_split_once_and_letters_not_at_all():
    """Texts have ever new words, so what a chunk costs the first time counts."""
    bpe = byte_bpe.ByteBPE.from_file(public_tokenizers.path("byte_bpe_50k.tiktoken"), public_tokenizers.PATTERN)
    split, seen = bpe.split, []
    bpe.split = lambda text: seen.append(text) or split(text)
    text = "first qzorbletion qzorbletion, don't 12ab é1,b x"
    ids = bpe.encode(text)
    assert seen == ["first", " qzorbletion,", " don't", " 12ab", " é1,b"]
    bpe.by_space = False
    assert ids == bpe.encode(text) and bpe.decode(ids) == text.encode()
