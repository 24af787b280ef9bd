"""Workers serve one operator after the other, and all of an executor's count towards its memory."""

import public_tokenizers

from erblock.llm import byte_bpe, common


def test_tables_stay_for_the_next_task_of_their_operator_and_go_before_another_s():
    where = public_tokenizers.path("byte_bpe_50k.tiktoken"), public_tokenizers.PATTERN
    common.settle("byte_bpe")
    first = byte_bpe.tokenizer(*where)
    ids = first.encode("a qzorbletion")
    common.settle("byte_bpe")
    assert byte_bpe.tokenizer(*where) is first and "qzorbletion" in first.chunks
    common.settle("suffix_dedup")
    assert not byte_bpe._LOADED
    common.settle("byte_bpe")
    assert byte_bpe.tokenizer(*where).encode("a qzorbletion") == ids


def test_a_worker_of_two_operators_keeps_the_tables_of_the_last_only(spark):
    def held(batches):
        import pyarrow as pa

        for _ in batches:
            pass
        yield pa.RecordBatch.from_arrays([pa.array([len(byte_bpe._LOADED)], pa.int64())], names=["n"])

    docs = spark.createDataFrame([(1, "one two " * 60)], "doc_id long, text string").coalesce(1)
    byte_bpe.digests(docs, public_tokenizers.path("byte_bpe_50k.tiktoken"), public_tokenizers.PATTERN).collect()
    from erblock.llm import suffix_dedup

    for _ in range(4):  # whichever worker of the last tasks serves these
        suffix_dedup._squeezed(docs.selectExpr("doc_id as k", "doc_id as k2", "text")).collect()
    assert spark.range(1).coalesce(1).mapInArrow(held, "n long").first().n == 0
