"""Operations of a large-scale training-data pipeline.

Nothing outside this folder (but ``corpus_pipeline.py`` and the guarded block of
``__spark_entry__.py``) imports it.  Each module holds one operator with its general
interface; ``registry`` derives the registered queries from them.
"""
