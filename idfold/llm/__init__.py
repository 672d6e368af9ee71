"""Operations of a training-data pipeline: dedup, quality, mixing, sharding, tokens, WARC, URL rules.

Nothing outside this subpackage imports it, apart from the top-level corpus_pipeline.py and the
guarded registration in ``__spark_entry__.py``.
"""
