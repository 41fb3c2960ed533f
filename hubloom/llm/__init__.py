"""Corpus operators for training-data pipelines.

Nothing outside this subpackage (and ``corpus_pipeline.py``, which counts as
part of it) imports it.  ``registry`` holds the queries and their SQL.
"""
