"""Operators of a training-data pipeline: one module for each.

Nothing outside this subpackage (and ``corpus_pipeline.py``) imports it.
"""
