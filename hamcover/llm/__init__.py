"""Operators of a training-data pipeline. Nothing outside this folder imports it, but for the entry module and corpus_pipeline.py."""
