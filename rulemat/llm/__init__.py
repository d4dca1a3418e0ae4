"""Corpus operators for large training-data pipelines.

Nothing outside this folder imports it; the engine in the parent package works without it.
"""
