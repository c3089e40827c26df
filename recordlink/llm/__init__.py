"""Operators of a training-data pipeline.

Self-contained: nothing else in the library imports this subpackage, and it can be
removed without touching the record-linkage engine.
"""
