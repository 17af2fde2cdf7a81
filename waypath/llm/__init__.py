"""Operators of a training-data pipeline: ten methods over documents, pages and vectors.

Nothing outside this folder imports it.  ``queries.py`` holds the thin contract
queries; the other modules are the operators with their general interfaces.
"""
