"""Operators of a training-data pipeline: each module holds one of them, with its query.

Nothing outside this folder imports it.
"""
