"""Operators of a training-data pipeline: search, quality, near and exact copies, mixing, packing, safety, language.

Nothing outside this subpackage imports it.
"""
