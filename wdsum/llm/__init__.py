"""Corpus operators: packing, deduplication, extraction, scoring and filters.

Nothing outside this subpackage imports it.
"""
