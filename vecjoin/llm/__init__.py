"""Operators for preparing training text: deduplication, filtering, extraction, tokenising.

Nothing else in the library imports this subpackage; ``registry`` holds its driver queries.
"""
