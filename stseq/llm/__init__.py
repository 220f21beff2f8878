"""Operators for preparing training corpora (language-model scoring, extraction, deduplication, packing ...).

Nothing outside this subpackage imports it; ``queries.py`` here holds its registered queries.
"""
