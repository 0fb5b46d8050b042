"""Operators for preparing training text: scoring, deduplication, redaction, fingerprints and encoding.

Nothing else in the package imports this subpackage; it can be deleted as a whole.
"""
