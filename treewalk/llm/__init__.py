"""Training-data operators: ten text and vector operators for very large corpora.

Nothing outside this subpackage imports it.  Each module documents what its operator does
with nulls, empty or very long texts, ties, repeated rows and empty tables.
"""
