"""Operators for large text corpora: encoding, joins, filters, search, dedup, mixing."""
