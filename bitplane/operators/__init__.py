"""Encoding, selection, aggregation, joins and baselines."""
