"""Bit functions, codecs, measures and SQL-visible functions."""
