"""Filtering over bit-plane encoded columns, written for Spark.

Columns are cut into blocks, shifted by a bias and stored as one 64-row machine
word per bit position.  Predicates against constants become a few bitwise
operations per word; the resulting row masks feed counts, sums and late fetches.
"""

__version__ = "0.1.0"
