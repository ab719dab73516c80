"""Predicates, their kernels, and cost-based choices."""
