"""Continuous ingest and windows over streams."""
