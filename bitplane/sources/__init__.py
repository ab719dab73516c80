"""Readers and writers: plain tables, encoded datasets, data source."""
