"""Snapshot-bound vector search on Spark: indexes as blobs beside a table, resolved through its log."""

__version__ = "0.1.0"
