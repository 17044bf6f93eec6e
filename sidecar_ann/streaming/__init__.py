"""Ingest, search and windows over streams."""
