"""Index builds, probes, refreshes and measures."""
