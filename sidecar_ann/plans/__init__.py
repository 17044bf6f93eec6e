"""Pattern detection, tier choice, statements, cost models."""
