"""Column functions on vectors and their numpy counterparts."""
