"""The experiments and operator checks as named queries, and their SQL."""
