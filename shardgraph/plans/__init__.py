"""Queries: methods end to end, experiments, and the relational surface."""
