"""Partitioning, building, merging, searching, scheduling and their measures."""
