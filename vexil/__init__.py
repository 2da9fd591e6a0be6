"""Filtered vector search on Spark: label constraints, bitmaps, indexes, tuning, workloads."""
