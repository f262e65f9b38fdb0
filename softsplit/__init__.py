"""Soft-split boosting on Spark: gradient boosting with untrained soft splitters."""
