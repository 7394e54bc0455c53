"""Verbatim-copy analytics and preference tuning on Spark."""
