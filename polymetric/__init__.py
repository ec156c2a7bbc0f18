"""Exact similarity search over rows that mix numbers, vectors, text and dates, on Spark."""
