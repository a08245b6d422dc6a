"""Exact statistics of contiguous term sequences on PySpark."""
