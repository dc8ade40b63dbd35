"""Weighted frequent items over very large tables and streams, on PySpark."""
