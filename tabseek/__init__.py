"""Keyword search over very large collections of tables, on Spark."""
