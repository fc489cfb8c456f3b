"""Staged learned membership filters and their operators, built on PySpark."""
