"""Operators over tables, each with a SQL twin, and the blocking, matching and measuring of columns."""
