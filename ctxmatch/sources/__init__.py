"""Catalogs and data: scenario schemas, metadata readers, files."""
