"""Compressed integer lists on Spark: differential coding, bit packing, patched codes, measures and queries."""
