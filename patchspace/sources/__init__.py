"""Rasters, masks and dictionaries made from the given tables, and files to keep them in."""
