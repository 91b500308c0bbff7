"""Patch search, exemplar fill and the measures around them, as Spark plans."""
