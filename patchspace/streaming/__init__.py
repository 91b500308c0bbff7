"""Arriving queries and rasters from event streams."""
