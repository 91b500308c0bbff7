"""Patch, index, search, fill and measure operators over DataFrames."""
