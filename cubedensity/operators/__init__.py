"""Density methods, tiles, colored sets and cube operators."""
