"""Operators on relations, bitmaps, trees, candidates and rules."""
