"""Edges from streams, windows over them, and communities that follow."""
