"""Queries of shapes, rewrites of them, and surrounding relational operators."""
