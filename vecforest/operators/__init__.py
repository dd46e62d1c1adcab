"""Projection, encoding, trees, range queries and the searches built on them."""
