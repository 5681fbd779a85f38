"""Vectors, scores and the SQL functions over them."""
