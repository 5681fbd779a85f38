"""Upkeep of triples and answers over streams."""
