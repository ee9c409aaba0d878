"""Vocabulary, mappings, query algebra and the graphs that answer it."""
