"""Pairing, indexing, scores, relations and general operators."""
