"""Joins of a stream or a stored relation with an indexed relation that decide per key where to compute."""
