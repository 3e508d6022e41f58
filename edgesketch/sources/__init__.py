"""Graphs derived from tables, generators, update streams and their files."""
