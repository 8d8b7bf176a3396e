"""Trajectory views of the given tables, files in and out."""
