"""Whole methods, composed from operators."""
