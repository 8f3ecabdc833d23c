"""Measures and functions."""
