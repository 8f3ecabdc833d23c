"""Matching on event streams."""
