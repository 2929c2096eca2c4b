"""Hashing, positions and user-defined functions."""
