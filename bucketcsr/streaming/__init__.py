"""Streams over growing inputs: windows, sessions, duplicates, and index batches."""
