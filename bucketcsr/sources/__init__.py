"""Stored indexes, and readers and writers of plain tables."""
