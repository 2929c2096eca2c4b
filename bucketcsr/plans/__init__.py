"""Sizes of an index and the choice of build and probe."""
