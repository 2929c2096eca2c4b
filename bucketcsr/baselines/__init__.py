"""The classic tables that the index is compared with, as exact operation counts and as joins."""
