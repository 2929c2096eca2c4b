"""Index builds, probes, joins, set operations and applications over them."""
