"""Part of the fuzzy multi-hop join engine."""
