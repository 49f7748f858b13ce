"""Partitioners, the replica engine and its programs, baselines and measures."""
