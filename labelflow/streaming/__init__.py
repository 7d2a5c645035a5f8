"""Sketches of event streams and incremental propagation."""
